"""The corpus pipeline: toxicity, repeated lines, near-duplicates, secrets, packing.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return the columns of
the documents they were given.  ``run`` writes each stage's result to the shared folder and reads it again
as the next stage's documents.

Defined results: null texts pass every stage, as there is nothing to judge or to compare, and are packed as
empty texts; of texts left without a word one stays; an empty table stays empty.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from splitcount.llm import bestfit_packing, line_dedup, near_copies, secret_scan, toxicity
from splitcount.llm.common import cut, held_out, table


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that score below 0.3; the model learns from the labelled documents of ``sf_dir``."""
    model = toxicity.fit(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), ~held_out("doc_id"))
    return docs.where(F.col("text").isNull() | (toxicity.score_column(docs, model) < 0.3))


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Later copies of repeated lines leave the texts; all documents stay."""
    return line_dedup.dedup_lines(docs)


def keep_one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The row with the smallest id of each class of near copies: 5-word similarity of 0.8 or more."""
    return near_copies.keep_one(docs)


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secret values in the texts become marks; all documents stay."""
    clean = secret_scan.redacted(docs)
    return docs.select(*(clean.alias(c) if c == "text" else F.col(f"`{c}`") for c in docs.columns))


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row per piece with its sequence and place."""
    return bestfit_packing.pack(docs)


STAGES = [
    ("toxicity", drop_toxic),
    ("line_dedup", drop_repeated_lines),
    ("simhash_dedup", keep_one_of_each_group),
    ("secret_scan", redact_secrets),
    ("bestfit_packing", pack_sequences),
]

#: The stages' models and searches cannot be said in SQL; tests hold each stage against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
