"""Sketch tables at rest: Parquet partitioned by pane, merged on write, read by range and as-of.

An upsert replaces whole panes: the new sketches of a pane merge with those stored, and the pane's
partition is overwritten.  Merging is idempotent, so a replayed batch changes nothing.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from splitcount.operators.aggregate import merge_sketches
from splitcount.session import cut


@dataclass
class SketchStore:
    """Rows (pane DATE, keys.., sketch BINARY) below ``path``."""

    spark: SparkSession
    path: str
    keys: tuple[str, ...] = ()

    def exists(self) -> bool:
        p = self.spark._jvm.org.apache.hadoop.fs.Path(self.path)
        fs = p.getFileSystem(self.spark._jsc.hadoopConfiguration())
        return fs.exists(p) and any(s.isDirectory() and s.getPath().getName().startswith("pane=") for s in fs.listStatus(p))

    def read(self, start: str | None = None, end: str | None = None) -> DataFrame:
        """Stored sketches; bounds on the pane prune partitions."""
        rows = self.spark.read.parquet(self.path)
        if start is not None:
            rows = rows.where(F.col("pane") >= F.lit(start).cast("date"))
        if end is not None:
            rows = rows.where(F.col("pane") <= F.lit(end).cast("date"))
        return rows

    def upsert(self, sketches: DataFrame) -> None:
        """Merge (pane, keys.., sketch) into the store; only the panes that occur are rewritten."""
        cols = ["pane", *self.keys, "sketch"]
        new = cut(sketches.select(*cols))
        if self.exists():
            panes = new.select("pane").distinct()
            old = self.read().select(*cols).join(F.broadcast(panes), "pane", "left_semi") if panes.count() <= 10_000 else self.read().select(*cols).join(panes, "pane", "left_semi")
            new = new.unionByName(old)
        merged = cut(merge_sketches(new, ["pane", *self.keys]))
        merged.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("pane").parquet(self.path)

    def validate(self) -> DataFrame:
        """(keys.., kinds): groups whose stored sketches differ in registers, hash or seed; empty if all is well."""
        head = F.concat(F.substring("sketch", 2, 1), F.substring("sketch", 5, 1), F.substring("sketch", 9, 8))
        return self.read().groupBy(*self.keys).agg(F.count_distinct(head).alias("kinds")).where("kinds > 1")

    def asof(self, day: str) -> DataFrame:
        """(keys.., pane, sketch): the latest pane at or before ``day`` per key."""
        return self.read(end=day).groupBy(*self.keys).agg(F.max_by(F.struct("pane", "sketch"), "pane").alias("x")).select(*self.keys, "x.*")


FORMATS = ("parquet", "orc", "json", "csv", "text")


def save(sketches: DataFrame, path: str, fmt: str = "parquet") -> None:
    """Write a sketch table; text formats carry the blob as base64."""
    if fmt in ("parquet", "orc"):
        sketches.write.mode("overwrite").format(fmt).save(path)
        return
    coded = sketches.withColumn("sketch", F.regexp_replace(F.base64("sketch"), r"\s", ""))  # line breaks would end a row
    if fmt == "text":
        coded.select(F.to_json(F.struct("*")).alias("value")).write.mode("overwrite").text(path)
    else:
        coded.write.mode("overwrite").format(fmt).option("header", fmt == "csv").save(path)


def load(spark: SparkSession, path: str, schema: str, fmt: str = "parquet") -> DataFrame:
    """Read a sketch table that :func:`save` wrote; ``schema`` gives the columns with ``sketch binary``."""
    if fmt in ("parquet", "orc"):
        return spark.read.format(fmt).schema(schema).load(path)
    coded = schema.replace("sketch binary", "sketch string")
    if fmt == "text":
        rows = spark.read.text(path).select(F.from_json("value", coded).alias("x")).select("x.*")
    else:
        rows = spark.read.format(fmt).schema(coded).option("header", fmt == "csv").load(path)
    return rows.withColumn("sketch", F.unbase64("sketch"))
