"""Accuracy measures: relative error, its spread over repetitions, equality of lossless forms."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from splitcount.functions.theory import rse
from splitcount.operators import estimate as E
from splitcount.operators import registers as R
from splitcount.operators.baselines import exact


def relative_error(df: DataFrame, keys: list[str], value: str, p: int, **how) -> DataFrame:
    """(keys.., n, est, rel_err, within_5_rse): estimates against exact counts."""
    est = E.from_registers(R.build(df, keys, value, p, **how), keys, p).select(*keys, F.round("est", 4).alias("est"))
    rel = F.col("est") / F.col("n") - 1
    return est.join(exact(df, keys, value), keys).select(*keys, "n", "est", F.round(rel, 6).alias("rel_err"), (F.abs(rel) <= 5 * rse(p)).alias("within_5_rse"))


def spread(spark: SparkSession, n: int, p: int, seeds: int = 30) -> DataFrame:
    """(mean_err, rmse, rse) over ``seeds`` repetitions of n distinct items, all in one job."""
    items = spark.range(n).crossJoin(F.broadcast(spark.range(seeds).select(F.col("id").alias("rep"))))  # fan-out by repetition
    mixed = F.xxhash64(F.col("rep"), F.col("id"))
    regs = R.build(items, ["rep"], mixed, p, family="xx64")
    est = E.from_registers(regs, ["rep"], p)
    err = F.col("est") / F.lit(float(n)) - 1
    return est.agg(F.avg(err).alias("mean_err"), F.sqrt(F.avg(err * err)).alias("rmse")).withColumn("rse", F.lit(rse(p)))


def same_estimate(a: DataFrame, b: DataFrame, keys: list[str]) -> DataFrame:
    """(max_diff): largest difference between two tables of estimates."""
    both = a.join(b.withColumnRenamed("est", "_est2"), keys, "full_outer")
    return both.agg(F.max(F.abs(F.col("est") - F.coalesce("_est2", F.lit(float("inf"))))).alias("max_diff"))
