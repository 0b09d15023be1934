"""The public surface: DataFrames in, DataFrames out, lazily."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from splitcount.measures import compare_variants
from splitcount.operators import estimate as _estimate
from splitcount.operators import registers as _registers
from splitcount.operators.aggregate import distinct_sketch, explode_registers, merge_sketches, rollup_sketches, sketch_bits, sketch_estimate, sketch_get, sketch_merge2
from splitcount.sources.store import SketchStore
from splitcount.streaming.panes import tumbling_registers
from splitcount.workloads import profile

__all__ = [
    "SketchStore",
    "approx_distinct",
    "compare_variants",
    "distinct_registers",
    "distinct_sketch",
    "estimate",
    "explode_registers",
    "merge_sketches",
    "overlap",
    "profile",
    "rollup_sketches",
    "sketch_bits",
    "sketch_estimate",
    "sketch_get",
    "sketch_merge2",
    "stream_sketch",
]


def distinct_registers(df: DataFrame, keys: list[str], value: Column | str, p: int = 12, **how) -> DataFrame:
    return _registers.build(df, keys, value, p, **how)


def estimate(regs: DataFrame, keys: list[str], p: int = 12, **how) -> DataFrame:
    return _estimate.from_registers(regs, keys, p, **how)


def approx_distinct(df: DataFrame, keys: list[str], value: Column | str, p: int = 12, **how) -> DataFrame:
    """(keys.., est): the approximate counterpart of count(distinct value)."""
    return estimate(distinct_registers(df, keys, value, p, **how), keys, p).select(*keys, "est")


def overlap(a: DataFrame, b: DataFrame, p: int = 12) -> DataFrame:
    """(est_a, est_b, union_est, inter_est, jaccard) of two register tables (j, r); only the union is exact in registers."""
    one = lambda x, name: estimate(x, [], p).select(F.col("est").alias(name))
    rows = one(a, "est_a").crossJoin(one(b, "est_b")).crossJoin(one(_registers.merge(a, b, []), "union_est"))  # one row each
    inter = F.greatest(F.lit(0.0), F.col("est_a") + F.col("est_b") - F.col("union_est"))
    return rows.withColumn("inter_est", inter).withColumn("jaccard", F.when(F.col("union_est") > 0, inter / F.col("union_est")).otherwise(0.0))


def stream_sketch(df: DataFrame, keys: list[str], value: str, window: str, watermark: str, p: int = 12, ts: str = "ts") -> DataFrame:
    """Streaming registers per tumbling window; merge them with ``streaming.panes.sliding`` for longer windows."""
    return tumbling_registers(df, keys, value, p, window, watermark, ts)
