"""Counting methods to compare with: exact, plain and coded register sketches, buckets, bit matrices,
smallest hashes, averages of registers, lossy offsets, and the built-in aggregates."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

from splitcount.functions.hashing import with_hash
from splitcount.operators import estimate as E
from splitcount.operators.rivals import HEADER_BITS, BitMatrix
from splitcount.operators.split import histogram
from splitcount.schema import registers_of
from splitcount.session import cut

#: Published constants of the averaged and bit-matrix estimates.
LOGLOG_CONSTANT = 0.39701
BITMATRIX_CONSTANT = 0.77351
#: Calibrated here by simulation of the register law for a kept share of 0.7.
SUPERLOGLOG_CONSTANT = 0.7645


def exact(df: DataFrame, keys: list[str], value: Column | str) -> DataFrame:
    """(keys.., n): all distinct items, aggregated in two steps so that no group gathers in one task."""
    v = F.col(value) if isinstance(value, str) else value
    return df.select(*keys, v.alias("_v")).where(F.col("_v").isNotNull()).distinct().groupBy(*keys).agg(F.count("*").alias("n"))


def reg6(regs: DataFrame, keys: list[str], p: int) -> DataFrame:
    """Plain sketch with six-bit cells: estimate and bits."""
    return E.from_registers(regs, keys, p).select(*keys, "est", F.lit(6 * registers_of(p)).cast("long").alias("bits"))


def builtin_improved(df: DataFrame, keys: list[str], value: str, rsd: float = 0.05) -> DataFrame:
    """The engine's own improved register sketch (64-bit hash, bias tables)."""
    return df.groupBy(*keys).agg(F.approx_count_distinct(value, rsd).alias("est"))


def builtin_sketch(df: DataFrame, keys: list[str], value: str, lg_k: int = 12) -> DataFrame:
    """The engine's own library sketch with byte-sized cells: estimate and serialised bits."""
    got = df.groupBy(*keys).agg(F.hll_sketch_agg(value, F.lit(lg_k)).alias("_s"))
    return got.select(*keys, F.hll_sketch_estimate("_s").alias("est"), (8 * F.length("_s")).cast("long").alias("bits"))


def builtin_theta(df: DataFrame, keys: list[str], value: str, lg_k: int = 12) -> DataFrame:
    """The engine's own smallest-hash sketch."""
    got = df.groupBy(*keys).agg(F.theta_sketch_agg(value, F.lit(lg_k)).alias("_s"))
    return got.select(*keys, F.theta_sketch_estimate("_s").alias("est"))


def linear_counting(rows: DataFrame, keys: list[str], p: int) -> DataFrame:
    """Occupied buckets only, from (j, r) pairs; null where every bucket is full."""
    m = registers_of(p)
    used = rows.select(*keys, "j").distinct().groupBy(*keys).agg(F.count("*").alias("_u"))
    return used.select(*keys, F.when(F.col("_u") < m, F.lit(float(m)) * F.log(F.lit(float(m)) / (m - F.col("_u")))).alias("est"))


def loglog(hist: DataFrame, keys: list[str], p: int) -> DataFrame:
    """Geometric-mean estimate over all registers."""
    m = registers_of(p)
    mean = F.sum(F.col("c") * F.col("r")) / F.lit(float(m))
    return hist.groupBy(*keys).agg((F.lit(LOGLOG_CONSTANT * m) * F.pow(F.lit(2.0), mean)).alias("est"))


def super_loglog(hist: DataFrame, keys: list[str], p: int, theta: float = 0.7) -> DataFrame:
    """The same over the smallest share of the registers, read off the histogram."""
    m = registers_of(p)
    keep = int(theta * m)
    before = F.coalesce(F.sum("c").over(W.partitionBy(*keys).orderBy("r").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    used = F.greatest(F.lit(0), F.least(F.col("c"), keep - F.col("_before")))
    got = hist.withColumn("_before", before).groupBy(*keys).agg((F.sum(F.col("r") * used) / F.lit(float(keep))).alias("_mean"))
    return got.select(*keys, (F.lit(SUPERLOGLOG_CONSTANT * m) * F.pow(F.lit(2.0), F.col("_mean"))).alias("est"))


def bit_rows(rows: DataFrame, keys: list[str]) -> DataFrame:
    """(keys.., j, bits): which ranks each substream has seen."""
    return rows.groupBy(*keys, "j").agg(F.bit_or(F.expr("shiftleft(1L, cast(r - 1 as int))")).alias("bits"))


def bitmatrix(rows: DataFrame, keys: list[str], p: int) -> DataFrame:
    """Mean place of the lowest unseen rank over all m substreams."""
    m = registers_of(p)
    place = F.bit_count(F.expr("bits ^ (bits + 1)")) - 1
    got = bit_rows(rows, keys).groupBy(*keys).agg((F.sum(place) / F.lit(float(m))).alias("_mean"))
    return got.select(*keys, (F.lit(m / BITMATRIX_CONSTANT) * F.pow(F.lit(2.0), F.col("_mean"))).alias("est"))


def bitmatrix_coded(rows: DataFrame, keys: list[str], p: int) -> DataFrame:
    """(keys.., est, bits): the bit matrix at its column entropy, estimated from its ones; :func:`matrix_blobs` codes it.

    The estimate inverts the expected number of ones; bits are m times the summed column entropies.
    """
    m = registers_of(p)
    bits = bit_rows(rows, keys)
    cells = bits.select(*keys, F.explode(F.sequence(F.lit(1), F.lit(63))).alias("k"), "bits").where(F.expr("getbit(bits, k - 1) = 1"))
    cols = cells.groupBy(*keys, "k").agg((F.count("*") / F.lit(float(m))).alias("f"))
    h = F.when((F.col("f") <= 0) | (F.col("f") >= 1), 0.0).otherwise(-F.col("f") * F.log2("f") - (1 - F.col("f")) * F.log2(1 - F.col("f")))
    got = cols.groupBy(*keys).agg((F.sum("f") * m).alias("_ones"), (F.sum(h) * m).alias("bits"))

    @F.pandas_udf("double")
    def solve(ones: pd.Series) -> pd.Series:
        return ones.map(lambda x: ones_to_count(x, m))

    return got.select(*keys, solve("_ones").alias("est"), "bits")


def ones_to_count(ones: float, m: int) -> float:
    """Count whose expected number of ones in the bit matrix is ``ones``."""
    from math import exp

    lo, hi = 1e-6, 2.0**60
    for _ in range(200):
        mid = (lo * hi) ** 0.5
        if sum(m * (1 - exp(-mid / (m * 2.0**k))) for k in range(1, 64)) < ones:
            lo = mid
        else:
            hi = mid
    return (lo * hi) ** 0.5


def kmin(df: DataFrame, keys: list[str], value: Column | str, k: int = 256) -> DataFrame:
    """(k - 1) over the k-th smallest hash in (0, 1); the exact count where there are fewer than k.

    Each (key, salt) keeps its k smallest before the final ranking, so no group gathers in one task.
    """
    v = F.col(value) if isinstance(value, str) else value
    src = df.select(*keys, v.alias("_v")).where(F.col("_v").isNotNull())
    # Fifty-two leading bits divide exactly in a double.
    h = with_hash(src, F.col("_v")).select(*keys, (F.col("hi") * (1 << 20) + F.shiftright("lo", 12)).alias("h")).distinct()
    salted = W.partitionBy(*keys, "_salt").orderBy("h")
    part = h.withColumn("_salt", F.pmod(F.xxhash64("h"), F.lit(64))).withColumn("_n", F.row_number().over(salted)).where(F.col("_n") <= k)
    top = part.withColumn("_n", F.row_number().over(W.partitionBy(*keys).orderBy("h"))).where(F.col("_n") <= k)
    got = top.groupBy(*keys).agg(F.count("*").alias("_c"), F.max("h").alias("_k"))
    est = F.when(F.col("_c") < k, F.col("_c").cast("double")).otherwise(F.lit((k - 1) * 2.0**52) / F.col("_k"))
    return got.select(*keys, est.alias("est"))


def tailcut(hist: DataFrame, keys: list[str], p: int, kappa: int = 3) -> DataFrame:
    """Lossy offsets: values above the smallest base's window are cut to its last value."""
    top = (1 << kappa) - 1
    low = F.min("r").over(W.partitionBy(*keys))
    cut = hist.withColumn("_b", low).select(*keys, (F.col("_b") + F.least(F.col("r") - F.col("_b"), F.lit(top))).alias("r"), "c")
    return E.from_hist(cut, keys, p).select(*keys, "est", F.lit(kappa * registers_of(p)).cast("long").alias("bits"))


def raising(rows: DataFrame, order: str) -> DataFrame:
    """(order, j, b, r): the rows of an ordered stream that raise a register, and what it held before.

    Only the first row of each (j, r) can raise one, so at most 64 m rows are left before anything is ordered.
    """
    firsts = rows.groupBy("j", "r").agg(F.min(order).alias(order))
    before = F.coalesce(F.max("r").over(W.partitionBy("j").orderBy(order).rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    return firsts.withColumn("b", before).where("r > b").select(order, "j", "b", "r")


def martingale(rows: DataFrame, p: int, order: str) -> DataFrame:
    """(est): a sequential estimator that cannot be merged: each raised register adds the inverse chance of a change.

    Meant for one ordered stream.  The chance falls by a known amount with every raise, so its course is a running
    sum over the raising rows, taken range by range.
    """
    m = registers_of(p)
    fall = (F.pow(F.lit(2.0), -F.col("b")) - F.pow(F.lit(2.0), -F.col("r"))) / F.lit(float(m))
    ups = running_sum(raising(rows, order).select(order, fall.alias("fall")), [order], "fall")
    return ups.agg(F.coalesce(F.sum(1 / (1 - F.col("before"))), F.lit(0.0)).alias("est"))


def running_sum(df: DataFrame, order: list[str], value: str) -> DataFrame:
    """``df`` with ``before``: the sum of ``value`` over all earlier rows, without a task that sees them all.

    Rows are sorted by ranges and written once; a range's own running sum is a window over that range, and what all
    earlier ranges hold is one number for each, joined by broadcast.
    """
    rows = cut(df.orderBy(*order).withColumn("_g", F.monotonically_increasing_id()))
    rows = rows.withColumn("_part", F.shiftright("_g", 33))
    sums = rows.groupBy("_part").agg(F.sum(value).alias("_s"))
    # As many rows as ranges.
    offsets = sums.select("_part", F.coalesce(F.sum("_s").over(W.orderBy("_part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("_o"))
    own = F.coalesce(F.sum(value).over(W.partitionBy("_part").orderBy("_g").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    return rows.withColumn("_own", own).join(F.broadcast(offsets), "_part").withColumn("before", F.col("_o") + F.col("_own")).drop("_g", "_part", "_s", "_o", "_own")


def reg8(regs: DataFrame, keys: list[str], p: int) -> DataFrame:
    """Library form with a byte for each register: estimate and bits."""
    return E.from_registers(regs, keys, p).select(*keys, "est", F.lit(8 * registers_of(p)).cast("long").alias("bits"))


def reg6_library(regs: DataFrame, keys: list[str], p: int) -> DataFrame:
    """Library form with six-bit cells behind a header: estimate and bits."""
    return E.from_registers(regs, keys, p).select(*keys, "est", F.lit(6 * registers_of(p) + HEADER_BITS).cast("long").alias("bits"))


def reg4(regs: DataFrame, keys: list[str], p: int) -> DataFrame:
    """Library form with four-bit offsets from the smallest register, the top code marking an exception: estimate and bits."""
    h = histogram(regs, keys, p)
    low = F.min("r").over(W.partitionBy(*keys))
    over = F.sum(F.when(F.col("r") - F.col("_b") >= 15, F.col("c")).otherwise(0)).cast("long")
    got = h.withColumn("_b", low).groupBy(*keys).agg(over.alias("exceptions"), F.sum(F.col("c") * F.pow(F.lit(2.0), -F.col("r"))).alias("s"), F.coalesce(F.sum(F.when(F.col("r") == 0, F.col("c"))), F.lit(0)).alias("v"))
    return got.select(*keys, "exceptions", (F.lit(4 * registers_of(p)) + F.col("exceptions") * (p + 6)).cast("long").alias("bits"), E.piecewise(p).alias("est"))


def matrix_blobs(rows: DataFrame, keys: list[str], p: int) -> DataFrame:
    """(keys.., matrix): the coded bit matrix of each group, from its at most m words."""

    @F.pandas_udf("binary")
    def code(words: pd.Series) -> pd.Series:
        def one(entries) -> bytes:
            x = BitMatrix(p)
            for e in entries:
                x.rows[e["j"]] = e["bits"]
            return x.to_bytes()

        return words.map(one)

    return bit_rows(rows, keys).groupBy(*keys).agg(F.collect_list(F.struct("j", "bits")).alias("_w")).select(*keys, code("_w").alias("matrix"))


@F.pandas_udf(T.StructType([T.StructField("est", T.DoubleType()), T.StructField("bits", T.LongType()), T.StructField("ones", T.LongType())]))
def matrix_read(blobs: pd.Series) -> pd.DataFrame:
    """Estimate, coded bits and ones of a coded bit matrix."""
    got = [BitMatrix.from_bytes(b) for b in blobs]
    return pd.DataFrame({"est": [x.estimate() for x in got], "bits": [x.bits for x in got], "ones": [x.ones for x in got]})


@F.pandas_udf(T.BinaryType())
def matrix_merge2(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([BitMatrix.from_bytes(x).merge(BitMatrix.from_bytes(y)).to_bytes() for x, y in zip(a, b, strict=True)])
