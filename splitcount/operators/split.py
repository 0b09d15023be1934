"""Split sketches over DataFrames: a shared base, narrow offsets, and a sparse rest.

Registers in [base, base + 2**kappa) are dense offsets; all others are sparse (j, r) entries.  Choosing
the base reads the histogram of register values, at most 64 rows per group, never the registers.
"""

from __future__ import annotations

from math import log2

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from splitcount.operators import registers as R
from splitcount.schema import check_kappa, registers_of


def histogram(regs: DataFrame, keys: list[str], p: int) -> DataFrame:
    """(keys.., r, c): how many registers hold each value; zero included where any register is zero."""
    m = registers_of(p)
    seen = regs.groupBy(*keys, "r").agg(F.count("*").alias("c"))
    # An empty global sketch still has m registers at zero.
    zeros = seen.groupBy(*keys).agg((F.lit(m) - F.coalesce(F.sum("c"), F.lit(0))).cast("long").alias("c"))
    zeros = zeros.where("c > 0").select(*keys, F.lit(0).cast("long").alias("r"), "c")
    return seen.select(*keys, "r", "c").unionByName(zeros)


def split_bits(sparse: Column, p: int, kappa: int, w: int = 64) -> Column:
    return (F.lit(kappa * registers_of(p)) + sparse * F.lit(p + int(log2(w)))).cast("long")


def _ranked(cand: DataFrame, keys: list[str], p: int, kappa: int, how: str) -> DataFrame:
    """The candidate with most dense registers, the smallest on ties."""
    m = registers_of(p)
    if how == "maxby":
        best = cand.groupBy(*keys).agg(F.max_by(F.struct("b", "dense"), F.struct("dense", -F.col("b"))).alias("x"))
        best = best.select(*keys, "x.b", "x.dense")
    else:
        order = W.partitionBy(*keys).orderBy(F.desc("dense"), "b")
        best = cand.withColumn("_n", F.row_number().over(order)).where("_n = 1").select(*keys, "b", "dense")
    sparse = (F.lit(m) - F.col("dense")).cast("long")
    return best.select(*keys, "b", F.col("dense").cast("long").alias("dense"), sparse.alias("sparse"), split_bits(sparse, p, kappa).alias("bits"))


def best_base(hist: DataFrame, keys: list[str], p: int, kappa: int = 3, how: str = "window") -> DataFrame:
    """(keys.., b, dense, sparse, bits) of the optimal split; bases are existing register values.

    ``how`` picks the plan: ``window`` (a sliding frame), ``theta`` (range self-join), ``maxby``
    (struct maximum over the frame), ``rownum`` (counts dealt to the bases that hold them).  All give the same rows.
    """
    check_kappa(kappa)
    wide = (1 << kappa) - 1
    if how == "theta":
        a, b = hist.alias("a"), hist.alias("b")
        on = [F.col(f"a.{k}") == F.col(f"b.{k}") for k in keys]
        cond = F.col("b.r").between(F.col("a.r"), F.col("a.r") + wide)
        for x in on:
            cond = cond & x
        cand = a.join(b, cond).groupBy(*(F.col(f"a.{k}").alias(k) for k in keys), F.col("a.r").alias("b")).agg(F.sum("b.c").alias("dense"))
    elif how == "rownum":
        # Each value counts for the bases whose window holds it; bases are values that some register has.
        spread = hist.select(*keys, "c", F.explode(F.sequence(F.col("r") - wide, F.col("r"))).alias("b"), "r")
        cand = spread.groupBy(*keys, "b").agg(F.sum("c").alias("dense"), F.min("r").alias("_r")).where("b = _r").drop("_r")
    else:
        frame = W.partitionBy(*keys).orderBy("r").rangeBetween(0, wide)
        cand = hist.select(*keys, F.col("r").alias("b"), F.sum("c").over(frame).alias("dense"))
    return _ranked(cand, keys, p, kappa, how)


def base_at(hist: DataFrame, bases: DataFrame, keys: list[str], p: int, kappa: int = 3) -> DataFrame:
    """(keys.., b, dense, sparse, bits) for given bases (keys.., b)."""
    check_kappa(kappa)
    inside = F.col("r").between(F.col("b"), F.col("b") + ((1 << kappa) - 1))
    joined = hist.join(bases.select(*keys, "b"), keys) if keys else hist.crossJoin(F.broadcast(bases.select("b")))
    dense = F.coalesce(F.sum(F.when(inside, F.col("c"))), F.lit(0)).cast("long")
    got = joined.groupBy(*keys, "b").agg(dense.alias("dense"))
    sparse = (F.lit(registers_of(p)) - F.col("dense")).cast("long")
    return got.select(*keys, "b", "dense", sparse.alias("sparse"), split_bits(sparse, p, kappa).alias("bits"))


def min_base(hist: DataFrame, keys: list[str]) -> DataFrame:
    """(keys.., b, c_min): the smallest register value and how many registers hold it."""
    return hist.groupBy(*keys).agg(F.min("r").alias("b"), F.min_by("c", "r").alias("c_min"))


def next_base(hist: DataFrame, keys: list[str]) -> DataFrame:
    """(keys.., b, next_b): every register value and the next larger one, null for the largest."""
    ahead = F.lead("r").over(W.partitionBy(*keys).orderBy("r"))
    return hist.select(*keys, F.col("r").alias("b"), ahead.alias("next_b"))


def lazy_step(hist: DataFrame, bases: DataFrame, keys: list[str], p: int, kappa: int = 3) -> DataFrame:
    """One step of the cheap rule: the next larger register value, if it takes strictly fewer bits."""
    nexts = bases.select(*keys, "b").join(next_base(hist, keys), [*keys, "b"], "left")
    now = base_at(hist, bases, keys, p, kappa).select(*keys, F.col("bits").alias("bits_now"))
    then = base_at(hist, nexts.where("next_b is not null").select(*keys, F.col("next_b").alias("b")), keys, p, kappa)
    then = then.select(*keys, F.col("b").alias("_b2"), F.col("bits").alias("_bits2"))
    joined = nexts.join(now, keys).join(then, keys, "left") if keys else nexts.crossJoin(F.broadcast(now)).join(F.broadcast(then), F.lit(True), "left")
    moved = F.coalesce(F.col("_bits2") < F.col("bits_now"), F.lit(False))
    return joined.select(*keys, F.when(moved, F.col("_b2")).otherwise(F.col("b")).alias("b"), F.when(moved, F.col("_bits2")).otherwise(F.col("bits_now")).alias("bits"), moved.alias("moved"))


def early_bound(hist: DataFrame, keys: list[str], p: int, kappa: int = 3) -> DataFrame:
    """(keys.., b, below, sparse): registers under a candidate bound its sparse count from below."""
    part = W.partitionBy(*keys).orderBy("r")
    below = F.coalesce(F.sum("c").over(part.rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).cast("long")
    dense = F.sum("c").over(part.rangeBetween(0, (1 << kappa) - 1))
    return hist.select(*keys, F.col("r").alias("b"), below.alias("below"), (F.lit(registers_of(p)) - dense).cast("long").alias("sparse"))


def _with_base(regs: DataFrame, base: DataFrame, keys: list[str]) -> DataFrame:
    if not keys:
        return regs.crossJoin(F.broadcast(base.select("b")))  # one row
    return regs.join(base.select(*keys, "b"), keys)


def with_zeros(regs: DataFrame, keys: list[str], p: int) -> DataFrame:
    """All m registers per group, zeros included."""
    m = registers_of(p)
    groups = regs.groupBy(*keys).agg(F.lit(1).alias("_one")) if keys else regs.sparkSession.range(1).select(F.lit(1).alias("_one"))
    every = groups.select(*keys, F.explode(F.sequence(F.lit(0).cast("long"), F.lit(m - 1).cast("long"))).alias("j"))
    return every.join(regs, [*keys, "j"], "left").select(*keys, "j", F.coalesce("r", F.lit(0)).cast("long").alias("r"))


def split(regs: DataFrame, base: DataFrame, keys: list[str], p: int, kappa: int = 3, zeros: bool = True) -> DataFrame:
    """(keys.., j, r, b, off): off is the dense offset, null for sparse registers."""
    every = with_zeros(regs, keys, p) if zeros else regs
    based = _with_base(every, base, keys)
    inside = (F.col("r") >= F.col("b")) & (F.col("r") < F.col("b") + (1 << check_kappa(kappa)))
    return based.select(*keys, "j", "r", "b", F.when(inside, F.col("r") - F.col("b")).alias("off"))


def dense_part(parts: DataFrame, keys: list[str]) -> DataFrame:
    return parts.where("off is not null").select(*keys, "j", "off")


def sparse_part(parts: DataFrame, keys: list[str]) -> DataFrame:
    """(keys.., j, r, packed): packed holds the index above the low six bits of the value."""
    return parts.where("off is null").select(*keys, "j", "r", F.shiftleft("j", 6).bitwiseOR(F.col("r")).alias("packed"))


def get(dense: DataFrame, sparse: DataFrame, base: DataFrame, keys: list[str]) -> DataFrame:
    """(keys.., j, r): the sparse value where there is one, else base plus offset."""
    d = _with_base(dense, base, keys).select(*keys, "j", (F.col("b") + F.col("off")).alias("_d"))
    s = sparse.select(*keys, "j", F.col("r").alias("_s"))
    return d.join(s, [*keys, "j"], "full_outer").select(*keys, "j", F.coalesce("_s", "_d").alias("r"))


def rebase_moves(hist: DataFrame, base: DataFrame, keys: list[str], shift: int = 1, kappa: int = 3) -> DataFrame:
    """(keys.., to_sparse, to_dense): registers that change sides when the base moves by ``shift``."""
    wide = 1 << check_kappa(kappa)
    h = _with_base(hist, base, keys)
    was = (F.col("r") >= F.col("b")) & (F.col("r") < F.col("b") + wide)
    now = (F.col("r") >= F.col("b") + shift) & (F.col("r") < F.col("b") + shift + wide)
    total = lambda cond: F.coalesce(F.sum(F.when(cond, F.col("c"))), F.lit(0)).cast("long")
    return h.groupBy(*keys).agg(total(was & ~now).alias("to_sparse"), total(now & ~was).alias("to_dense"))


def merge_split(a: DataFrame, b: DataFrame, keys: list[str], p: int, kappa: int = 3) -> DataFrame:
    """(keys.., b_start, b, dense, sparse, bits): merged registers, from the larger base to the optimal one."""
    base = lambda x: best_base(histogram(x, keys, p), keys, p, kappa).select(*keys, "b")
    both = base(a).unionByName(base(b))
    start = both.groupBy(*keys).agg(F.max("b").alias("b_start"))
    merged = best_base(histogram(R.merge(a, b, keys), keys, p), keys, p, kappa)
    return start.join(merged, keys) if keys else F.broadcast(start).crossJoin(merged)


def theory_base(n: float, p: int) -> int:
    """The base that the analysis uses, with the true count known."""
    return max(0, round(log2(max(n, 1) / registers_of(p))))


# ------------------------------------------------------------------ many sizes at once: p is a column


def histograms(regs: DataFrame) -> DataFrame:
    """(p, r, c) from registers (p, j, r) of several sizes; zero included where any register is zero."""
    seen = regs.groupBy("p", "r").agg(F.count("*").alias("c"))
    zeros = seen.groupBy("p").agg((F.pow(F.lit(2.0), F.first("p")).cast("long") - F.sum("c")).alias("c")).where("c > 0")
    return seen.unionByName(zeros.select("p", F.lit(0).cast("long").alias("r"), "c"))


def windows(hist: DataFrame, keys: list[str], kappa: int = 3) -> DataFrame:
    """(keys.., b, here, sparse): for base 0 and every register value, its registers and those outside its window."""
    order = W.partitionBy(*keys).orderBy("r")
    rows = hist.select(*keys, "r", "c").unionByName(hist.select(*keys).distinct().select(*keys, F.lit(0).cast("long").alias("r"), F.lit(0).cast("long").alias("c")))
    rows = rows.groupBy(*keys, "r").agg(F.sum("c").alias("c"))
    inside = F.sum("c").over(order.rangeBetween(0, (1 << kappa) - 1))
    total = F.sum("c").over(W.partitionBy(*keys))
    return rows.withColumn("_in", inside).withColumn("_all", total).select(*keys, F.col("r").alias("b"), F.col("c").alias("here"), (F.col("_all") - F.col("_in")).alias("sparse"))


def widest(windows: DataFrame, keys: list[str]) -> DataFrame:
    """(keys.., b, sparse): the base with the fewest sparse registers, the smallest on ties."""
    best = windows.where("here > 0").groupBy(*keys).agg(F.min(F.struct("sparse", "b")).alias("x"))
    return best.select(*keys, "x.b", "x.sparse")


def lowest(windows: DataFrame, keys: list[str]) -> DataFrame:
    """(keys.., b, sparse): the smallest register as base."""
    return windows.where("here > 0").groupBy(*keys).agg(F.min(F.struct("b", "sparse")).alias("x")).select(*keys, "x.b", "x.sparse")


def climbed(windows: DataFrame, keys: list[str]) -> DataFrame:
    """(keys.., b, sparse): from base 0 to the next register value as long as that makes the sparse part smaller."""
    order = W.partitionBy(*keys).orderBy("b")
    steps = windows.withColumn("_stop", F.coalesce(F.col("sparse") >= F.lag("sparse").over(order), F.lit(False)))
    steps = steps.withColumn("_stopped", F.max("_stop").over(order)).where("not _stopped")
    return steps.groupBy(*keys).agg(F.max(F.struct("b", "sparse")).alias("x")).select(*keys, "x.b", "x.sparse")
