"""Register sketches in long form: (keys.., j, r), registers at zero absent.

Building is one partial and one final maximum per (keys, j): a task sends at most groups x m rows
whatever it reads, and a key that a third of all rows share costs no more than any other.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from splitcount.functions.hashing import pairs
from splitcount.schema import registers_of


def build(df: DataFrame, keys: list[str], value: Column | str, p: int = 10, **how) -> DataFrame:
    """Registers of the items of ``value`` per key; updates are idempotent and in any order."""
    return from_pairs(pairs(df, keys, value, p, **how), keys)


def from_pairs(rows: DataFrame, keys: list[str]) -> DataFrame:
    """Registers of raw (j, r) pairs, without hashing."""
    return rows.groupBy(*keys, "j").agg(F.max("r").alias("r"))


def merge(a: DataFrame, b: DataFrame, keys: list[str]) -> DataFrame:
    """Element-wise maximum as a union and one aggregation."""
    cols = [*keys, "j", "r"]
    return from_pairs(a.select(*cols).unionByName(b.select(*cols)), keys)


def merge_join(a: DataFrame, b: DataFrame, keys: list[str], hint: str | None = None) -> DataFrame:
    """The same as a full outer join on (keys, j); ``hint`` names a join strategy."""
    right = b.select(*keys, "j", F.col("r").alias("r2"))
    right = right.hint(hint) if hint else right
    joined = a.select(*keys, "j", "r").join(right, [*keys, "j"], "full_outer")
    return joined.select(*keys, "j", F.greatest("r", "r2").alias("r"))


def rollup(regs: DataFrame, to_keys: list[str]) -> DataFrame:
    """Registers of coarser groups from those of finer ones."""
    return from_pairs(regs, to_keys)


def fold(regs: DataFrame, keys: list[str], p_from: int, p_to: int) -> DataFrame:
    """Registers with fewer index bits; valid for the ``fib`` index, whose top bits nest."""
    registers_of(p_from)
    registers_of(p_to)
    if p_to > p_from:
        raise ValueError("a sketch folds to fewer registers only")
    return from_pairs(regs.select(*keys, F.shiftright("j", p_from - p_to).alias("j"), "r"), keys)


def to_array(regs: DataFrame, keys: list[str], p: int) -> DataFrame:
    """(keys.., regs): dense array of m bytes' worth of small numbers per group."""
    m = registers_of(p)
    seen = F.map_from_entries(F.collect_list(F.struct("j", "r")))
    per = regs.groupBy(*keys).agg(seen.alias("_m"))
    dense = F.transform(F.sequence(F.lit(0).cast("long"), F.lit(m - 1).cast("long")), lambda j: F.coalesce(F.try_element_at("_m", j), F.lit(0)).cast("tinyint"))
    return per.select(*keys, dense.alias("regs"))


def from_array(arrays: DataFrame, keys: list[str], col: str = "regs") -> DataFrame:
    out = arrays.select(*keys, F.posexplode(col).alias("j", "r"))
    return out.where("r > 0").select(*keys, F.col("j").cast("long").alias("j"), F.col("r").cast("long").alias("r"))


def merge_arrays(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: F.greatest(x, y))


def early_reject(rows: DataFrame, regs: DataFrame, keys: list[str], p: int) -> DataFrame:
    """Pairs that can still change a sketch: those above the smallest register of their group."""
    m = registers_of(p)
    low = regs.groupBy(*keys).agg(F.when(F.count("*") < m, 0).otherwise(F.min("r")).alias("_low"))
    if not keys:
        return rows.crossJoin(F.broadcast(low)).where("r > _low").drop("_low")  # one row
    return rows.join(low, keys, "left").where(F.col("r") > F.coalesce("_low", F.lit(0))).drop("_low")


def changed(rows: DataFrame, keys: list[str], order: str) -> DataFrame:
    """(keys.., n_changed, n_total): updates in ``order`` that raise a register."""
    from pyspark.sql import Window as W

    before = F.max("r").over(W.partitionBy(*keys, "j").orderBy(order).rowsBetween(W.unboundedPreceding, -1))
    marked = rows.withColumn("_up", (F.col("r") > F.coalesce(before, F.lit(0))).cast("long"))
    return marked.groupBy(*keys).agg(F.sum("_up").alias("n_changed"), F.count("*").alias("n_total"))
