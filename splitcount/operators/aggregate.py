"""Sketches as binary columns: partial building, tree merges, scalar functions and table functions.

A task first reduces its rows to (keys, j, r) in whole-stage code; only then Python packs them.  Two
forms give the same registers, and the same bytes but for the lazy variant's base: ``relational`` (maximum per
register, packed at the end) and ``partial`` (a blob per task and group, merged in rounds whose fan-in bounds
what one task holds).
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from splitcount.functions.hashing import pairs
from splitcount.operators import registers as R
from splitcount.operators.codec import Sketch, merge
from splitcount.schema import HASH_IDS, registers_of
from splitcount.session import cut


def _key_schema(df: DataFrame, keys: list[str]) -> str:
    return "".join(f"`{f.name}` {f.dataType.simpleString()}, " for f in df.schema.fields if f.name in keys)


def pack_registers(regs: DataFrame, keys: list[str], p: int, kappa: int = 3, variant: str = "opt", family: str = "md5_64", seed: int = 0) -> DataFrame:
    """(keys.., sketch) from registers in long form; a group's m registers at most reach one task."""
    registers_of(p)
    tags = {"hash_id": HASH_IDS[family], "seed": seed, "variant": variant}

    def pack(j, r) -> bytes:
        return Sketch.from_pairs(p, j, r, kappa, **tags).to_bytes()

    if not keys:
        @F.pandas_udf("binary")
        def blob(js: pd.Series, rs: pd.Series) -> pd.Series:
            return pd.Series([pack(j, r) for j, r in zip(js, rs, strict=True)])

        one = regs.agg(F.collect_list(F.struct("j", "r")).alias("_l"))  # at most m entries
        return one.select(blob(F.col("_l.j"), F.col("_l.r")).alias("sketch"))

    def group(t: pa.Table) -> pa.Table:
        head = t.select(keys).slice(0, 1)
        return head.append_column("sketch", pa.array([pack(t["j"].to_numpy(), t["r"].to_numpy())], pa.binary()))

    return regs.select(*keys, "j", "r").groupBy(*keys).applyInArrow(group, _key_schema(regs, keys) + "sketch binary")


#: Bytes of sketches that one task of a partial build holds; beyond them it gives out what it has.
_HELD = 64 << 20


def partial_sketches(df: DataFrame, keys: list[str], value, p: int, kappa: int = 3, variant: str = "opt", max_groups: int = 4096, **how) -> DataFrame:
    """(keys.., sketch): one blob per task and group; a group may come several times."""
    rows = pairs(df, keys, value, p, **how)
    tags = {"hash_id": HASH_IDS[how.get("family", "md5_64")], "seed": how.get("seed", 0), "variant": variant}
    most = max(1, min(max_groups, _HELD // registers_of(p)))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: dict = {}
        for b in batches:
            b = b.groupby([*keys, "j"], as_index=False, dropna=False)["r"].max() if keys else b.groupby("j", as_index=False)["r"].max()
            for k, g in b.groupby(keys, dropna=False) if keys else [((), b)]:
                held[k] = (held.get(k) or Sketch.empty(p, kappa, **tags)).offer_many(g["j"], g["r"])[0]
                if len(held) > most:  # a bounded table; its groups simply come again
                    yield out(held)
                    held = {}
        if held:
            yield out(held)

    def out(held: dict) -> pd.DataFrame:
        f = pd.DataFrame([list(k) for k in held], columns=keys) if keys else pd.DataFrame(index=range(len(held)))
        f["sketch"] = [s.to_bytes() for s in held.values()]
        return f

    return rows.mapInPandas(run, _key_schema(rows, keys) + "sketch binary")


def _largest(rows: DataFrame, by: list[str]) -> int:
    """Rows of the largest group; reads the keys alone."""
    return rows.groupBy(*by).agg(F.count("*").alias("n")).agg(F.max("n")).first()[0] or 0


def merge_rounds(blobs: DataFrame, keys: list[str], fan_in: int = 128, col: str = "sketch") -> Iterator[DataFrame]:
    """The written input of each round of a merge: (keys.., sketch, _id, _salt), no (keys, _salt) above ``fan_in`` rows.

    The number of salts follows from the largest group and doubles until the count of every salted group is
    within the bound, so a task never holds more than ``fan_in`` blobs of a group, however many there are.
    """
    rows = blobs.select(*keys, col)
    while True:
        rows = cut(rows.withColumn("_id", F.monotonically_increasing_id()))
        salts = -(-_largest(rows, keys) // fan_in)
        if salts <= 1:
            yield rows.withColumn("_salt", F.lit(0))
            return
        while True:
            salted = rows.withColumn("_salt", F.pmod(F.xxhash64("_id"), F.lit(salts)).cast("int"))
            if _largest(salted, [*keys, "_salt"]) <= fan_in:
                break
            salts *= 2
        yield salted
        rows = _folded(salted, [*keys, "_salt"], col).select(*keys, col)


def _folded(rows: DataFrame, names: list[str], col: str) -> DataFrame:
    def fold(t: pa.Table) -> pa.Table:
        part = [Sketch.from_bytes(x) for x in t[col].to_pylist() if x is not None]
        return t.select(names).slice(0, 1).append_column(col, pa.array([merge(part).to_bytes() if part else None], pa.binary()))

    return rows.select(*names, col).groupBy(*names).applyInArrow(fold, _key_schema(rows, names) + f"{col} binary")


def merge_sketches(blobs: DataFrame, keys: list[str], fan_in: int = 128, col: str = "sketch") -> DataFrame:
    """(keys.., sketch): one blob per group, in as many rounds as the largest group asks for.

    Null blobs count as none; sketches of different kinds are refused.
    """
    for rows in merge_rounds(blobs, keys, fan_in, col):
        last = rows
    return _folded(last, [*keys, "_salt"], col).select(*keys, col)


def distinct_sketch(df: DataFrame, keys: list[str], value, p: int = 12, kappa: int = 3, variant: str = "opt", form: str | None = None, groups: int | None = None, **how) -> DataFrame:
    """(keys.., sketch) of the distinct items of ``value``; ``form`` is relational, partial, or chosen by size.

    The choice reads the plan's size; where there are keys, ``groups`` says how many, or they are counted roughly.
    """
    from splitcount.plans.choose import choose_form, input_figures

    if (form or choose_form(p, *input_figures(df, keys, groups))) == "partial":
        return merge_sketches(partial_sketches(df, keys, value, p, kappa, variant, **how), keys)
    tags = {k: how[k] for k in ("family", "seed") if k in how}
    return pack_registers(R.build(df, keys, value, p, **how), keys, p, kappa, variant, **tags)


def rollup_sketches(blobs: DataFrame, to_keys: list[str], fan_in: int = 128) -> DataFrame:
    return merge_sketches(blobs, to_keys, fan_in)


# ------------------------------------------------------------------ functions over blobs

_REGISTER = T.StructType([T.StructField("j", T.LongType()), T.StructField("r", T.LongType()), T.StructField("is_sparse", T.BooleanType())])


@F.pandas_udf(T.DoubleType())
def sketch_estimate(blobs: pd.Series) -> pd.Series:
    return blobs.map(lambda b: None if b is None else Sketch.from_bytes(b).estimate()).astype(float)


@F.pandas_udf(T.LongType())
def sketch_bits(blobs: pd.Series) -> pd.Series:
    return blobs.map(lambda b: None if b is None else Sketch.from_bytes(b).bits).astype("Int64")


@F.pandas_udf(T.LongType())
def sketch_get(blobs: pd.Series, j: pd.Series) -> pd.Series:
    return pd.Series([None if b is None else Sketch.from_bytes(b).get(int(k)) for b, k in zip(blobs, j, strict=True)], dtype="Int64")


@F.pandas_udf(T.BinaryType())
def sketch_merge2(a: pd.Series, b: pd.Series) -> pd.Series:
    one = lambda x, y: y if x is None else x if y is None else merge([Sketch.from_bytes(x), Sketch.from_bytes(y)]).to_bytes()
    return pd.Series([one(x, y) for x, y in zip(a, b, strict=True)])


@F.pandas_udf(T.ArrayType(_REGISTER))
def sketch_registers(blobs: pd.Series) -> pd.Series:
    def rows(b):
        if b is None:
            return None
        s = Sketch.from_bytes(b)
        out = set(s.sparse_part()[0].tolist())
        return [{"j": j, "r": r, "is_sparse": j in out} for j, r in s.iter_registers()]

    return blobs.map(rows)


def explode_registers(blobs: DataFrame, keys: list[str], col: str = "sketch") -> DataFrame:
    """(keys.., j, r, is_sparse): all registers of every blob."""
    return blobs.select(*keys, F.explode(sketch_registers(col)).alias("x")).select(*keys, "x.*")



class ExplodeRegisters:
    """Table function: rows (j, r, is_sparse) of one blob."""

    def eval(self, blob: bytes):
        if blob is not None:
            s = Sketch.from_bytes(bytes(blob))
            out = set(s.sparse_part()[0].tolist())
            for j, r in s.iter_registers():
                yield j, r, j in out


def register(spark: SparkSession) -> None:
    """SQL names of the functions above."""
    for name, f in (("sketch_estimate", sketch_estimate), ("sketch_bits", sketch_bits), ("sketch_get", sketch_get), ("sketch_merge2", sketch_merge2), ("sketch_agg", sketch_agg)):
        spark.udf.register(name, f)
    spark.udtf.register("explode_registers", F.udtf(ExplodeRegisters, returnType=_REGISTER))


@F.pandas_udf(T.BinaryType())
def sketch_agg(j: pd.Series, r: pd.Series, p: pd.Series) -> bytes:
    """Aggregate of (j, r) rows into a sketch of 2**p registers; for registers, of which a group has at most 2**p."""
    return Sketch.from_pairs(int(p.iloc[0]), j, r).to_bytes()
