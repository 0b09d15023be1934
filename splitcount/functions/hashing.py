"""Items to (j, r) pairs inside whole-stage code: canonical form, 64-bit hash, index and rank.

A 64-bit hash is carried as two longs ``hi`` and ``lo`` of 32 bits each, since longs are signed and
arithmetic that passes 2**63 is an error.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from splitcount.schema import MAX_RANK, registers_of

_M32 = 0xFFFFFFFF
_M16 = 0xFFFF
#: Fixed value: the 64-bit golden-ratio multiplier, as two 32-bit halves.
GOLDEN_HI, GOLDEN_LO = 0x9E3779B9, 0x7F4A7C15
FAMILIES = ("md5_64", "xx64", "mix64", "sha_64")
INDEXES = ("fib", "second", "prefix")


def canon(col: Column | str, dtype: T.DataType | None = None, cents: bool = False) -> Column:
    """Text form of an item, the same for equal items whatever engine reads them; null stays null."""
    c = F.col(col) if isinstance(col, str) else col
    if cents or isinstance(dtype, (T.DecimalType, T.DoubleType, T.FloatType)):
        return F.round(c * 100).cast("long").cast("string")
    if isinstance(dtype, T.BooleanType):
        return F.when(c, "1").when(~c, "0")
    if isinstance(dtype, (T.TimestampType, T.TimestampNTZType, T.DateType)):
        return F.unix_micros(c.cast("timestamp")).cast("string")
    if isinstance(dtype, (T.ArrayType, T.MapType, T.StructType)):
        return F.to_json(c)
    if isinstance(dtype, T.DayTimeIntervalType):
        return F.try_divide(c.cast("interval second").cast("decimal(20,6)") * 1_000_000, F.lit(1)).cast("long").cast("string")
    return c.cast("string")


def joined_key(*cols: Column | str) -> Column:
    """One item from several columns; null if any is null."""
    return F.concat(*(x for c in cols for x in (F.lit(chr(31)), (F.col(c) if isinstance(c, str) else c).cast("string"))))


def _mul_low(a: Column, k: int) -> Column:
    """Low 32 bits of a * k for 32-bit a and k."""
    high = F.shiftright(a, 16) * F.lit(k)
    return (a.bitwiseAND(_M16) * F.lit(k) + F.shiftleft(high.bitwiseAND(_M16), 16)).bitwiseAND(_M32)


def _mul_high(a: Column, k: int) -> Column:
    """High 32 bits of the 64-bit product a * k for 32-bit a and k."""
    return F.shiftright(F.shiftright(a, 16) * F.lit(k) + F.shiftright(a.bitwiseAND(_M16) * F.lit(k), 16), 16)


def mul64(hi: Column, lo: Column, k: int) -> tuple[Column, Column]:
    """(hi, lo) of the product with the 64-bit constant k, modulo 2**64."""
    kh, kl = k >> 32, k & _M32
    top = (_mul_low(hi, kl) + _mul_low(lo, kh) + _mul_high(lo, kl)).bitwiseAND(_M32)
    return top, _mul_low(lo, kl)


def _xorshift(hi: Column, lo: Column, n: int) -> tuple[Column, Column]:
    """h ^ (h >> n) for 0 < n < 32."""
    low = F.shiftright(lo, n).bitwiseOR(F.shiftleft(hi, 32 - n).bitwiseAND(_M32))
    return hi.bitwiseXOR(F.shiftright(hi, n)), lo.bitwiseXOR(low)


def _hex_halves(h: Column) -> tuple[Column, Column]:
    part = lambda at: F.conv(F.substring(h, at, 8), 16, 10).cast("long")
    return part(1), part(9)


def with_hash(df: DataFrame, value: Column, family: str = "md5_64", seed: int = 0, hi: str = "hi", lo: str = "lo") -> DataFrame:
    """Adds the two halves of the item's hash.  The hash itself sits in a projection of its own, so it is computed once."""
    if family in ("md5_64", "sha_64"):
        text = value.cast("string") if not seed else F.concat(F.lit(f"{seed}:"), value.cast("string"))
        h = F.md5(text.cast("binary")) if family == "md5_64" else F.sha2(text.cast("binary"), 256)
        a, b = _hex_halves(F.col("_h"))
        return df.withColumn("_h", h).withColumns({hi: a, lo: b}).drop("_h")
    if family == "xx64":
        halves = F.shiftrightunsigned("_h", 32), F.col("_h").bitwiseAND(_M32)
        h = F.when(value.isNotNull(), F.xxhash64(F.lit(seed), value))
        return df.withColumn("_h", h).withColumns({hi: halves[0], lo: halves[1]}).drop("_h")
    if family == "mix64":
        v = value.cast("long").bitwiseXOR(F.lit(seed))
        a, b = F.shiftrightunsigned(v, 32), v.bitwiseAND(_M32)
        df = df.withColumns({hi: a, lo: b})
        # Three rounds of shift-xor and multiply; fixed values: published mixing multipliers.
        for n, k in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
            df = df.withColumns(dict(zip((hi, lo), _xorshift(F.col(hi), F.col(lo), n), strict=True)))
            df = df.withColumns(dict(zip((hi, lo), mul64(F.col(hi), F.col(lo), k), strict=True)))
        return df.withColumns(dict(zip((hi, lo), _xorshift(F.col(hi), F.col(lo), 31), strict=True)))
    raise ValueError(f"unknown hash family {family}")


def rank(hi: Column | str = "hi", lo: Column | str = "lo") -> Column:
    """Place of the first one-bit, from 1; at most 63, also where no bit is set."""
    hi = F.col(hi) if isinstance(hi, str) else hi
    lo = F.col(lo) if isinstance(lo, str) else lo
    r = F.when(hi > 0, 33 - F.length(F.bin(hi))).otherwise(F.least(F.lit(MAX_RANK), 65 - F.length(F.bin(lo))))
    return r.cast("long")


def fib_index(p: int, hi: Column | str = "hi", lo: Column | str = "lo") -> Column:
    """Top p bits of hash times the golden-ratio constant, modulo 2**64."""
    registers_of(p)
    hi = F.col(hi) if isinstance(hi, str) else hi
    lo = F.col(lo) if isinstance(lo, str) else lo
    top = (_mul_low(hi, GOLDEN_LO) + _mul_low(lo, GOLDEN_HI) + _mul_high(lo, GOLDEN_LO)).bitwiseAND(_M32)
    return F.shiftright(top, 32 - p)


def prefix_index(p: int, w: int = 64, hi: Column | str = "hi", lo: Column | str = "lo") -> tuple[Column, Column]:
    """(j, r) from one hash: its first p bits, and the rank of the remaining w - p bits."""
    registers_of(p)
    hi = F.col(hi) if isinstance(hi, str) else hi
    lo = F.col(lo) if isinstance(lo, str) else lo
    j = F.shiftright(hi, 32 - p)
    rest = hi.bitwiseAND((1 << (32 - p)) - 1)
    first = 33 - p - F.length(F.bin(rest))
    if w == 32:
        return j, F.when(rest > 0, first).otherwise(33 - p).cast("long")
    second = F.when(lo > 0, 65 - p - F.length(F.bin(lo))).otherwise(65 - p)
    return j, F.least(F.lit(MAX_RANK), F.when(rest > 0, first).otherwise(second)).cast("long")


def pairs(df: DataFrame, keys: list[str], value: Column | str, p: int = 10, family: str = "md5_64", seed: int = 0, index: str = "fib", w: int = 64) -> DataFrame:
    """(keys.., j, r) per row with an item; rows whose item is null drop out, as count(distinct) does.

    Only the keys and the item's column are read.  ``index`` is ``fib`` (from the same hash), ``second``
    (a hash of its own) or ``prefix`` (the hash's first bits).
    """
    registers_of(p)
    v = F.col(value) if isinstance(value, str) else value
    src = df.select(*keys, v.alias("_v")).where(F.col("_v").isNotNull())
    src = with_hash(src, F.col("_v"), family, seed)
    if index == "fib":
        j, r = fib_index(p), rank()
    elif index == "second":
        src = with_hash(src, F.col("_v"), family, seed + 1, "hi2", "lo2")
        j, r = F.shiftright("hi2", 32 - p), rank()
    elif index == "prefix":
        j, r = prefix_index(p, w)
    else:
        raise ValueError(f"unknown index rule {index}")
    if w == 32 and index != "prefix":
        r = F.when(F.col("hi") > 0, 33 - F.length(F.bin("hi"))).otherwise(33).cast("long")
    return src.select(*keys, j.alias("j"), r.alias("r"))
