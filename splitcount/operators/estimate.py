"""Cardinality estimates from histograms or registers: harmonic, with its two branches, and relatives."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from splitcount.schema import registers_of

#: Bias corrections of the harmonic estimate.
_ALPHA = {16: 0.673, 32: 0.697, 64: 0.709}


def alpha(p: int) -> float:
    m = registers_of(p)
    return _ALPHA.get(m, 0.7213 / (1 + 1.079 / m))


def moments(hist: DataFrame, keys: list[str]) -> DataFrame:
    """(keys.., s, v): the sum of 2**-r over all registers, and the number of zero registers."""
    return hist.groupBy(*keys).agg(
        F.sum(F.col("c") * F.pow(F.lit(2.0), -F.col("r"))).alias("s"),
        F.coalesce(F.sum(F.when(F.col("r") == 0, F.col("c"))), F.lit(0)).cast("long").alias("v"),
    )


def raw(p: int, s: Column | str = "s") -> Column:
    m = registers_of(p)
    return F.lit(alpha(p) * m * m) / (F.col(s) if isinstance(s, str) else s)


def small_range(p: int, v: Column | str = "v") -> Column:
    m = registers_of(p)
    return F.lit(float(m)) * F.log(F.lit(float(m)) / (F.col(v) if isinstance(v, str) else v))


def large_range(e: Column, bits: int = 32) -> Column:
    top = 2.0**bits
    return F.lit(-top) * F.log(1 - e / top)


def branch(p: int, range_bits: int | None = 64, e: Column | None = None, v: str = "v") -> Column:
    """Which formula applies: small, large or raw."""
    m = registers_of(p)
    e = raw(p) if e is None else e
    out = F.when((e <= 2.5 * m) & (F.col(v) > 0), "small")
    if range_bits:
        out = out.when(e > 2.0**range_bits / 30, "large")
    return out.otherwise("raw")


def piecewise(p: int, range_bits: int | None = 64) -> Column:
    """The full estimate over columns s and v; ``range_bits`` picks the large-range constant."""
    e, which = raw(p), branch(p, range_bits)
    out = F.when(which == "small", small_range(p))
    if range_bits:
        out = out.when(which == "large", large_range(e, range_bits))
    return out.otherwise(e)


def from_hist(hist: DataFrame, keys: list[str], p: int, estimator: str = "classic", range_bits: int | None = 64) -> DataFrame:
    """(keys.., v, est), est unrounded."""
    m = moments(hist, keys)
    if estimator == "classic":
        est = piecewise(p, range_bits)
    elif estimator == "raw":
        est = raw(p)
    elif estimator == "linear":
        est = F.when(F.col("v") > 0, small_range(p))
    elif estimator == "mle":
        return likelihood(hist, keys, p)
    elif estimator == "improved":
        return improved(hist, keys, p)
    else:
        raise ValueError(f"unknown estimator {estimator}")
    return m.select(*keys, "v", est.alias("est"))


def from_registers(regs: DataFrame, keys: list[str], p: int, **how) -> DataFrame:
    from splitcount.operators.split import histogram

    return from_hist(histogram(regs, keys, p), keys, p, **how)


#: Terms of the zero-register series; the rest is below the last bit of a double up to 2**18 registers.
_TERMS = 25


def improved(hist: DataFrame, keys: list[str], p: int) -> DataFrame:
    """(keys.., v, est) by the corrected harmonic sum: one formula over all ranges, without branches or bias tables.

    Zero registers enter as the limit of the same sum for ranks below one: x + sum over k of x^(2^k) 2^(k-1) at the
    share x of zero registers.
    """
    m = registers_of(p)
    got = hist.groupBy(*keys).agg(
        F.sum(F.when(F.col("r") > 0, F.col("c") * F.pow(F.lit(2.0), -F.col("r"))).otherwise(0.0)).alias("s"),
        F.coalesce(F.sum(F.when(F.col("r") == 0, F.col("c"))), F.lit(0)).cast("long").alias("v"),
    )
    x = F.col("v") / F.lit(float(m))
    zeros = x + sum((F.pow(x, F.lit(2.0**k)) * F.lit(2.0 ** (k - 1)) for k in range(1, _TERMS + 1)), F.lit(0.0))
    from math import log

    est = F.when(F.col("v") == m, 0.0).otherwise(F.lit(m * m / (2 * log(2))) / (F.lit(float(m)) * zeros + F.col("s")))
    return got.select(*keys, "v", est.alias("est"))


def likelihood_of(values: dict[int, int], p: int) -> float:
    """Maximum-likelihood count from {register value: registers}, by bisection on the score.

    Under the Poisson form of the register law a register is at most k with chance exp(-n / (m 2**k)).
    """
    from math import exp, expm1

    m = registers_of(p)
    if values.get(0, 0) == m:
        return 0.0

    def score(n: float) -> float:
        out = 0.0
        for k, c in values.items():
            low = 1 / (m * 2.0**k)
            # d/dn log P: an exact zero register gives -1/m; others the difference of two exponentials.
            if k == 0:
                out -= c / m
                continue
            gap = low  # 1/(m 2**(k-1)) - 1/(m 2**k)
            x = n * gap
            out += c * (-low + (gap * exp(-x) / -expm1(-x) if x > 0 else float("inf")))
        return out

    lo, hi = 1e-9, float(m) * 2.0 ** (max(values) + 4)
    for _ in range(200):
        mid = (lo * hi) ** 0.5
        if score(mid) > 0:
            lo = mid
        else:
            hi = mid
        if hi / lo < 1 + 1e-12:
            break
    return (lo * hi) ** 0.5


def likelihood(hist: DataFrame, keys: list[str], p: int) -> DataFrame:
    """(keys.., v, est) by maximum likelihood; an Arrow function over at most 64 entries per group."""
    @F.pandas_udf("double")
    def solve(col: pd.Series) -> pd.Series:
        return col.map(lambda es: likelihood_of({int(e["r"]): int(e["c"]) for e in es}, p))

    packed = hist.groupBy(*keys).agg(
        F.collect_list(F.struct("r", "c")).alias("h"), F.coalesce(F.sum(F.when(F.col("r") == 0, F.col("c"))), F.lit(0)).cast("long").alias("v")
    )
    return packed.select(*keys, "v", solve("h").alias("est"))
