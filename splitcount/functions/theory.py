"""Closed forms: the law of a register, tails, size bounds, amortisation, error."""

from __future__ import annotations

from math import ceil, exp, log, log1p, log2, sqrt

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from splitcount.schema import registers_of


def cdf_column(k: Column, n: Column, p: int) -> Column:
    """P[register <= k] after n distinct items: (1 - 1/(m 2**k)) ** n, stable for huge n."""
    return F.exp(n * F.log1p(-1 / (F.lit(float(registers_of(p))) * F.pow(F.lit(2.0), k))))


def law(spark: SparkSession, n: float, p: int) -> DataFrame:
    """(k, prob, cum) for k in 0..63."""
    cum = cdf_column(F.col("k").cast("double"), F.lit(float(n)), p)
    rows = spark.range(64).select(F.col("id").alias("k")).withColumn("cum", cum)
    prev = F.coalesce(F.lag("cum").over(W.orderBy("k")), F.lit(0.0))  # 64 rows
    return rows.select("k", (F.col("cum") - prev).alias("prob"), "cum")


def cdf(n: float, p: int, k: float) -> float:
    return exp(n * log1p(-1 / (registers_of(p) * 2.0**k)))


def pmf(n: float, p: int) -> list[float]:
    c = [cdf(n, p, k) for k in range(64)]
    return [c[0], *(b - a for a, b in zip(c, c[1:], strict=False))]


def tail_bounds(delta: float) -> tuple[float, float, float]:
    """Lower tail's bound exp(-2**delta), then 2**-delta for the lower and for the upper tail."""
    return exp(-(2.0**delta)), 2.0**-delta, 2.0**-delta


def delta_all(p: int, beta: float) -> float:
    return log2(2 * registers_of(p) / beta)


def bits_all(p: int, beta: float) -> tuple[int, float]:
    """(offset bits, least n) so that every register fits with chance at least 1 - beta."""
    m = registers_of(p)
    return ceil(log2(log2(2 * m / beta))) + 1, 2 * m * m / beta


def bits_split(p: int) -> dict:
    """All but m / log m registers fit: offset bits, delta, least n, outliers, failure bound."""
    m = registers_of(p)
    d = 2 + log2(log2(m))
    return {"bits": ceil(log2(d)) + 1, "delta": d, "least_n": 4 * m * log2(m), "outliers": m / log2(m), "fails": exp(-m / (6 * log2(m)))}


def bits_deep(p: int) -> dict:
    """The same with m / log log m outliers and a narrower window."""
    m = registers_of(p)
    ll = log2(log2(m))
    d = 2 + log2(ll)
    return {"bits": ceil(log2(d)) + 1, "delta": d, "least_n": 4 * m * ll, "outliers": m / ll, "fails": exp(-m / (6 * ll))}


def chernoff(eps: float, mean: float) -> float:
    """Bound on a sum of negatively dependent 0-1 variables passing (1 + eps) times its mean."""
    return exp(-eps * eps / 3 * mean)


def size_formula(p: int, n: float) -> dict:
    """Leading terms of the asymptotic sizes, in bits."""
    m = registers_of(p)
    lll = log2(log2(log2(m)))
    return {"plain": m * log2(log2(n)), "split": m * lll + m + log2(log2(n)), "deep": m * max(0.0, log2(lll) if lll > 0 else 0.0) + m * lll / log2(log2(m)) + log2(log2(n))}


def entropy(n: float, p: int) -> float:
    """Bits per register of the law."""
    return -sum(x * log2(x) for x in pmf(n, p) if x > 0)


def window_mass(n: float, p: int, kappa: int = 3) -> tuple[int, float]:
    """(base, mass) of the likeliest window of 2**kappa values."""
    q = pmf(n, p)
    wide = 1 << kappa
    return max(((b, sum(q[b : b + wide])) for b in range(64)), key=lambda x: (x[1], -x[0]))


def expected_bits(n: float, p: int, kappa: int = 3) -> float:
    m = registers_of(p)
    return kappa * m + (p + 6) * m * (1 - window_mass(n, p, kappa)[1])


def amortised(n: float, p: int, gamma: float = 1.0) -> dict:
    """Compress calls and work stay below these; ``constant`` where updates are amortised constant."""
    m, k = registers_of(p), log2(gamma * n)
    return {"calls": k * m, "work": k * k * m * m, "constant": n / log2(n) ** 2 > m * m}


def rse(p: int) -> float:
    return 1.04 / sqrt(registers_of(p))


def succinct_bits(s: float, universe: float) -> float:
    """A succinct dictionary of s out of ``universe`` keys, without its linear term."""
    return s * log2(universe / s) if s else 0.0


def linear_count(m: int, zeros: int) -> float:
    return m * log(m / zeros)


def outliers(hist: DataFrame, counts: DataFrame, keys: list[str], p: int, delta: float) -> DataFrame:
    """(keys.., below, above, outliers): registers outside (log2(n/m) - delta, log2(n/m) + delta)."""
    m = registers_of(p)
    centre = F.log2(F.col("n") / F.lit(float(m)))
    joined = hist.join(counts.select(*keys, "n"), keys) if keys else hist.crossJoin(F.broadcast(counts.select("n")))
    low = F.sum(F.when(F.col("r") <= centre - delta, F.col("c")).otherwise(0)).cast("long")
    high = F.sum(F.when(F.col("r") >= centre + delta, F.col("c")).otherwise(0)).cast("long")
    got = joined.groupBy(*keys, "n").agg(low.alias("below"), high.alias("above"))
    return got.select(*keys, "n", "below", "above", (F.col("below") + F.col("above")).alias("outliers"))


def covariance(reps: DataFrame, rep: str = "rep") -> DataFrame:
    """(cov) of two registers' outlier flags (x, y) over repetitions, for the negative-dependence check."""
    return reps.agg(F.covar_samp("x", "y").alias("cov"), (F.avg("x") * F.avg("y")).alias("product"), F.avg(F.col("x") * F.col("y")).alias("joint"))
