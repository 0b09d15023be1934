"""Closed forms against measured histograms."""

from __future__ import annotations

from pyspark.sql import functions as F

from splitcount import workloads
from splitcount.functions import theory as T
from splitcount.operators import estimate as E
from splitcount.operators import split as S
from splitcount.operators.baselines import exact
from splitcount.queries.methods import G, hist_of
from splitcount.queries.registry import ALL_P, P, query, src, src_sql, with_base, with_hist, with_sized
from splitcount.session import cut

_M = 1 << P
_N = f"n as (select g, count(distinct v) as n from ({src_sql('cents')}) group by g)"
_LAW = f"""{_N}, k as (select cast(k as bigint) as k from range(64) t(k)),
cum as (select k, n, exp(n * ln(1 - 1 / ({float(_M)!r} * pow(2.0, k)))) as cum from k, n),
law as (select k, n, cum - coalesce(lag(cum) over (order by k), 0) as prob, cum from cum)"""


def _law(spark, d):
    """The law at the exact count, as columns; one broadcast row carries the count."""
    from pyspark.sql import Window as W

    n = exact(src(spark, d, "cents"), G, "v").select("n")
    rows = spark.range(64).select(F.col("id").alias("k")).crossJoin(F.broadcast(n))
    rows = rows.withColumn("cum", T.cdf_column(F.col("k").cast("double"), F.col("n").cast("double"), P))
    return rows.withColumn("prob", F.col("cum") - F.coalesce(F.lag("cum").over(W.orderBy("k")), F.lit(0.0)))  # 64 rows


@query("q_law_pmf", f"with {_LAW} select k, round(prob, 6) as prob, round(cum, 6) as cum from law")
def law_pmf(spark, d):
    return _law(spark, d).select("k", F.round("prob", 6).alias("prob"), F.round("cum", 6).alias("cum"))


@query("q_law_vs_hist", f"with {_LAW}, {with_hist(src_sql('cents'))} select k, round(prob, 6) as prob, round(coalesce(c, 0) / {float(_M)!r}, 6) as observed from law left join hist on law.k = hist.r")
def law_vs_hist(spark, d):
    h = hist_of(spark, d, "cents").select(F.col("r").alias("k"), "c")
    got = _law(spark, d).join(h, "k", "left")
    return got.select("k", F.round("prob", 6).alias("prob"), F.round(F.coalesce("c", F.lit(0)) / float(_M), 6).alias("observed"))


@query("q_law_distance", f"with {_LAW}, {with_hist(src_sql('cents'))} select round(sum(abs(prob - coalesce(c, 0) / {float(_M)!r})) / 2, 6) as total_variation from law left join hist on law.k = hist.r")
def law_distance(spark, d):
    h = hist_of(spark, d, "cents").select(F.col("r").alias("k"), "c")
    got = _law(spark, d).join(h, "k", "left")
    return got.agg(F.round(F.sum(F.abs(F.col("prob") - F.coalesce("c", F.lit(0)) / float(_M))) / 2, 6).alias("total_variation"))


@query(
    "q_expected_bits",
    f"""with {_LAW}, mass as (select a.k, sum(b.prob) as mass from law a join law b on b.k between a.k and a.k + 7 group by a.k), {with_base(src_sql('cents'))}
select round(3072 + 16384 * (1 - (select max(mass) from mass)), 4) as expected, bits as measured from base""",
)
def expected_bits(spark, d):
    from pyspark.sql import Window as W

    mass = _law(spark, d).select(F.sum("prob").over(W.orderBy("k").rangeBetween(0, 7)).alias("mass")).agg(F.max("mass").alias("mass"))  # 64 rows
    base = S.best_base(hist_of(spark, d, "cents"), G, P)
    return base.crossJoin(F.broadcast(mass)).select(F.round(3072 + 16384 * (1 - F.col("mass")), 4).alias("expected"), F.col("bits").alias("measured"))


@query("q_entropy_law", f"with {_LAW} select round(sum(case when prob > 0 then -prob * log2(prob) else 0 end), 4) as per_register from law")
def entropy_law(spark, d):
    x = F.col("prob")
    return _law(spark, d).agg(F.round(F.sum(F.when(x > 0, -x * F.log2(x)).otherwise(0.0)), 4).alias("per_register"))


def _outlier_sql(delta: float, bound: float) -> str:
    return f"""with {with_hist(src_sql('cents'))}, {_N}
select n, cast(sum(case when r <= log2(n / {float(_M)!r}) - {delta!r} then c else 0 end) as bigint) as below,
       cast(sum(case when r >= log2(n / {float(_M)!r}) + {delta!r} then c else 0 end) as bigint) as above,
       round(cast({bound!r} as double), 6) as bound,
       sum(case when r <= log2(n / {float(_M)!r}) - {delta!r} or r >= log2(n / {float(_M)!r}) + {delta!r} then c else 0 end) <= {bound!r} as ok
from hist join n using (g) group by n"""


def _outliers(spark, d, delta, bound):
    n = exact(src(spark, d, "cents"), G, "v")
    got = T.outliers(hist_of(spark, d, "cents"), n, G, P, delta)
    return got.select("n", "below", "above", F.round(F.lit(bound), 6).alias("bound"), (F.col("outliers") <= bound).alias("ok"))


_SPLIT, _DEEP = T.bits_split(P), T.bits_deep(P)


@query("q_split_outliers", _outlier_sql(_SPLIT["delta"], _SPLIT["outliers"]))
def split_outliers(spark, d):
    return _outliers(spark, d, _SPLIT["delta"], _SPLIT["outliers"])


@query("q_deep_outliers", _outlier_sql(_DEEP["delta"], _DEEP["outliers"]))
def deep_outliers(spark, d):
    return _outliers(spark, d, _DEEP["delta"], _DEEP["outliers"])


_TAILS = " union all ".join(f"select cast({x!r} as double) as delta" for x in (1.0, 2.0, 3.0, 4.0))


@query(
    "q_tail_bounds",
    f"""with {with_hist(src_sql('cents'))}, {_N}, d as ({_TAILS})
select delta, round(sum(case when r < log2(n / {float(_M)!r}) - delta then c else 0 end) / {float(_M)!r}, 6) as below,
       round(sum(case when r > log2(n / {float(_M)!r}) + delta then c else 0 end) / {float(_M)!r}, 6) as above,
       round(exp(-pow(2.0, delta)), 6) as below_bound, round(pow(2.0, -delta), 6) as above_bound
from hist join n using (g), d group by delta""",
)
def tail_bounds(spark, d):
    n = exact(src(spark, d, "cents"), G, "v")
    deltas = F.broadcast(spark.createDataFrame([(float(x),) for x in range(1, 5)], "delta double"))
    h = hist_of(spark, d, "cents").join(n, G).crossJoin(deltas)
    centre = F.log2(F.col("n") / float(_M))
    part = lambda cond: F.round(F.sum(F.when(cond, F.col("c")).otherwise(0)) / float(_M), 6)
    got = h.groupBy("delta").agg(part(F.col("r") < centre - F.col("delta")).alias("below"), part(F.col("r") > centre + F.col("delta")).alias("above"))
    return got.select("delta", "below", "above", F.round(F.exp(-F.pow(F.lit(2.0), "delta")), 6).alias("below_bound"), F.round(F.pow(F.lit(2.0), -F.col("delta")), 6).alias("above_bound"))


@query("q_amortised_bound", f"with {_N} select n, round(log2(n) * {_M}, 4) as calls, round(log2(n) * log2(n) * {_M * _M}, 4) as work, n / (log2(n) * log2(n)) > {_M * _M} as constant from n")
def amortised_bound(spark, d):
    n = exact(src(spark, d, "cents"), G, "v").select("n")
    lg = F.log2("n")
    return n.select("n", F.round(lg * _M, 4).alias("calls"), F.round(lg * lg * (_M * _M), 4).alias("work"), (F.col("n") / (lg * lg) > _M * _M).alias("constant"))


def _count(spark, d):
    """(n): distinct items of the table column, one row."""
    return F.broadcast(exact(src(spark, d, "cents"), G, "v").select("n"))


_SIZED = with_sized(src_sql("cents"))


@query(
    "q_rse",
    f"""with {_SIZED}, s as (select p, m, am, sum(pow(2.0, -r)) + (m - count(*)) as s, m - count(*) as v from sized group by p, m, am),
e as (select p, m, case when am / s <= 2.5 * m and v > 0 then m * ln(m / v) else am / s end as est from s)
select cast(p as bigint) as p, round(1.04 / sqrt(m), 6) as rse, n, round(est, 4) as est, round(est / n - 1, 6) as error from e, n""",
)
def rse(spark, d):
    """The law's relative error for every p, beside the error of the column's sketch of that size."""
    regs = cut(workloads.sized(src(spark, d, "cents")))
    out = None
    for p in ALL_P:
        one = E.from_registers(regs.where(F.col("p") == p).select("j", "r"), [], p).select(F.lit(p).cast("long").alias("p"), "est")
        out = one if out is None else out.unionByName(one)
    got = out.crossJoin(_count(spark, d))
    return got.select("p", F.round(1.04 / F.sqrt(F.pow(F.lit(2.0), "p")), 6).alias("rse"), "n", F.round("est", 4).alias("est"), F.round(F.col("est") / F.col("n") - 1, 6).alias("error"))


_BITS_SQL = f"""with {_SIZED}, hist as (
  select p, m, r, count(*) as c from sized group by all union all select p, m, cast(0 as bigint), cast(m as bigint) - count(*) from sized group by p, m having count(*) < m),
seen as (select p, abs(r - log2(n / m)) as away, c from hist, n where p > 4)
select cast(p as bigint) as p, cast(ceil(log2(p + 2)) + 1 as bigint) as bits_all,
cast(ceil(log2(2 + log2(p))) + 1 as bigint) as bits_split, round(pow(2.0, p) / p, 4) as outliers_split,
cast(ceil(log2(2 + log2(log2(p)))) + 1 as bigint) as bits_deep, round(pow(2.0, p) / log2(p), 4) as outliers_deep,
round(exp(-pow(2.0, p) / (6 * p)), 9) as fails_split,
cast(sum(case when away >= 2 + log2(p) then c else 0 end) as bigint) as seen_split,
cast(sum(case when away >= 2 + log2(log2(p)) then c else 0 end) as bigint) as seen_deep from seen group by p"""


@query("q_theorem_bits", _BITS_SQL)
def theorem_bits(spark, d):
    """Offset widths and outlier counts that the bounds give for each p, with failure chance a half, and the column's outliers."""
    p, m = F.col("p").cast("double"), F.pow(F.lit(2.0), "p")
    up = lambda x: (F.ceil(x) + 1).cast("long")
    hist = S.histograms(workloads.sized(src(spark, d, "cents"))).where("p > 4").crossJoin(_count(spark, d))
    away = F.abs(F.col("r") - F.log2(F.col("n") / m))
    seen = lambda delta: F.sum(F.when(away >= delta, F.col("c")).otherwise(0)).cast("long")
    got = hist.groupBy("p").agg(seen(2 + F.log2(p)).alias("seen_split"), seen(2 + F.log2(F.log2(p))).alias("seen_deep"))
    return got.select(
        F.col("p").cast("long").alias("p"),
        up(F.log2(p + 2)).alias("bits_all"),
        up(F.log2(2 + F.log2(p))).alias("bits_split"),
        F.round(m / p, 4).alias("outliers_split"),
        up(F.log2(2 + F.log2(F.log2(p)))).alias("bits_deep"),
        F.round(m / F.log2(p), 4).alias("outliers_deep"),
        F.round(F.exp(-m / (6 * p)), 9).alias("fails_split"),
        "seen_split",
        "seen_deep",
    )


@query(
    "q_reduction_law",
    f"""with {_N}, ps as (select cast(p as bigint) as p, pow(2.0, p) as m from range(4, 19) t(p)), ks as (select cast(k as bigint) as k from range(64) t(k)),
cum as (select p, m, k, n, exp(n * ln(1 - 1 / (m * pow(2.0, k)))) as cum from ps, ks, n),
law as (select p, m, k, n, cum - coalesce(lag(cum) over (partition by p order by k), 0) as prob from cum),
mass as (select a.p, a.k, a.n, sum(b.prob) as mass from law a join law b on a.p = b.p and b.k between a.k and a.k + 7 group by a.p, a.k, a.n)
select p, n, round(3 + (p + 6) * (1 - max(mass)), 4) as per_register, round(1 - (3 + (p + 6) * (1 - max(mass))) / 6, 4) as reduction from mass group by p, n""",
)
def reduction_law(spark, d):
    """Size of the split form from the register law at the column's count, for every p."""
    from pyspark.sql import Window as W

    rows = spark.range(4, 19).select(F.col("id").alias("p")).crossJoin(F.broadcast(spark.range(64).select(F.col("id").alias("k")))).crossJoin(_count(spark, d))
    m = F.pow(F.lit(2.0), "p")
    per = W.partitionBy("p").orderBy("k")
    rows = rows.withColumn("cum", F.exp(F.col("n") * F.log1p(-1 / (m * F.pow(F.lit(2.0), "k")))))
    rows = rows.withColumn("prob", F.col("cum") - F.coalesce(F.lag("cum").over(per), F.lit(0.0)))
    mass = rows.withColumn("mass", F.sum("prob").over(per.rangeBetween(0, 7))).groupBy("p", "n").agg(F.max("mass").alias("mass"))
    bits = 3 + (F.col("p") + 6) * (1 - F.col("mass"))
    return mass.select("p", "n", F.round(bits, 4).alias("per_register"), F.round(1 - bits / 6, 4).alias("reduction"))


@query(
    "q_calculators",
    f"""with {_N} select cast(p as bigint) as p, n, round(exp(-pow(2.0, p) / (2 * p) / 3), 9) as chernoff,
round(pow(2.0, p) * log2(log2(p)) + pow(2.0, p) + log2(log2(n)), 4) as split_bits, round(pow(2.0, p) * log2(log2(n)), 4) as plain_bits,
round(pow(2.0, p) / log2(p) * log2(64 * log2(p)), 4) as succinct_bits, round(log2(n) * pow(2.0, p), 4) as most_calls from range(6, 19) t(p), n where n > 2""",
)
def calculators(spark, d):
    """Scalar bounds for each p at the column's count: tail of a sum, leading sizes, coded outliers, base searches."""
    n = exact(src(spark, d, "cents"), G, "v").where("n > 2").select("n").first()
    rows = []
    for p in range(6, 19) if n else ():
        m = float(1 << p)
        s = T.size_formula(p, n[0])
        rows.append((p, n[0], T.chernoff(1.0, m / (2 * p)), s["split"], s["plain"], T.succinct_bits(T.bits_deep(p)["outliers"], 64 * m), T.amortised(n[0], p)["calls"]))
    got = spark.createDataFrame(rows, "p long, n long, chernoff double, split_bits double, plain_bits double, succinct_bits double, most_calls double")
    return got.select("p", "n", F.round("chernoff", 9).alias("chernoff"), *(F.round(c, 4).alias(c) for c in ("split_bits", "plain_bits", "succinct_bits", "most_calls")))
