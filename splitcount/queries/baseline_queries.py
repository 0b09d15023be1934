"""Methods to compare with, each per flag over the order keys unless said otherwise."""

from __future__ import annotations

from math import log

from pyspark.sql import functions as F

from splitcount.functions import hashing as H
from splitcount.operators import baselines as B
from splitcount.operators.rivals import HEADER_BITS
from splitcount.queries.methods import G, hist_of, regs_of
from splitcount.queries.registry import P, _union, est_sql, query, src, src_sql, with_est, with_hist, with_moments, with_pairs
from splitcount.session import table

_BY_FLAG = src_sql("orderkeys_by_flag")
_M = 1 << P


def _pairs(spark, d, name="orderkeys_by_flag"):
    return H.pairs(src(spark, d, name), G, "v", P)


_COUNTS = {
    "c_name": "customer",
    "event_id": "events",
    "l_orderkey": "lineitem",
    "l_partkey": "lineitem",
    "l_suppkey": "lineitem",
    "lang": "documents",
    "o_custkey": "orders",
    "props": "events",
    "source": "documents",
    "text": "documents",
    "url": "pages",
    "user_id": "events",
}


@query("q_exact_counts", " union all ".join(f"select '{c}' as name, count(distinct {c}) as n from {t}" for c, t in _COUNTS.items()))
def exact_counts(spark, d):
    return _union([B.exact(table(spark, d, t).select(F.lit(c).alias("name"), F.col(c).cast("string").alias("v")), ["name"], "v") for c, t in _COUNTS.items()])


@query("q_exact_builtin", f"select g, count(distinct v) as n from ({_BY_FLAG}) group by g")
def exact_builtin(spark, d):
    return src(spark, d, "orderkeys_by_flag").groupBy("g").agg(F.count_distinct("v").alias("n"))


@query("q_reg6", f"with {with_est(_BY_FLAG)} select g, est, cast({6 * _M} as bigint) as bits from est")
def reg6(spark, d):
    return B.reg6(regs_of(spark, d, "orderkeys_by_flag"), G, P).select("g", F.round("est", 4).alias("est"), "bits")


@query(
    "q_reg4",
    f"""with {with_est(_BY_FLAG)}, low as (select g, min(r) as b from hist group by g),
x as (select h.g, cast(sum(case when h.r - l.b >= 15 then h.c else 0 end) as bigint) as exceptions from hist h join low l on h.g = l.g group by h.g)
select g, exceptions, cast({4 * _M} + exceptions * {P + 6} as bigint) as bits, est from x join est using (g)""",
)
def reg4(spark, d):
    return B.reg4(regs_of(spark, d, "orderkeys_by_flag"), G, P).withColumn("est", F.round("est", 4))


@query("q_reg8", f"with {with_est(_BY_FLAG)} select g, est, cast({8 * _M} as bigint) as bits from est")
def reg8(spark, d):
    return B.reg8(regs_of(spark, d, "orderkeys_by_flag"), G, P).withColumn("est", F.round("est", 4))


@query("q_reg6_library", f"with {with_est(_BY_FLAG)} select g, est, cast({6 * _M + HEADER_BITS} as bigint) as bits from est")
def reg6_library(spark, d):
    return B.reg6_library(regs_of(spark, d, "orderkeys_by_flag"), G, P).withColumn("est", F.round("est", 4))


@query("q_linear_counting", f"with {with_pairs(_BY_FLAG)}, u as (select g, count(distinct j) as u from pairs group by g) select g, case when u < {_M} then round({float(_M)!r} * ln({float(_M)!r} / ({_M} - u)), 4) end as est from u")
def linear_counting(spark, d):
    return B.linear_counting(_pairs(spark, d), G, P).select("g", F.round("est", 4).alias("est"))


@query("q_linear_estimate", f"with {with_hist(src_sql('four'))}, {with_moments()} select g, case when v > 0 then round({float(_M)!r} * ln({float(_M)!r} / v), 4) end as est from moments")
def linear_estimate(spark, d):
    from splitcount.operators import estimate as E

    return E.from_hist(hist_of(spark, d, "four"), G, P, "linear").select("g", F.round("est", 4).alias("est"))


@query("q_loglog", f"with {with_hist(_BY_FLAG)} select g, round({B.LOGLOG_CONSTANT * _M!r} * pow(2.0, sum(c * r) / {float(_M)!r}), 4) as est from hist group by g")
def loglog(spark, d):
    return B.loglog(hist_of(spark, d, "orderkeys_by_flag"), G, P).select("g", F.round("est", 4).alias("est"))


_KEEP = int(0.7 * _M)


@query(
    "q_superloglog",
    f"""with {with_hist(_BY_FLAG)},
b as (select *, coalesce(sum(c) over (partition by g order by r rows between unbounded preceding and 1 preceding), 0) as before from hist)
select g, round({B.SUPERLOGLOG_CONSTANT * _M!r} * pow(2.0, sum(r * greatest(0, least(c, {_KEEP} - before))) / {float(_KEEP)!r}), 4) as est from b group by g""",
)
def super_loglog(spark, d):
    return B.super_loglog(hist_of(spark, d, "orderkeys_by_flag"), G, P).select("g", F.round("est", 4).alias("est"))


@query(
    "q_bitmatrix",
    f"""with {with_pairs(_BY_FLAG)}, rows as (select g, j, bit_or(cast(1 as bigint) << cast(r - 1 as integer)) as x from pairs group by g, j)
select g, round({_M / B.BITMATRIX_CONSTANT!r} * pow(2.0, sum(bit_count(xor(x, x + 1)) - 1) / {float(_M)!r}), 4) as est from rows group by g""",
)
def bitmatrix(spark, d):
    return B.bitmatrix(_pairs(spark, d), G, P).select("g", F.round("est", 4).alias("est"))


@query(
    "q_kmin",
    f"""with h as (select distinct g, ('0x' || substr(md5(v), 1, 13))::bigint as h from ({_BY_FLAG}) where v is not null),
k as (select *, row_number() over (partition by g order by h) as n from h)
select g, round(case when count(*) < 256 then cast(count(*) as double) else {255 * 2.0**52!r} / max(h) end, 4) as est from k where n <= 256 group by g""",
)
def kmin(spark, d):
    return B.kmin(src(spark, d, "orderkeys_by_flag"), G, "v").select("g", F.round("est", 4).alias("est"))


@query(
    "q_tailcut",
    f"""with {with_hist(_BY_FLAG, tag='0')}, low as (select g, min(r) as b from hist0 group by g),
hist as (select h.g, l.b + least(h.r - l.b, 7) as r, h.c from hist0 h join low l on h.g = l.g), {with_moments()}
select g, round({est_sql()}, 4) as est, cast({3 * _M} as bigint) as bits from moments""",
)
def tailcut(spark, d):
    return B.tailcut(hist_of(spark, d, "orderkeys_by_flag"), G, P).select("g", F.round("est", 4).alias("est"), "bits")


def _matrix_sql(select: str, last: str) -> str:
    """Ones, estimate by bisection and coded bits of the bit matrices of a grouped select."""
    return f"""with recursive {with_pairs(select)}, cells as (select distinct g, j, r from pairs), gs as (select distinct g from cells),
cols as (select g, r as k, count(*) as ones from cells group by g, r),
full_cols as (select gs.g, t.k, coalesce(c.ones, 0) as ones from gs join (select g, max(r) as top from cells group by g) x on x.g = gs.g, range(1, 64) t(k) left join cols c on c.g = gs.g and c.k = t.k where t.k <= x.top),
marks as (
  select f.g, f.k, i.j, case when 2 * f.ones > {_M} then {_M} - f.ones else f.ones end as n
  from full_cols f, range(0, {_M}) i(j) left join cells c on c.g = f.g and c.r = f.k and c.j = i.j
  where (c.j is null) = (2 * f.ones > {_M})),
gaps as (select g, k, n, case when ({_M} - n) // n < 1 then 0 else length(bin(({_M} - n) // n)) - 1 end as s, j - coalesce(lag(j) over (partition by g, k order by j), -1) - 1 as gap from marks),
rice as (select g, k, sum((gap >> s) + 1 + s) as size from gaps group by g, k),
coded as (select f.g, cast(7 + sum({P + 3} + least(coalesce(x.size, 0), {_M})) as bigint) as bits, cast(sum(f.ones) as bigint) as ones from full_cols f left join rice x on x.g = f.g and x.k = f.k group by f.g),
solve(g, ones, step, lo, hi) as (
  select g, ones, 0, 1e-6::double, pow(2.0, 60) from coded
  union all
  select g, ones, step + 1, case when below then sqrt(lo * hi) else lo end, case when below then hi else sqrt(lo * hi) end
  from (select *, list_sum(list_transform(range(1, 64), lambda k: {_M} * (1 - exp(-sqrt(lo * hi) / ({_M} * pow(2.0, k)))))) < ones as below from solve where step < 200))
{last}"""


@query("q_bitmatrix_coded", _matrix_sql(_BY_FLAG, "select g, round(sqrt(lo * hi), 4) as est, bits, c.ones from solve join coded c using (g) where step = 200"))
def bitmatrix_coded(spark, d):
    """Bit matrices coded to bytes, and read back from them."""
    return B.matrix_blobs(_pairs(spark, d), G, P).select("g", B.matrix_read("matrix").alias("x")).select("g", F.round("x.est", 4).alias("est"), "x.bits", "x.ones")


@query("q_bitmatrix_merge", _matrix_sql(f"select 'A+N' as g, v from ({_BY_FLAG}) where g <> 'R'", "select round(sqrt(lo * hi), 4) as est, bits, c.ones from solve join coded c using (g) where step = 200"))
def bitmatrix_merge(spark, d):
    """Two coded matrices merged in their stored form."""
    b = B.matrix_blobs(_pairs(spark, d), G, P)
    one = b.where("g = 'A'").select(F.lit(1).alias("k"), F.col("matrix").alias("a"))
    two = b.where("g = 'N'").select(F.lit(1).alias("k"), F.col("matrix").alias("b"))
    got = one.join(two, "k").select(B.matrix_read(B.matrix_merge2("a", "b")).alias("x"))
    return got.select(F.round("x.est", 4).alias("est"), "x.bits", "x.ones")


_ENTROPY = f"""with {with_pairs(_BY_FLAG)}, cells as (select distinct g, j, r from pairs), f as (select g, r, count(*) / {float(_M)!r} as f from cells group by g, r)
select g, round(sum(case when f >= 1 then 0.0 else -f * log2(f) - (1 - f) * log2(1 - f) end) * {_M}, 4) as bits from f group by g"""


@query("q_bitmatrix_entropy", _ENTROPY)
def bitmatrix_entropy(spark, d):
    """What no coder of the columns can go below."""
    return B.bitmatrix_coded(_pairs(spark, d), G, P).select("g", F.round("bits", 4).alias("bits"))


_MLE = f"""with recursive {with_hist(src_sql("four"))}, top as (select g, list(r order by r) as rs, list(c order by r) as cs, max(r) as t, max(case when r = 0 then c else 0 end) as zero from hist group by g),
solve(g, step, lo, hi) as (
  select g, 0, 1e-9::double, {float(_M)!r} * pow(2.0, t + 4) from top
  union all
  select g, step + 1, case when score > 0 then mid else lo end, case when score > 0 then hi else mid end
  from (select s.g, step, lo, hi, sqrt(lo * hi) as mid,
          list_sum(list_transform(range(1, len(rs) + 1), lambda i: case when rs[i] = 0 then -cs[i] / {float(_M)!r}
            else cs[i] * (-1 / ({_M} * pow(2.0, rs[i])) + 1 / ({_M} * pow(2.0, rs[i])) * exp(-sqrt(lo * hi) / ({_M} * pow(2.0, rs[i]))) / (1 - exp(-sqrt(lo * hi) / ({_M} * pow(2.0, rs[i]))))) end)) as score
        from solve s join top using (g) where step < 90))
select g, round(sqrt(lo * hi), 1) as est from solve where step = 90"""


@query("q_estimate_mle", _MLE)
def estimate_mle(spark, d):
    """Maximum likelihood, to one decimal: the score's zero is flat in its last bits."""
    from splitcount.operators import estimate as E

    return E.likelihood(hist_of(spark, d, "four"), G, P).select("g", F.round("est", 1).alias("est"))


@query(
    "q_estimate_improved",
    f"""with {with_hist(src_sql("four"))}, s as (select g, sum(case when r > 0 then c * pow(2.0, -r) else 0.0 end) as s, coalesce(sum(case when r = 0 then c end), 0) / {float(_M)!r} as x from hist group by g)
select g, round(case when x = 1 then 0.0 else {_M * _M / (2 * log(2))!r} / ({float(_M)!r} * (x + list_sum(list_transform(range(1, 26), lambda k: pow(x, pow(2.0, k)) * pow(2.0, k - 1)))) + s) end, 4) as est from s""",
)
def estimate_improved(spark, d):
    from splitcount.operators import estimate as E

    return E.improved(hist_of(spark, d, "four"), G, P).select("g", F.round("est", 4).alias("est"))


@query(
    "q_martingale",
    f"""with {with_pairs("select event_id, cast(event_id as varchar) as v from events", cols="event_id")}, f as (select j, r, min(event_id) as id from pairs group by j, r),
u as (select id, r, coalesce(max(r) over (partition by j order by id rows between unbounded preceding and 1 preceding), 0) as b from f),
c as (select 1 - coalesce(sum((pow(2.0, -b) - pow(2.0, -r)) / {float(_M)!r}) over (order by id rows between unbounded preceding and 1 preceding), 0) as chance from u where r > b)
select round(coalesce(sum(1 / chance), 0), 4) as est from c""",
)
def martingale(spark, d):
    rows = H.pairs(table(spark, d, "events"), ["event_id"], F.col("event_id").cast("string"), P)
    return B.martingale(rows, P, "event_id").select(F.round("est", 4).alias("est"))


@query("q_builtin_hllpp")
def builtin_hllpp(spark, d):
    return B.builtin_improved(src(spark, d, "four"), G, "v", 0.03)


@query("q_builtin_sketch")
def builtin_sketch(spark, d):
    return B.builtin_sketch(src(spark, d, "four"), G, "v", 10)


@query("q_builtin_theta")
def builtin_theta(spark, d):
    return B.builtin_theta(src(spark, d, "four"), G, "v")


@query(
    "q_error_by_group",
    f"""with {with_est(src_sql('four'))}, n as (select g, count(distinct v) as n from ({src_sql('four')}) group by g)
select g, n, est, round(est / n - 1, 6) as rel_err, abs(est / n - 1) <= {5 * 1.04 / 32!r} as within_5_rse from est join n using (g)""",
)
def error_by_group(spark, d):
    from splitcount import accuracy

    return accuracy.relative_error(src(spark, d, "four"), G, "v", P)
