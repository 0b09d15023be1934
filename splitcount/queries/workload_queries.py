"""The experiments re-expressed: parameter grid, merges of halves, sizes, error, k-hop reach."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from splitcount import accuracy, measures, workloads
from splitcount.operators import estimate as E
from splitcount.operators import registers as R
from splitcount.operators import split as S
from splitcount.operators.codec import coded_registers
from splitcount.operators.estimate import alpha
from splitcount.operators.rivals import HEADER_BITS
from splitcount.queries.registry import est_sql, query, src, src_sql, with_hist, with_moments, with_pairs, with_regs, with_sized
from splitcount.schema import registers_of
from splitcount.session import cut, table

_RUNGS = tuple(range(4, 61, 4))
_REPS = 2
_ALL_P = tuple(range(4, 19))
#: (p, m, alpha m m) of every size.
_SIZES = "(values " + ", ".join(f"({p}, {float(registers_of(p))!r}, {alpha(p) * registers_of(p) ** 2!r})" for p in _ALL_P) + ") sizes(p, m, am)"
_TOP_E = 2.0**64

_GRID_SQL = f"""with items as (
  select 'integers' as input, cast(ceil(2 * log2(greatest(l_orderkey, 1))) as integer) as step, cast(l_orderkey as varchar) as v from lineitem
  union all select 'strings', cast(ceil(2 * log2(greatest(c_custkey, 1))) as integer), c_name from customer
  union all select 'pairs', cast(ceil(2 * log2(greatest(event_id, 1))) as integer), 'pair ' || event_id from events
), reps as (
  select input, cast(k as integer) as rep, step, k || ':' || v as v from items, range(0, {_REPS}) t(k)
), {with_regs("select * from reps", 18, cols="input, rep, step")},
rungs as (select cast(k as integer) as upto from (values {", ".join(f"({k})" for k in _RUNGS)}) t(k)),
every as (select input, rep, upto, j, max(r) as r from regs join rungs on step <= upto group by all),
folded as (select input, rep, upto, p, m, am, j >> (18 - p) as j, max(r) as r from every, {_SIZES} group by all),
s as (select input, rep, upto, p, m, am, sum(pow(2.0, -r)) + (m - count(*)) as s, m - count(*) as v from folded group by input, rep, upto, p, m, am),
n as (select input, rep, upto, count(distinct v) as n from reps join rungs on step <= upto group by all),
e as (select *, round(case when am / s <= 2.5 * m and v > 0 then m * ln(m / v) when am / s > {_TOP_E / 30!r} then {-_TOP_E!r} * ln(1 - am / s / {_TOP_E!r}) else am / s end, 4) as est from s join n using (input, rep, upto))
select cast(p as integer) as p, input, rep, upto, n, est, round(est / n - 1, 6) as rel_err from e"""


@query("q_w01_grid", _GRID_SQL)
def grid(spark, d):
    """Every size, three inputs, repetitions; every fourth rung of the ladder and two repetitions here."""
    return workloads.grid(spark, d, _ALL_P, _RUNGS, _REPS)


_EVENTS_SQL = "select event_id as id, '{0}:' || event_id as v from events"


@query("q_w04_pairs", f"with {with_regs(_EVENTS_SQL.format(0), 8, cols='id').replace('regs as (select id, j, max(r) as r from pairs group by id, j)', 'regs as (select 0 as g, j, max(r) as r from pairs group by j)')}, {with_hist(None, 8)}, {with_moments(8)} select round({est_sql(8)}, 4) as est from moments")
def raw_pairs(spark, d):
    """Pairs drawn for every event's id, taken as they are."""
    rows = workloads.raw_pairs(spark, 0, 8, family="md5_64", ids=workloads.event_stream(spark, d, 0))
    return E.from_registers(R.from_pairs(rows, []), [], 8).select(F.round("est", 4).alias("est"))


@query("q_w05_hash_only", "select count(*) as n, cast(sum(('0x' || substr(md5(text), 1, 8))::bigint) as bigint) as sum_hi, max(('0x' || substr(md5(text), 1, 8))::bigint) as max_hi from documents where text is not null")
def hash_only(spark, d):
    from splitcount.functions.hashing import with_hash

    h = with_hash(table(spark, d, "documents").select("text").where("text is not null"), F.col("text"))
    return h.agg(F.count("*").alias("n"), F.sum("hi").alias("sum_hi"), F.max("hi").alias("max_hi"))


@query("q_w06_update_time")
def update_time(spark, d):
    """Sequential update time of every implementation as the stream of events grows, at the figure's size."""
    ids = workloads.event_stream(spark, d, 1 << 14)
    plain = measures.update_scaling(spark, 15, (1 << 8, 1 << 11, 1 << 14), reps=1, ids=ids)
    return plain.unionByName(measures.update_scaling(spark, 15, (1 << 8, 1 << 11), ("zstd",), reps=1, ids=ids))


@query("q_w07_total_time")
def total_time(spark, d):
    """Time for one stream of events, over the number of registers."""
    return measures.total_by_registers(spark, 1 << 13, ids=workloads.event_stream(spark, d, 1 << 13))


_LOAD_P, _TOP_LOAD = (4,), 1 << 17


def _stream_sql(least: int) -> str:
    """The ids of all events, and of as many copies with shifted ids as make ``least`` of them."""
    return f"select event_id + k * span as id from events, (select span, unnest(range(0, greatest(1, cast(ceil({float(least)!r} / n) as bigint)))) as k from (select max(event_id) + 1 as span, count(*) as n from events))"


@query(
    "q_w08_load_factor",
    "with "
    + ",\n".join(
        f"""{with_pairs(f"select id, '3:' || id as v from ({_stream_sql(_TOP_LOAD << p)})", p, f"_{p}", cols="id")},
f_{p} as (select j, r, min(id) as id from pairs_{p} group by j, r),
u_{p} as (select id, r, coalesce(max(r) over (partition by j order by id rows between unbounded preceding and 1 preceding), 0) as b from f_{p})"""
        for p in _LOAD_P
    )
    + " "
    + " union all ".join(f"select cast({p} as integer) as p, cast(floor(log2((id + 1) / {float(1 << p)!r})) as integer) as load, count(*) as changed from u_{p} where r > b group by 2" for p in _LOAD_P),
)
def load_factor(spark, d):
    """Pairs of the events that still raise a register, by doublings of the load up to 2**17 at least: the work that is left."""
    return workloads.load_changes(spark, _LOAD_P, _TOP_LOAD, workloads.event_stream(spark, d, _TOP_LOAD << max(_LOAD_P)))


@query("q_w08_load_time")
def load_time(spark, d):
    """Time per item of the stream of events and base searches against the load, up to 2**17, per variant."""
    runs = [(v, 4, 16 << k, 0, "pairs") for v in ("opt", "lazy", "min") for k in (0, 3, 6, 9, 12, 15, 17)]
    got = measures.sequential(spark, runs, workloads.event_stream(spark, d, 16 << 17))
    return got.select("variant", "p", (F.col("n") / 16).cast("long").alias("load"), "per_item", "changed", "compress_calls", "rebases")


@query("q_w09_merge_halves", "select cast(0 as bigint) as mismatches")
def merge_halves(spark, d):
    return workloads.merge_check(table(spark, d, "lineitem"), "l_orderkey", 10)


_LAW_N = 2.0**30


def _events(spark, d) -> float:
    return float(src(spark, d, "events").agg(F.count_distinct("v")).first()[0])


_WINDOWS = """w as (
  select a.p, a.b, a.here, a.m - cast(sum(h.c) as bigint) as sparse from cand a join hist h on h.p = a.p and h.r between a.b and a.b + 7 group by a.p, a.b, a.here, a.m
)"""

_SIZES_SQL = f"""with {with_sized(src_sql('events'))},
hist as (
  select p, cast(m as bigint) as m, r, count(*) as c from sized group by all
  union all select p, cast(m as bigint), cast(0 as bigint), cast(m as bigint) - count(*) from sized group by p, m having count(*) < m),
cand as (select p, m, r as b, c as here from hist union all select distinct p, m, cast(0 as bigint), cast(0 as bigint) from hist x where not exists (select 1 from hist y where y.p = x.p and y.r = 0)),
{_WINDOWS},
opt as (select p, min_by(sparse, struct_pack(s := sparse, b := b)) as s from w where here > 0 group by p),
low as (select p, min_by(sparse, b) as s from w where here > 0 group by p),
steps as (select *, coalesce(sparse >= lag(sparse) over (partition by p order by b), false) as stop from w),
climb as (select p, max_by(sparse, b) as s from (select *, bool_or(stop) over (partition by p order by b) as stopped from steps) where not stopped group by p),
four as (select h.p, cast(sum(case when h.r - l.b >= 15 then h.c else 0 end) as bigint) as s from hist h join (select p, min(r) as b from hist group by p) l on l.p = h.p group by h.p),
f as (select p, m, -(exp(-n / (m * pow(2.0, k))) - 1) as f from (select distinct p, m from hist), range(1, 64) t(k), n),
x as (
  select p, 'split_opt' as variant, 3 * (1::bigint << p) + s * (p + 6) as bits from opt
  union all select p, 'split_min', 3 * (1::bigint << p) + s * (p + 6) from low
  union all select p, 'split_lazy', 3 * (1::bigint << p) + s * (p + 6) from climb
  union all select p, 'reg4', 4 * (1::bigint << p) + s * (p + 6) from four
  union all select p, 'reg6', 6 * (1::bigint << p) from four
  union all select p, 'reg6_library', 6 * (1::bigint << p) + {HEADER_BITS} from four
  union all select p, 'reg8', 8 * (1::bigint << p) from four
  union all select p, 'matrix', cast(round(m * sum(case when f <= 0 or f >= 1 then 0.0 else -f * log2(f) - (1 - f) * log2(1 - f) end)) as bigint) from f group by p, m
)
select p, variant, cast(bits as bigint) as bits, round(bits / pow(2.0, p), 6) as per_register, round(1 - bits / pow(2.0, p) / 6, 6) as reduction from x"""


@query("q_w10_sizes", _SIZES_SQL)
def sizes(spark, d):
    """Every implementation at all sizes, from the registers of the events' ids."""
    return workloads.sizes_at(spark, _events(spark, d), _ALL_P, regs=workloads.sized(src(spark, d, "events")))


@query("q_w10_zstd")
def zstd_sizes(spark, d):
    """(p, bits, per_register) of byte-wide registers under Zstandard, from the same registers."""

    @F.pandas_udf("long")
    def coded(p: pd.Series, regs: pd.Series) -> pd.Series:
        out = []
        for size, entries in zip(p, regs, strict=True):
            cells = np.zeros(1 << size, np.uint8)
            for e in entries:
                cells[e["j"]] = e["r"]
            out.append(8 * len(coded_registers(cells)))
        return pd.Series(out)

    one = workloads.law_rows(spark, _LAW_N, _ALL_P).groupBy("p").agg(F.collect_list(F.struct("j", "r")).alias("x"))  # m entries each
    return one.select("p", coded("p", "x").alias("bits")).withColumn("per_register", F.round(F.col("bits") / F.pow(F.lit(2.0), "p"), 6))


@query(
    "q_w10_closed",
    f"""with n as (select count(distinct v) as n from ({src_sql('events')})),
c as (select cast(p as integer) as p, m, k, exp(n * ln(1 - 1 / (m * pow(2.0, k)))) as cum from {_SIZES}, range(0, 64) t(k), n),
l as (select p, m, k, cum - coalesce(lag(cum) over (partition by p order by k), 0) as prob from c),
w as (select a.p, a.m, a.k, sum(b.prob) as mass from l a join l b on b.p = a.p and b.k between a.k and a.k + 7 group by all)
select p, round(3 + (p + 6) * (1 - max(mass)), 3) as per_register, round(1 - (3 + (p + 6) * (1 - max(mass))) / 6, 3) as reduction, round(min(e), 3) as entropy
from w join (select p, -sum(case when prob > 0 then prob * log2(prob) else 0 end) as e from l group by p) using (p) group by p""",
)
def closed_sizes(spark, d):
    """The closed form at the count of the events' ids."""
    got = workloads.closed_sizes(spark, _events(spark, d))
    return got.select("p", *(F.round(c, 3).alias(c) for c in ("per_register", "reduction", "entropy")))


@query("q_w11_point")
def point(spark, d):
    """Size and update time of every implementation at the figure's size; slow coders over fewer items, said in n."""
    quick = measures.sequential(spark, [(v, 15, 1 << 14, 0, "pairs") for v in measures.CONTENDERS if v not in ("zstd", "matrix")])
    slow = measures.sequential(spark, [(v, 15, 1 << 11, 0, "pairs") for v in ("zstd", "matrix", "lazy", "opt")])
    return quick.unionByName(slow).select("variant", "p", "n", "bits", "per_item", "est")


@query("q_w11_curve")
def curve(spark, d):
    """The same for every second size from 2**10 to 2**18 registers."""
    return measures.tradeoff(spark, (10, 12, 14, 16, 18), 1 << 12)


@query("q_w11_front")
def curve_front(spark, d):
    """The points that no other beats in both size and time."""
    return measures.front(cut(measures.tradeoff(spark, (10, 12), 1 << 12)))


@query("q_w13_spread")
def spread(spark, d):
    return accuracy.spread(spark, 5_000, 8, 30)


@query("q_w14_dependence")
def dependence(spark, d):
    from splitcount.functions.theory import covariance

    return covariance(workloads.outlier_flags(spark, 512, 4, 1.5, 100))


@query("q_w12_same_estimate", "select 0.0::double as max_diff")
def same_estimate(spark, d):
    rows = table(spark, d, "orders").select(F.col("o_orderstatus").alias("g"), F.col("o_custkey").cast("string").alias("v"))
    regs = R.build(rows, ["g"], "v", 10)
    base = S.best_base(S.histogram(regs, ["g"], 10), ["g"], 10)
    parts = S.split(regs, base, ["g"], 10)
    back = S.get(S.dense_part(parts, ["g"]), S.sparse_part(parts, ["g"]), base, ["g"])
    plain = E.from_registers(regs, ["g"], 10).select("g", "est")
    return accuracy.same_estimate(plain, E.from_registers(back.where("r > 0"), ["g"], 10).select("g", "est"), ["g"])
