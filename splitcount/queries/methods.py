"""Core methods: hashing, registers, estimates, split, base choice, merge, sizes."""

from __future__ import annotations

from pyspark.sql import functions as F

from splitcount.functions import cost
from splitcount.functions import hashing as H
from splitcount.operators import estimate as E
from splitcount.operators import registers as R
from splitcount.operators import split as S
from splitcount.queries.registry import KAPPA, P, RANK_SQL, _union, alpha_of, est_sql, hash_sql, index_sql, query, src, src_sql, with_base, with_est, with_hist, with_moments, with_pairs, with_regs
from splitcount.session import table

G = ["g"]


def regs_of(spark, d, name: str, p: int = P):
    return R.build(src(spark, d, name), G, "v", p)


def hist_of(spark, d, name: str, p: int = P):
    return S.histogram(regs_of(spark, d, name, p), G, p)


# ------------------------------------------------------------------ hashing

_EVENTS = "select event_id, cast(event_id as varchar) as v from events"


def _hashed(spark, d):
    return H.with_hash(table(spark, d, "events").select("event_id"), F.col("event_id").cast("string"))


@query("q_hash_md5_hilo", f"select event_id, {hash_sql()} from ({_EVENTS})")
def hash_md5_hilo(spark, d):
    return _hashed(spark, d).select("event_id", "hi", "lo")


@query("q_rank", f"select event_id, {RANK_SQL} as r from (select event_id, {hash_sql()} from ({_EVENTS}))")
def rank(spark, d):
    return _hashed(spark, d).select("event_id", H.rank().alias("r"))


@query("q_index_fib", f"select event_id, {index_sql(P)} as j from (select event_id, {hash_sql()} from ({_EVENTS}))")
def index_fib(spark, d):
    return _hashed(spark, d).select("event_id", H.fib_index(P).alias("j"))


@query("q_index_second", f"select event_id, {RANK_SQL} as r, hi2 // {1 << (32 - P)} as j from (select event_id, {hash_sql()}, ('0x' || substr(md5('1:' || v), 1, 8))::bigint as hi2 from ({_EVENTS}))")
def index_second(spark, d):
    return H.pairs(table(spark, d, "events"), ["event_id"], F.col("event_id").cast("string"), P, index="second")


@query(
    "q_index_prefix",
    f"""select event_id, hi // {1 << (32 - P)} as j,
  cast(case when hi % {1 << (32 - P)} > 0 then {33 - P} - length(bin(hi % {1 << (32 - P)})) else least(63, case when lo > 0 then {65 - P} - length(bin(lo)) else {65 - P} end) end as bigint) as r
from (select event_id, {hash_sql()} from ({_EVENTS}))""",
)
def index_prefix(spark, d):
    return H.pairs(table(spark, d, "events"), ["event_id"], F.col("event_id").cast("string"), P, index="prefix")


@query(
    "q_hash_sha",
    f"select event_id, {RANK_SQL} as r, {index_sql(P)} as j from (select event_id, ('0x' || substr(sha256(v), 1, 8))::bigint as hi, ('0x' || substr(sha256(v), 9, 8))::bigint as lo from ({_EVENTS}))",
)
def hash_sha(spark, d):
    return H.pairs(table(spark, d, "events"), ["event_id"], F.col("event_id").cast("string"), P, family="sha_64")


@query("q_rank_w32", f"select event_id, {index_sql(P)} as j, cast(case when hi > 0 then 33 - length(bin(hi)) else 33 end as bigint) as r from (select event_id, {hash_sql()} from ({_EVENTS}))")
def rank_w32(spark, d):
    """Ranks of a 32-bit hash: the first word alone."""
    return H.pairs(table(spark, d, "events"), ["event_id"], F.col("event_id").cast("string"), P, w=32)


def _mix_sql() -> str:
    """Shift-xor and multiply rounds on 128-bit numbers."""
    h = "h::uhugeint"
    one = lambda n, k: f"((xor(h, h // {1 << n}::uhugeint) * {k}::uhugeint) % 18446744073709551616::uhugeint)"
    return f"""with a as (select event_id, event_id::uhugeint as h from events),
b as (select event_id, {one(30, 0xBF58476D1CE4E5B9)} as h from a),
c as (select event_id, {one(27, 0x94D049BB133111EB)} as h from b),
e as (select event_id, xor(h, h // {1 << 31}::uhugeint) as h from c)
select event_id, cast({h} // 4294967296::uhugeint as bigint) as hi, cast({h} % 4294967296::uhugeint as bigint) as lo from e"""


@query("q_hash_mix64", _mix_sql())
def hash_mix64(spark, d):
    return H.with_hash(table(spark, d, "events").select("event_id"), F.col("event_id"), "mix64").select("event_id", "hi", "lo")


@query("q_gen_pairs", f"with {with_pairs(_EVENTS, P, cols='event_id')} select event_id, j, r from pairs")
def gen_pairs(spark, d):
    return H.pairs(table(spark, d, "events"), ["event_id"], F.col("event_id").cast("string"), P)


# ------------------------------------------------------------------ registers


@query("q_reg_global", f"with {with_regs(src_sql('orderkeys'))} select j, r from regs")
def reg_global(spark, d):
    return R.build(table(spark, d, "lineitem"), [], F.col("l_orderkey").cast("string"), P)


@query("q_reg_hist", f"with {with_hist(src_sql('orderkeys'))} select r, c from hist")
def reg_hist(spark, d):
    return S.histogram(reg_global(spark, d), [], P)


@query("q_reg_by_lang", f"with {with_regs(src_sql('texts'))} select g, j, r from regs")
def reg_by_lang(spark, d):
    return regs_of(spark, d, "texts")


@query("q_reg_by_event_type", f"with {with_regs(src_sql('events'))} select g, j, r from regs")
def reg_by_event_type(spark, d):
    return regs_of(spark, d, "events")


@query("q_reg_filtered", f"with {with_regs(src_sql('orderkeys') + ' where l_quantity > 25')} select j, r from regs")
def reg_filtered(spark, d):
    return R.build(table(spark, d, "lineitem").where("l_quantity > 25"), [], F.col("l_orderkey").cast("string"), P)


@query(
    "q_reg_filter_clause",
    f"""with {with_pairs(src_sql('orderkeys_by_flag'))}
select j, max(r) filter (where g = 'A') as r_a, max(r) filter (where g = 'N') as r_n from pairs group by j""",
)
def reg_filter_clause(spark, d):
    rows = H.pairs(src(spark, d, "orderkeys_by_flag"), G, "v", P)
    return rows.groupBy("j").agg(F.expr("max(r) filter (where g = 'A')").alias("r_a"), F.expr("max(r) filter (where g = 'N')").alias("r_n"))


@query("q_reg_two_keys", f"with {with_regs('select l_returnflag, l_linestatus, cast(l_partkey as varchar) as v from lineitem', cols='l_returnflag, l_linestatus')} select l_returnflag, l_linestatus, j, r from regs")
def reg_two_keys(spark, d):
    return R.build(table(spark, d, "lineitem"), ["l_returnflag", "l_linestatus"], F.col("l_partkey").cast("string"), P)


@query("q_reg_multi_column", f"with {with_regs('select chr(31) || l_partkey || chr(31) || l_suppkey as v, 1 as g from lineitem')} select j, r from regs")
def reg_multi_column(spark, d):
    return R.build(table(spark, d, "lineitem"), [], H.joined_key("l_partkey", "l_suppkey"), P)


_HALF = "select 'all' as g, cast(event_id as varchar) as v from events where event_id {} (select (min(event_id) + max(event_id)) // 2 from events)"


@query(
    "q_early_reject",
    f"""with {with_regs(_HALF.format('<='), 4, '1')}, {with_pairs(_HALF.format('>'), 4, '2')},
low as (select case when count(*) < 16 then 0 else min(r) end as low from regs1)
select j, count(*) as n_kept from pairs2, low where r > low group by j""",
)
def early_reject(spark, d):
    ev = table(spark, d, "events")
    mid = ev.agg(F.expr("(min(event_id) + max(event_id)) div 2").alias("mid"))
    ev = ev.select("event_id").crossJoin(F.broadcast(mid))  # one row
    halves = H.pairs(ev, ["event_id", "mid"], F.col("event_id").cast("string"), 4)
    first = R.from_pairs(halves.where("event_id <= mid"), [])
    kept = R.early_reject(halves.where("event_id > mid").select("j", "r"), first, [], 4)
    return kept.groupBy("j").agg(F.count("*").alias("n_kept"))


@query(
    "q_changed_registers",
    f"""with {with_pairs(_EVENTS, cols='event_id')},
u as (select r > coalesce(max(r) over (partition by j order by event_id rows between unbounded preceding and 1 preceding), 0) as up from pairs)
select cast(sum(cast(up as int)) as bigint) as n_changed, count(*) as n_total from u""",
)
def changed_registers(spark, d):
    return R.changed(gen_pairs(spark, d), [], "event_id")


@query("q_fold", f"with {with_regs(src_sql('texts'), P - 2)} select g, j, r from regs")
def fold(spark, d):
    return R.fold(regs_of(spark, d, "texts"), G, P, P - 2)


@query("q_array_registers", f"""with {with_regs("select l_returnflag as g, cast(l_suppkey as varchar) as v from lineitem", 4)},
every as (select g, cast(j as bigint) as j from (select distinct g from regs), range(16) t(j))
select e.g, string_agg(cast(coalesce(r.r, 0) as varchar), ',' order by e.j) as regs from every e left join regs r on e.g = r.g and e.j = r.j group by e.g""")
def array_registers(spark, d):
    regs = R.build(table(spark, d, "lineitem").withColumn("g", F.col("l_returnflag")), G, F.col("l_suppkey").cast("string"), 4)
    return R.to_array(regs, G, 4).select("g", F.array_join(F.col("regs").cast("array<string>"), ",").alias("regs"))


# ------------------------------------------------------------------ estimates

_FOUR = with_hist(src_sql("four")) + ",\n" + with_moments()


def _moments(spark, d):
    return E.moments(hist_of(spark, d, "four"), G)


@query("q_estimate_raw", f"with {_FOUR} select g, v, round({alpha_of(P) * (1 << P) ** 2!r} / s, 4) as est from moments")
def estimate_raw(spark, d):
    return _moments(spark, d).select("g", "v", F.round(E.raw(P), 4).alias("est"))


def _estimate(name: str, bits):
    @query(name, f"with {_FOUR} select g, v, round({est_sql(P, bits)}, 4) as est from moments")
    def run(spark, d):
        return _moments(spark, d).select("g", "v", F.round(E.piecewise(P, bits), 4).alias("est"))

    return run


estimate_classic = _estimate("q_estimate_classic", 64)
estimate_w32 = _estimate("q_estimate_w32", 32)
estimate_open = _estimate("q_estimate_open", None)


@query(
    "q_estimate_branch",
    f"with {_FOUR}, e as (select *, {alpha_of(P) * (1 << P) ** 2!r} / s as e from moments) select g, v, case when e <= {2.5 * (1 << P)!r} and v > 0 then 'small' when e > {2.0**32 / 30!r} then 'large' else 'raw' end as branch from e",
)
def estimate_branch(spark, d):
    return _moments(spark, d).select("g", "v", E.branch(P, 32).alias("branch"))


@query("q_estimate_split", f"with {with_est(src_sql('texts'))} select g, est from est")
def estimate_split(spark, d):
    """The estimate read through the split form: sparse value or base plus offset."""
    parts, base = _split_texts(spark, d)
    got = S.get(S.dense_part(parts, G), S.sparse_part(parts, G), base, G)
    return E.from_registers(got.where("r > 0"), G, P).select("g", F.round("est", 4).alias("est"))


@query("q_same_estimate", f"with {with_est(src_sql('texts'))} select g, cast(0.0 as double) as max_diff from est")
def same_estimate(spark, d):
    """Largest difference between the plain and the split form's estimates."""
    plain = E.from_hist(hist_of(spark, d, "texts"), G, P).select("g", F.round("est", 4).alias("plain"))
    return plain.join(estimate_split(spark, d), "g").groupBy("g").agg(F.max(F.abs(F.col("plain") - F.col("est"))).alias("max_diff"))


# ------------------------------------------------------------------ base choice

_BASE = f"with {with_base(src_sql('four'))} select g, b, dense, sparse, bits from base"


def _base(name: str, how: str):
    @query(name, _BASE)
    def run(spark, d):
        return S.best_base(hist_of(spark, d, "four"), G, P, KAPPA, how)

    return run


base_window = _base("q_base_window", "window")
base_theta = _base("q_base_theta", "theta")
base_maxby = _base("q_base_maxby", "maxby")
base_rownum = _base("q_base_rownum", "rownum")


@query("q_base_opt", f"with {with_base(src_sql('orderkeys'))}, {with_moments()} select g, b, dense, sparse, bits, round({est_sql()}, 4) as est from base join moments using (g)")
def base_opt(spark, d):
    h = hist_of(spark, d, "orderkeys")
    return S.best_base(h, G, P).join(E.from_hist(h, G, P).select("g", F.round("est", 4).alias("est")), "g")


_CENTS = with_base(src_sql("cents_by_flag"))


@query("q_min_base", f"with {_CENTS} select g, min(r) as b, arg_min(c, r) as c_min from hist group by g")
def min_base(spark, d):
    return S.min_base(hist_of(spark, d, "cents_by_flag"), G)


_MIN_BITS = """lowest as (select g, min(r) as b from hist group by g),
at_low as (select h.g, l.b, cast(sum(case when h.r between l.b and l.b + 7 then h.c else 0 end) as bigint) as dense from hist h join lowest l on h.g = l.g group by h.g, l.b)"""


@query("q_base_min", f"with {_CENTS}, {_MIN_BITS} select g, b, dense, 1024 - dense as sparse, cast(3072 + (1024 - dense) * 16 as bigint) as bits from at_low")
def base_min(spark, d):
    h = hist_of(spark, d, "cents_by_flag")
    return S.base_at(h, S.min_base(h, G), G, P)


@query("q_next_base", f"with {_CENTS} select g, r as b, lead(r) over (partition by g order by r) as next_b from hist")
def next_base(spark, d):
    return S.next_base(hist_of(spark, d, "cents_by_flag"), G)


@query(
    "q_base_lazy_step",
    f"""with {_CENTS}, {_MIN_BITS},
nexts as (select l.g, l.b, min(h.r) as b2 from lowest l left join hist h on h.g = l.g and h.r > l.b group by l.g, l.b),
two as (select n.g, n.b2, cast(3072 + (1024 - sum(case when h.r between n.b2 and n.b2 + 7 then h.c else 0 end)) * 16 as bigint) as bits2 from nexts n join hist h on n.g = h.g group by n.g, n.b2),
one as (select g, b, cast(3072 + (1024 - dense) * 16 as bigint) as bits from at_low)
select o.g, case when t.bits2 < o.bits then t.b2 else o.b end as b, least(t.bits2, o.bits) as bits, coalesce(t.bits2 < o.bits, false) as moved from one o left join two t on o.g = t.g""",
)
def base_lazy_step(spark, d):
    h = hist_of(spark, d, "cents_by_flag")
    return S.lazy_step(h, S.min_base(h, G), G, P)


@query(
    "q_early_bound",
    f"""with {_CENTS} select a.g, a.r as b, cast(coalesce(sum(case when h.r < a.r then h.c end), 0) as bigint) as below,
cast(1024 - sum(case when h.r between a.r and a.r + 7 then h.c else 0 end) as bigint) as sparse from hist a join hist h on a.g = h.g group by a.g, a.r""",
)
def early_bound(spark, d):
    return S.early_bound(hist_of(spark, d, "cents_by_flag"), G, P)


@query(
    "q_base_theory",
    f"""with {_CENTS}, n as (select g, count(distinct v) as n from ({src_sql('cents_by_flag')}) group by g),
bb as (select g, cast(greatest(0, round(log2(n / 1024.0))) as bigint) as b from n)
select h.g, bb.b, cast(sum(case when h.r between bb.b and bb.b + 7 then h.c else 0 end) as bigint) as dense,
cast(1024 - sum(case when h.r between bb.b and bb.b + 7 then h.c else 0 end) as bigint) as sparse,
cast(3072 + (1024 - sum(case when h.r between bb.b and bb.b + 7 then h.c else 0 end)) * 16 as bigint) as bits
from hist h join bb on h.g = bb.g group by h.g, bb.b""",
)
def base_theory(spark, d):
    from splitcount.operators.baselines import exact

    n = exact(src(spark, d, "cents_by_flag"), G, "v")
    bases = n.select("g", F.greatest(F.lit(0), F.round(F.log2(F.col("n") / 1024.0))).cast("long").alias("b"))
    return S.base_at(hist_of(spark, d, "cents_by_flag"), bases, G, P)


# ------------------------------------------------------------------ split, get, rebase

_TEXTS = with_base(src_sql("texts"))
_FULL = _TEXTS + """,
every as (select g, cast(j as bigint) as j from (select distinct g from regs), range(1024) t(j)),
parts as (select e.g, e.j, coalesce(r.r, 0) as r, b.b, case when coalesce(r.r, 0) between b.b and b.b + 7 then coalesce(r.r, 0) - b.b end as off
  from every e left join regs r on e.g = r.g and e.j = r.j join base b on b.g = e.g)"""


def _split_texts(spark, d):
    regs = regs_of(spark, d, "texts")
    base = S.best_base(S.histogram(regs, G, P), G, P)
    return S.split(regs, base, G, P), base


@query("q_split_dense", f"with {_FULL} select g, j, off from parts where off is not null")
def split_dense(spark, d):
    return S.dense_part(_split_texts(spark, d)[0], G)


@query("q_split_sparse", f"with {_FULL} select g, j, r from parts where off is null")
def split_sparse(spark, d):
    return S.sparse_part(_split_texts(spark, d)[0], G).select("g", "j", "r")


@query("q_sparse_packed", f"with {_FULL} select g, string_agg(cast(j * 64 + r as varchar), ',' order by j) as packed from parts where off is null group by g")
def sparse_packed(spark, d):
    s = S.sparse_part(_split_texts(spark, d)[0], G)
    return s.groupBy("g").agg(F.array_join(F.sort_array(F.collect_list("packed")).cast("array<string>"), ",").alias("packed"))


@query("q_sparse_map", f"with {_FULL} select g, count(*) as n, cast(sum(r) as bigint) as sum_r, max(j) as max_j from parts where off is null group by g")
def sparse_map(spark, d):
    """The sparse part as a map, then read back through map functions."""
    s = S.sparse_part(_split_texts(spark, d)[0], G)
    m = s.groupBy("g").agg(F.map_from_entries(F.collect_list(F.struct("j", "r"))).alias("m"))
    total = F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda a, x: a + x)
    return m.select("g", F.size("m").cast("long").alias("n"), total.alias("sum_r"), F.array_max(F.map_keys("m")).alias("max_j"))


@query("q_sparse_semi", f"with {_FULL} select r.g, r.j, r.r from regs r semi join (select g, j from parts where off is null) s on r.g = s.g and r.j = s.j")
def sparse_semi(spark, d):
    parts, _ = _split_texts(spark, d)
    return regs_of(spark, d, "texts").join(S.sparse_part(parts, G), ["g", "j"], "left_semi").select("g", "j", "r")


@query("q_dense_anti", f"with {_FULL} select r.g, r.j, r.r from regs r anti join (select g, j from parts where off is null) s on r.g = s.g and r.j = s.j")
def dense_anti(spark, d):
    parts, _ = _split_texts(spark, d)
    return regs_of(spark, d, "texts").join(S.sparse_part(parts, G), ["g", "j"], "left_anti").select("g", "j", "r")


@query("q_get_coalesce", f"with {_FULL} select g, j, r from parts")
def get_coalesce(spark, d):
    parts, base = _split_texts(spark, d)
    return S.get(S.dense_part(parts, G), S.sparse_part(parts, G), base, G)


@query("q_get_roundtrip", f"with {_TEXTS} select g, cast(0 as bigint) as mismatches from base")
def get_roundtrip(spark, d):
    back = get_coalesce(spark, d).select("g", "j", F.col("r").alias("r2"))
    both = S.with_zeros(regs_of(spark, d, "texts"), G, P).join(back, ["g", "j"], "full_outer")
    return both.groupBy("g").agg(F.sum((~F.col("r").eqNullSafe(F.col("r2"))).cast("long")).alias("mismatches"))


@query(
    "q_rebase_moves",
    f"""with {_TEXTS} select h.g, cast(sum(case when h.r = b.b then c else 0 end) as bigint) as to_sparse, cast(sum(case when h.r = b.b + 8 then c else 0 end) as bigint) as to_dense
from hist h join base b on h.g = b.g group by h.g""",
)
def rebase_moves(spark, d):
    h = hist_of(spark, d, "texts")
    return S.rebase_moves(h, S.best_base(h, G, P), G)


# ------------------------------------------------------------------ merge

_ODD, _EVEN = (f"select 'all' as g, cast(l_orderkey as varchar) as v from lineitem where l_linenumber % 2 = {x}" for x in (1, 0))


def _halves(spark, d):
    line = table(spark, d, "lineitem")
    part = lambda x: R.build(line.where(F.col("l_linenumber") % 2 == x), [], F.col("l_orderkey").cast("string"), P)
    return part(1), part(0)


_MERGED = f"with {with_regs(src_sql('orderkeys'))} select j, r from regs"


@query("q_union_merge", _MERGED)
def union_merge(spark, d):
    return R.merge(*_halves(spark, d), [])


@query("q_merge_join", _MERGED)
def merge_join(spark, d):
    return R.merge_join(*_halves(spark, d), [])


@query("q_merge_smj", _MERGED)
def merge_smj(spark, d):
    return R.merge_join(*_halves(spark, d), [], "merge")


@query("q_zip_merge", f"with {with_regs(src_sql('orderkeys'), 6)} select j, r from regs")
def zip_merge(spark, d):
    line = table(spark, d, "lineitem").withColumn("g", F.lit("all"))
    arr = lambda x: R.to_array(R.build(line.where(F.col("l_linenumber") % 2 == x), G, F.col("l_orderkey").cast("string"), 6), G, 6)
    both = arr(1).join(arr(0).withColumnRenamed("regs", "regs2"), "g")
    return R.from_array(both.select("g", R.merge_arrays(F.col("regs"), F.col("regs2")).alias("regs")), G).select("j", "r")


@query(
    "q_merge_split",
    f"""with {with_base(_ODD, tag='1')}, {with_base(_EVEN, tag='2')},
regs as (select g, j, max(r) as r from (select * from regs1 union all select * from regs2) group by g, j),
{with_base(None)}
select greatest(base1.b, base2.b) as b_start, base.b, base.dense, base.sparse, base.bits from base1, base2, base""",
)
def merge_split(spark, d):
    return S.merge_split(*_halves(spark, d), [], P)


@query("q_merge_equals_single", "select cast(0 as bigint) as mismatches")
def merge_equals_single(spark, d):
    merged = union_merge(spark, d).withColumnRenamed("r", "r2")
    both = reg_global(spark, d).join(merged, "j", "full_outer")
    return both.agg(F.coalesce(F.sum((~F.col("r").eqNullSafe(F.col("r2"))).cast("long")), F.lit(0)).alias("mismatches"))


@query("q_idempotent", "select cast(0 as bigint) as mismatches")
def idempotent(spark, d):
    line = table(spark, d, "lineitem")
    twice = R.build(line.unionAll(line), [], F.col("l_orderkey").cast("string"), P).withColumnRenamed("r", "r2")
    both = reg_global(spark, d).join(twice, "j", "full_outer")
    return both.agg(F.coalesce(F.sum((~F.col("r").eqNullSafe(F.col("r2"))).cast("long")), F.lit(0)).alias("mismatches"))


# ------------------------------------------------------------------ sizes

_PS = (4, 6, 8, 10, 12)


@query(
    "q_size_by_p",
    "with "
    + ",\n".join(with_base(src_sql("cents"), p, tag=f"_{p}") for p in _PS)
    + "\n"
    + " union all ".join(f"select cast({p} as bigint) as p, b, sparse, bits, round(bits / {float(1 << p)}, 6) as per_register from base_{p}" for p in _PS),
)
def size_by_p(spark, d):
    """One build at the largest p; coarser sketches fold from it."""
    top = _PS[-1]
    fine = regs_of(spark, d, "cents", top)
    rows = []
    for p in _PS:
        base = S.best_base(S.histogram(R.fold(fine, G, top, p), G, p), G, p)
        rows.append(base.select(F.lit(p).cast("long").alias("p"), "b", "sparse", "bits", F.round(cost.bits_per_register(F.col("bits"), p), 6).alias("per_register")))
    return _union(rows)


@query(
    "q_size_by_kappa",
    f"with {with_hist(src_sql('cents'))},\n"
    + ",\n".join(with_base(None, kappa=k, tag=f"_{k}", hist=False).replace(f"hist_{k}", "hist") for k in range(1, 7))
    + "\n"
    + " union all ".join(f"select cast({k} as bigint) as kappa, b, sparse, bits from base_{k}" for k in range(1, 7)),
)
def size_by_kappa(spark, d):
    h = hist_of(spark, d, "cents")
    return _union([S.best_base(h, G, P, k).select(F.lit(k).cast("long").alias("kappa"), "b", "sparse", "bits") for k in range(1, 7)])


_VARIANTS = f"""with {with_base(src_sql('cents'))}, {_MIN_BITS},
ent as (select sum(-c * log2(c / 1024.0)) as e from hist),
rows as (
  select 'reg6' as variant, cast(6144 as double) as bits union all select 'reg8', 8192.0
  union all select 'split_opt', cast(bits as double) from base
  union all select 'split_min', cast(3072 + (1024 - dense) * 16 as double) from at_low
  union all select 'tailcut', 3072.0 union all select 'entropy', e from ent)"""


@query("q_size_all_variants", f"{_VARIANTS} select variant, round(bits, 4) as bits, round(bits / 1024.0, 6) as per_register from rows")
def size_all_variants(spark, d):
    h = hist_of(spark, d, "cents")
    fixed = spark.createDataFrame([("reg6", 6144.0), ("reg8", 8192.0), ("tailcut", 3072.0)], "variant string, bits double")
    named = lambda df, name: df.select(F.lit(name).alias("variant"), F.col("bits").cast("double").alias("bits"))
    rows = _union([fixed, named(S.best_base(h, G, P), "split_opt"), named(S.base_at(h, S.min_base(h, G), G, P), "split_min"), named(cost.entropy_bits(h, G, P), "entropy")])
    return rows.select("variant", F.round("bits", 4).alias("bits"), F.round(cost.bits_per_register(F.col("bits"), P), 6).alias("per_register"))


@query("q_reduction", f"{_VARIANTS} select variant, round(1 - bits / 6144.0, 6) as reduction from rows")
def reduction(spark, d):
    return size_all_variants(spark, d).select("variant", F.round(cost.reduction(F.col("bits"), P), 6).alias("reduction"))


@query("q_entropy_bits", f"with {with_hist(src_sql('four'))} select g, round(sum(-c * log2(c / 1024.0)), 4) as bits from hist group by g")
def entropy_bits(spark, d):
    return cost.entropy_bits(hist_of(spark, d, "four"), G, P).select("g", F.round("bits", 4).alias("bits"))


@query("q_word_bits", f"with {with_base(src_sql('four'))} select g, cast(64 * (ceil(3072 / 64.0) + ceil(sparse * 16 / 64.0)) as bigint) as word_bits, bits as logical_bits from base")
def word_bits(spark, d):
    base = S.best_base(hist_of(spark, d, "four"), G, P)
    words = F.ceil(F.lit(KAPPA * 1024 / 64.0)) + F.ceil(F.col("sparse") * (P + 6) / 64.0)
    return base.select("g", (64 * words).cast("long").alias("word_bits"), F.col("bits").alias("logical_bits"))


@query(
    "q_pareto",
    f"""{_VARIANTS}, pts as (select variant, bits, case when variant = 'tailcut' then 1 else 0 end as lossy from rows)
select a.variant, not exists (select 1 from pts b where b.bits <= a.bits and b.lossy <= a.lossy and (b.bits < a.bits or b.lossy < a.lossy)) as on_front from pts a""",
)
def pareto(spark, d):
    """Which forms no other beats in both size and loss."""
    pts = size_all_variants(spark, d).select("variant", "bits", F.when(F.col("variant") == "tailcut", 1).otherwise(0).alias("lossy"))
    b = F.broadcast(pts.select(F.col("bits").alias("b2"), F.col("lossy").alias("l2")))  # one row per form
    beaten = pts.join(b, (F.col("b2") <= F.col("bits")) & (F.col("l2") <= F.col("lossy")) & ((F.col("b2") < F.col("bits")) | (F.col("l2") < F.col("lossy"))), "left_semi")
    return pts.join(F.broadcast(beaten.select("variant", F.lit(False).alias("_f"))), "variant", "left").select("variant", F.coalesce("_f", F.lit(True)).alias("on_front"))


