"""Operators around the sketches: cubes, windows, panes, overlap, strings, graph hops, profiling."""

from __future__ import annotations

from pyspark.sql import functions as F

from splitcount.functions import hashing as H
from splitcount.operators import estimate as E
from splitcount.operators import registers as R
from splitcount.operators.aggregate import sketch_estimate
from splitcount.operators.baselines import exact
from splitcount.queries.registry import P, est_sql, query, with_est, with_hist, with_moments, with_pairs, with_regs
from splitcount.session import table


def _est(regs, keys, p=P):
    return E.from_registers(regs, keys, p).select(*keys, F.round("est", 4).alias("est"))


# ------------------------------------------------------------------ grouping sets from one fine sketch

_FLAGS = "select l_returnflag as f, l_linestatus as s, cast(l_partkey as varchar) as v from lineitem"


def _flags(spark, d):
    line = table(spark, d, "lineitem")
    return R.build(line.select(F.col("l_returnflag").alias("f"), F.col("l_linestatus").alias("s"), F.col("l_partkey").cast("string").alias("v")), ["f", "s"], "v", P)


def _sets_sql(sets: str) -> str:
    return f"""with {with_pairs(_FLAGS, cols='f, s')},
g0 as (select coalesce(f, '*') || '/' || coalesce(s, '*') as g, j, max(r) as r from pairs group by grouping sets ({sets})),
regs as (select g, j, r from g0), {with_hist(None)}, {with_moments()}
select g, round({est_sql()}, 4) as est from moments"""


def _named(rows):
    return rows.select(F.concat(F.coalesce("f", F.lit("*")), F.lit("/"), F.coalesce("s", F.lit("*"))).alias("g"), "j", "r")


_CUBE = "(f, s, j), (f, j), (s, j), (j)"


@query("q_cube_direct", _sets_sql(_CUBE))
def cube_direct(spark, d):
    """Every pair enters all grouping sets."""
    line = table(spark, d, "lineitem").select(F.col("l_returnflag").alias("f"), F.col("l_linestatus").alias("s"), F.col("l_partkey").cast("string").alias("v"))
    pairs = H.pairs(line, ["f", "s"], "v", P)
    got = pairs.groupingSets([["f", "s", "j"], ["f", "j"], ["s", "j"], ["j"]], "f", "s", "j").agg(F.max("r").alias("r"))
    return _est(_named(got), ["g"])


@query("q_cube_from_sketch", _sets_sql(_CUBE))
def cube_from_sketch(spark, d):
    """The finest sketches are built once; coarser ones merge from them."""
    fine = _flags(spark, d)
    got = fine.groupingSets([["f", "s", "j"], ["f", "j"], ["s", "j"], ["j"]], "f", "s", "j").agg(F.max("r").alias("r"))
    return _est(_named(got), ["g"])


@query("q_grouping_sets", _sets_sql("(f, j), (s, j)"))
def grouping_sets(spark, d):
    got = _flags(spark, d).groupingSets([["f", "j"], ["s", "j"]], "f", "s", "j").agg(F.max("r").alias("r"))
    return _est(_named(got), ["g"])


_NATION = "select c_nationkey as k, cast(o_custkey as varchar) as v from orders join customer on o_custkey = c_custkey"


@query(
    "q_rollup_nation_region",
    f"""with {with_regs(_NATION, cols='k', tag='0')},
named as (select r_name, n_name, j, r from regs0 join nation on k = n_nationkey join region on n_regionkey = r_regionkey),
regs as (select r_name || '/' || n_name as g, j, r from named union all select r_name || '/*' as g, j, max(r) as r from named group by r_name, j),
{with_hist(None)}, {with_moments()} select g, round({est_sql()}, 4) as est from moments""",
)
def rollup_nation_region(spark, d):
    """Sketches per nation, named through two small dimension tables, then merged per region."""
    orders = table(spark, d, "orders").select("o_custkey")
    cust = table(spark, d, "customer").select("c_custkey", F.col("c_nationkey").alias("k"))
    regs = R.build(orders.join(cust, orders["o_custkey"] == cust["c_custkey"]), ["k"], F.col("o_custkey").cast("string"), P)
    nation = table(spark, d, "nation").join(table(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    named = regs.join(F.broadcast(nation.select(F.col("n_nationkey").alias("k"), "n_name", "r_name")), "k")  # a fixed dimension
    fine = named.select(F.concat("r_name", F.lit("/"), "n_name").alias("g"), "j", "r")
    coarse = R.from_pairs(named.select(F.concat("r_name", F.lit("/*")).alias("g"), "j", "r"), ["g"])
    return _est(fine.unionByName(coarse), ["g"])


# ------------------------------------------------------------------ time: panes, windows, sessions, as-of

_USERS = "cast(user_id as varchar) as v"


def _panes(spark, d, unit: str, keys=()):
    ev = table(spark, d, "events").withColumn("g", F.date_trunc(unit, F.col("ts")).cast("date" if unit == "day" else "timestamp"))
    return R.build(ev.select("g", *keys, F.col("user_id").cast("string").alias("v")), ["g", *keys], "v", P)


def _text(c="g", fmt="yyyy-MM-dd HH:mm"):
    return F.date_format(c, fmt)


@query("q_daily_users", f"with {with_est(f'select cast(ts as date) as g, {_USERS} from events')} select strftime(g, '%Y-%m-%d') as pane, est from est")
def daily_users(spark, d):
    return _est(_panes(spark, d, "day"), ["g"]).select(_text("g", "yyyy-MM-dd").alias("pane"), "est")


@query(
    "q_hourly_users",
    f"with {with_est(f"select date_trunc('hour', ts) as g, event_type, {_USERS} from events", cols='g, event_type')} select strftime(g, '%Y-%m-%d %H:%M') as pane, event_type, est from est",
)
def hourly_users(spark, d):
    return _est(_panes(spark, d, "hour", ["event_type"]), ["g", "event_type"]).select(_text().alias("pane"), "event_type", "est")


@query("q_window_tumbling", f"with {with_est(f"select time_bucket(interval 6 hour, ts, timestamp '1970-01-01') as g, {_USERS} from events")} select strftime(g, '%Y-%m-%d %H:%M') as pane, est from est")
def window_tumbling(spark, d):
    ev = table(spark, d, "events").select(F.window(F.col("ts").cast("timestamp"), "6 hours").alias("w"), F.col("user_id").cast("string").alias("v"))
    return _est(R.build(ev.select(F.col("w.start").alias("g"), "v"), ["g"], "v", P), ["g"]).select(_text().alias("pane"), "est")


@query(
    "q_window_sliding",
    f"""with {with_regs(f'select cast(ts as date) as g, {_USERS} from events', tag='0')},
moved as (select g - cast(x as integer) as g, j, r from regs0, range(3) t(x)), regs as (select g, j, max(r) as r from moved group by g, j), {with_hist(None)}, {with_moments()}
select strftime(g, '%Y-%m-%d') as pane, round({est_sql()}, 4) as est from moments""",
)
def window_sliding(spark, d):
    """Three-day windows every day, merged from one-day panes: an event enters one pane only."""
    days = _panes(spark, d, "day")
    into = days.select(F.explode(F.array(*(F.date_sub("g", x) for x in range(3)))).alias("g"), "j", "r")
    return _est(R.from_pairs(into, ["g"]), ["g"]).select(_text("g", "yyyy-MM-dd").alias("pane"), "est")


@query(
    "q_window_session",
    f"""with e as (select user_id, ts, coalesce(ts - lag(ts) over (partition by user_id order by ts, event_id) > interval 12 hour, true) as new, event_id from events),
s as (select user_id, event_id, ts, sum(cast(new as integer)) over (partition by user_id order by ts, event_id) as no from e),
b as (select *, min(ts) over (partition by user_id, no) as t0 from s),
src as (select cast(t0 as date) as g, user_id || ':' || no as v from b), {with_est('select g, v from src')}
select strftime(g, '%Y-%m-%d') as pane, est from est""",
)
def window_session(spark, d):
    """Sessions first, per user; then the sessions that begin on a day are counted."""
    from pyspark.sql import Window as W

    ev = table(spark, d, "events").select("user_id", "event_id", F.col("ts").cast("timestamp").alias("ts"))
    per = W.partitionBy("user_id").orderBy("ts", "event_id")
    gap = F.col("ts") - F.lag("ts").over(per) > F.expr("interval 12 hours")
    s = ev.withColumn("no", F.sum(F.coalesce(gap, F.lit(True)).cast("long")).over(per))
    s = s.withColumn("t0", F.min("ts").over(W.partitionBy("user_id", "no")))
    rows = s.select(F.col("t0").cast("date").alias("g"), F.concat(F.col("user_id").cast("string"), F.lit(":"), F.col("no").cast("string")).alias("v"))
    return _est(R.build(rows, ["g"], "v", P), ["g"]).select(_text("g", "yyyy-MM-dd").alias("pane"), "est")


@query(
    "q_running_distinct",
    f"""with {with_regs(f'select cast(ts as date) as g, {_USERS} from events', tag='0')}, days as (select distinct g from regs0),
regs as (select d.g, x.j, max(x.r) as r from days d join regs0 x on x.g <= d.g group by d.g, x.j), {with_hist(None)}, {with_moments()}
select strftime(g, '%Y-%m-%d') as pane, round({est_sql()}, 4) as est from moments""",
)
def running_distinct(spark, d):
    """Distinct users up to each day: a running maximum per register over the panes."""
    from pyspark.sql import Window as W

    days = _panes(spark, d, "day")
    upto = F.max("r").over(W.partitionBy("j").orderBy("g").rowsBetween(W.unboundedPreceding, 0))
    seen = days.withColumn("r", upto)
    # A register keeps its value until the next day that changes it.
    nxt = F.lead("g").over(W.partitionBy("j").orderBy("g"))
    spans = seen.withColumn("until", nxt)
    cal = days.select(F.col("g").alias("day")).distinct()
    got = spans.join(F.broadcast(cal), (F.col("day") >= F.col("g")) & (F.col("until").isNull() | (F.col("day") < F.col("until"))))  # one row per day
    return _est(got.select(F.col("day").alias("g"), "j", "r"), ["g"]).select(_text("g", "yyyy-MM-dd").alias("pane"), "est")


_PANES = "select date_trunc('month', l_shipdate)::date as g, cast(l_partkey as varchar) as v from lineitem"


def _months(spark, d):
    line = table(spark, d, "lineitem").select(F.trunc("l_shipdate", "month").alias("g"), F.col("l_partkey").cast("string").alias("v"))
    return R.build(line, ["g"], "v", P)


@query(
    "q_range_panes",
    f"""with {with_regs(_PANES, tag='0')}, q as (select distinct date_trunc('month', o_orderdate)::date as g from orders),
regs as (select q.g, x.j, max(x.r) as r from q join regs0 x on x.g between q.g - interval 2 month and q.g group by q.g, x.j), {with_hist(None)}, {with_moments()}
select strftime(g, '%Y-%m') as pane, round({est_sql()}, 4) as est from moments""",
)
def range_panes(spark, d):
    """Each order month with the panes of its last three months (a range join as a bounded fan-out)."""
    asked = table(spark, d, "orders").select(F.trunc("o_orderdate", "month").alias("g")).distinct()
    into = _months(spark, d).select(F.explode(F.array(*(F.add_months("g", x) for x in range(3)))).alias("g"), "j", "r")
    return _est(R.from_pairs(into.join(asked, "g", "left_semi"), ["g"]), ["g"]).select(_text("g", "yyyy-MM").alias("pane"), "est")


@query(
    "q_asof_pane",
    f"""with {with_est(_PANES)}, q as (select distinct cast(o_orderdate as date) as t from orders)
select strftime(q.t, '%Y-%m-%d') as key, strftime(e.g, '%Y-%m') as pane, e.est from q asof join est e on q.t >= e.g""",
)
def asof_pane(spark, d):
    """Latest monthly pane at or before each order date: one ordered pass, no range join."""
    from pyspark.sql import Window as W

    panes = _est(_months(spark, d), ["g"]).select(F.col("g").alias("t"), F.struct("g", "est").alias("pane"))
    asked = table(spark, d, "orders").select(F.col("o_orderdate").cast("date").alias("t")).distinct()
    none = F.lit(None).cast(panes.schema["pane"].dataType)
    # The pass splits by year; the last pane of the years before stands at the start (one row per year).
    ends = panes.groupBy(F.year("t").alias("_y")).agg(F.max_by("pane", "t").alias("pane"))
    years = asked.select(F.year("t").alias("_y")).distinct().join(ends, "_y", "full_outer")
    before = F.last("pane", ignorenulls=True).over(W.orderBy("_y").rowsBetween(W.unboundedPreceding, -1))
    carry = years.select(F.make_date("_y", F.lit(1), F.lit(1)).alias("t"), before.alias("pane"), "_y", F.lit(0).alias("_o"))
    rows = panes.select("t", "pane", F.year("t").alias("_y"), F.lit(1).alias("_o")).unionByName(asked.select("t", none.alias("pane"), F.year("t").alias("_y"), F.lit(2).alias("_o"))).unionByName(carry)
    last = F.last("pane", ignorenulls=True).over(W.partitionBy("_y").orderBy("t", "_o").rowsBetween(W.unboundedPreceding, 0))
    got = rows.withColumn("p", last).where("_o = 2 and p is not null")
    return got.select(_text("t", "yyyy-MM-dd").alias("key"), _text("p.g", "yyyy-MM").alias("pane"), F.col("p.est").alias("est"))


# ------------------------------------------------------------------ overlap of sets

_STATUS = "select o_orderstatus as g, cast(o_custkey as varchar) as v from orders"
_PAIRED = f"""with {with_regs(_STATUS, tag='0')}, gs as (select distinct g from regs0),
single as (select g, g as g2, j, r from regs0),
two as (select a.g as a, b.g as b from gs a join gs b on a.g < b.g),
regs as (select a || '+' || b as g, j, max(r) as r from two join regs0 x on x.g = two.a or x.g = two.b group by a, b, j
         union all select g, j, r from regs0), {with_hist(None)}, {with_moments()},
e as (select g, round({est_sql()}, 4) as est from moments)"""


#: Groups that are compared pair by pair; their number is checked first.
_MOST_GROUPS = 100


def _status(spark, d):
    return R.build(table(spark, d, "orders").select(F.col("o_orderstatus").alias("g"), F.col("o_custkey").cast("string").alias("v")), ["g"], "v", P)


def _overlap(spark, d):
    """(a, b, est_a, est_b, union_est) for pairs of groups; each group's registers go to its pairs."""
    regs = _status(spark, d)
    names = [r["g"] for r in regs.select("g").distinct().limit(_MOST_GROUPS + 1).collect()]
    if len(names) > _MOST_GROUPS:
        raise ValueError(f"pairs of more than {_MOST_GROUPS} groups are not compared all with all")
    pairs = [(a, b) for a in names for b in names if a < b]
    two = F.broadcast(spark.createDataFrame(pairs, "a string, b string"))  # of checked size
    union = R.from_pairs(regs.join(two, (F.col("g") == F.col("a")) | (F.col("g") == F.col("b"))), ["a", "b"])
    single = _est(regs, ["g"])  # as many rows as names
    got = _est(union, ["a", "b"]).withColumnRenamed("est", "union_est")
    for side in ("a", "b"):
        got = got.join(F.broadcast(single.select(F.col("g").alias(side), F.col("est").alias(f"est_{side}"))), side)
    return got


@query("q_pair_overlap", f"{_PAIRED} select a, b, u.est as union_est, round(x.est + y.est - u.est, 4) as inter_est from two join e u on u.g = a || '+' || b join e x on x.g = a join e y on y.g = b")
def pair_overlap(spark, d):
    return _overlap(spark, d).select("a", "b", "union_est", F.round(F.col("est_a") + F.col("est_b") - F.col("union_est"), 4).alias("inter_est"))


@query("q_sketch_jaccard", f"{_PAIRED} select a, b, round((x.est + y.est - u.est) / u.est, 4) as jaccard, round(u.est - y.est, 4) as a_only from two join e u on u.g = a || '+' || b join e x on x.g = a join e y on y.g = b")
def sketch_jaccard(spark, d):
    o = _overlap(spark, d)
    inter = F.col("est_a") + F.col("est_b") - F.col("union_est")
    return o.select("a", "b", F.round(inter / F.col("union_est"), 4).alias("jaccard"), F.round(F.col("union_est") - F.col("est_b"), 4).alias("a_only"))


def _words(spark, d, name):
    return table(spark, d, name).select(F.explode(F.split("text", " ")).alias("w"))


@query("q_intersect_truth", "select count(*) as n from (select unnest(string_split(text, ' ')) as w from documents intersect select unnest(string_split(text, ' ')) from benchmark)")
def intersect_truth(spark, d):
    return _words(spark, d, "documents").intersect(_words(spark, d, "benchmark")).agg(F.count("*").alias("n"))


@query("q_except_truth", "select count(*) as n from (select unnest(string_split(text, ' ')) as w from benchmark except select unnest(string_split(text, ' ')) from documents)")
def except_truth(spark, d):
    return _words(spark, d, "benchmark").subtract(_words(spark, d, "documents")).agg(F.count("*").alias("n"))


# ------------------------------------------------------------------ text, reports


@query("q_words_distinct", f"""with {with_est("select lang as g, unnest(string_split(text, ' ')) as v from documents")} select g, est from est""")
def words_distinct(spark, d):
    rows = table(spark, d, "documents").select(F.col("lang").alias("g"), F.explode(F.split("text", " ")).alias("v"))
    return _est(R.build(rows, ["g"], "v", P), ["g"])


@query("q_kmer_distinct", f"""with {with_est("select lang as g, unnest(list_transform(range(1, greatest(length(text) - 6, 1)), lambda i: substr(text, i, 8))) as v from documents")} select g, est from est""")
def kmer_distinct(spark, d):
    """Eight-character windows of every text per language."""
    # Slices that overlap by seven characters, each found in one pass; no row holds all windows of a text.
    parts = F.regexp_extract_all("text", F.lit("(?s)(?=(.{1,4103})).{1,4096}"), 1)
    rows = table(spark, d, "documents").select(F.col("lang").alias("g"), F.explode(parts).alias("part"))
    # A look-ahead yields the window at every character.
    rows = rows.select("g", F.explode(F.regexp_extract_all("part", F.lit("(?s)(?=(.{8}))"), 1)).alias("v"))
    return _est(R.build(rows, ["g"], "v", P), ["g"])


@query("q_host_distinct", f"""with {with_est("select regexp_extract(url, '^([a-z]+)://', 1) as g, regexp_extract(url, '://([^/]+)', 1) as v from pages")} select g, est from est""")
def host_distinct(spark, d):
    rows = table(spark, d, "pages").select(F.regexp_extract("url", "^([a-z]+)://", 1).alias("g"), F.regexp_extract("url", "://([^/]+)", 1).alias("v"))
    return _est(R.build(rows, ["g"], "v", P), ["g"])


@query("q_json_distinct", f"""with {with_est("select event_type as g, json_extract_string(props, '$.k') as v from events")} select g, est from est""")
def json_distinct(spark, d):
    rows = table(spark, d, "events").select(F.col("event_type").alias("g"), F.get_json_object("props", "$.k").alias("v"))
    return _est(R.build(rows, ["g"], "v", P), ["g"])


@query("q_user_turns", f"""with {with_est("select role as g, text as v from conversations")} select g, est from est""")
def user_turns(spark, d):
    rows = table(spark, d, "conversations").select(F.col("role").alias("g"), F.col("text").alias("v"))
    return _est(R.build(rows, ["g"], "v", P), ["g"])


@query("q_topk_estimate", f"with {with_est('select source as g, text as v from documents')} select g as source, est from est order by est desc, g limit 5")
def topk_estimate(spark, d):
    rows = table(spark, d, "documents").select(F.col("source").alias("g"), F.col("text").alias("v"))
    return _est(R.build(rows, ["g"], "v", P), ["g"]).select(F.col("g").alias("source"), "est").orderBy(F.desc("est"), "source").limit(5)


@query(
    "q_pivot",
    f"""with {with_est('select o_orderpriority as a, o_orderstatus as b, cast(o_custkey as varchar) as v from orders', cols='a, b')}
select a as priority, max(case when b = 'F' then est end) as f, max(case when b = 'O' then est end) as o, max(case when b = 'P' then est end) as p from est group by a""",
)
def pivot(spark, d):
    rows = table(spark, d, "orders").select(F.col("o_orderpriority").alias("a"), F.col("o_orderstatus").alias("b"), F.col("o_custkey").cast("string").alias("v"))
    got = _est(R.build(rows, ["a", "b"], "v", P), ["a", "b"])
    wide = got.groupBy(F.col("a").alias("priority")).pivot("b", ["F", "O", "P"]).agg(F.first("est"))
    return wide.select("priority", F.col("F").alias("f"), F.col("O").alias("o"), F.col("P").alias("p"))


_ORDERS = ("o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice", "o_orderdate", "o_orderpriority")


@query(
    "q_scan_profile",
    " union all ".join(f"select '{c}' as name, count(*) as n, count(*) - count({c}) as nulls, count(distinct {c}) as n_distinct from orders" for c in _ORDERS),
)
def scan_profile(spark, d):
    orders = table(spark, d, "orders")
    aggs = [f for c in _ORDERS for f in (F.count(c).alias(f"n_{c}"), F.count_distinct(c).alias(f"d_{c}"))]
    one = orders.agg(F.count("*").alias("n"), *aggs)
    return one.select(F.explode(F.array(*(F.struct(F.lit(c).alias("name"), F.col("n"), (F.col("n") - F.col(f"n_{c}")).alias("nulls"), F.col(f"d_{c}").alias("n_distinct")) for c in _ORDERS))).alias("x")).select("x.*")


#: Columns of every table, and how their items are written where a cast to text differs between engines.
_TABLES = {
    "region": ("r_regionkey", "r_name"),
    "nation": ("n_nationkey", "n_name", "n_regionkey"),
    "customer": ("c_custkey", "c_name", "c_nationkey", "c_acctbal", "c_mktsegment"),
    "supplier": ("s_suppkey", "s_name", "s_nationkey", "s_acctbal"),
    "part": ("p_partkey", "p_name", "p_brand", "p_type", "p_size", "p_retailprice"),
    "orders": _ORDERS,
    "lineitem": ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"),
    "events": ("event_id", "ts", "user_id", "event_type", "value", "props"),
    "documents": ("doc_id", "text", "lang", "source", "n_chars"),
    "pages": ("page_id", "url", "html"),
    "benchmark": ("item_id", "text"),
    "labels": ("doc_id", "quality", "toxic"),
    "conversations": ("conv_id", "turn", "role", "text"),
}
_CENTS = ("c_acctbal", "s_acctbal", "p_retailprice", "o_totalprice", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "value")
_TIMES = ("o_orderdate", "l_shipdate", "ts")


def _item_sql(c: str) -> str:
    return f"cast(cast(round({c} * 100) as bigint) as varchar)" if c in _CENTS else f"cast(epoch_us({c}) as varchar)" if c in _TIMES else f"cast({c} as varchar)"


_ITEMS = " union all ".join(f"select '{t}.{c}' as g, {_item_sql(c)} as v from {t}" for t, cs in _TABLES.items() for c in cs)


@query("q_profile_all", f"with {with_est(_ITEMS)}, n as (select g, count(distinct v) as n from ({_ITEMS}) group by g) select g, n, est from est join n using (g)")
def profile_all(spark, d):
    """Every column of every table, one scan for each table; the vectors have no text form and are left to exact search."""
    from splitcount.workloads import profile

    out = None
    for t, cs in _TABLES.items():
        one = profile(table(spark, d, t).select(*cs), P).select(F.concat(F.lit(f"{t}."), "name").alias("g"), "n", "est")
        out = one if out is None else out.unionByName(one)
    return out


_HOPS_P = 6


@query(
    "q_khop_neighbours",
    f"""with e as (select distinct l_partkey as a, l_suppkey as b from lineitem),
{with_regs('select a, cast(b as varchar) as v from e', _HOPS_P, tag='1', cols='a')},
back as (select e.b, x.j, max(x.r) as r from e join regs1 x on x.a = e.a group by e.b, x.j),
regs as (select e.a as g, x.j, max(x.r) as r from e join back x on x.b = e.b group by e.a, x.j),
{with_hist(None, _HOPS_P)}, {with_moments(_HOPS_P)} select g as part, round({est_sql(_HOPS_P)}, 4) as est from moments""",
)
def khop_neighbours(spark, d):
    """Suppliers that a part reaches in three steps over the supply graph, by merging sketches."""
    from splitcount.workloads import neighbourhood

    edges = table(spark, d, "lineitem").select(F.col("l_partkey").alias("a"), F.col("l_suppkey").alias("b")).distinct()
    return neighbourhood(edges, _HOPS_P, hops=3).select(F.col("g").alias("part"), F.round(sketch_estimate("sketch"), 4).alias("est"))


@query("q_exact_neighbours", "select l_suppkey as supplier, count(distinct l_partkey) as n from lineitem group by l_suppkey")
def exact_neighbours(spark, d):
    return exact(table(spark, d, "lineitem").select(F.col("l_suppkey").alias("supplier"), "l_partkey"), ["supplier"], "l_partkey")

