"""Packed sketches: functions, aggregates and table functions over binary columns."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql import types as T

from splitcount.functions.theory import bits_deep
from splitcount.operators import aggregate as A
from splitcount.operators.codec import CodedTrace, Sketch, Trace, coded_registers
from splitcount.operators.deep import deep_size
from splitcount.queries.methods import G, regs_of
from splitcount.queries.registry import P, query, src, src_sql, with_base, with_est, with_pairs, with_regs
from splitcount.session import table


def _blobs(spark, d, name="texts"):
    return A.pack_registers(regs_of(spark, d, name), G, P)


_EST = f"with {with_est(src_sql('texts'))} select g, est from est"


@query("q_udf_estimate", _EST)
def udf_estimate(spark, d):
    return _blobs(spark, d).select("g", F.round(A.sketch_estimate("sketch"), 4).alias("est"))


@query("q_udf_bits", f"with {with_base(src_sql('texts'))} select g, bits from base")
def udf_bits(spark, d):
    return _blobs(spark, d).select("g", A.sketch_bits("sketch").alias("bits"))


@query("q_udf_get", f"with {with_regs(src_sql('texts'))}, k as (select cast(k as bigint) as j from range(0, 1024, 64) t(k)), gs as (select distinct g from regs) select gs.g, k.j, coalesce(r.r, 0) as r from gs cross join k left join regs r on r.g = gs.g and r.j = k.j")
def udf_get(spark, d):
    """Sixteen registers of every sketch by look-up."""
    asked = _blobs(spark, d).select("g", "sketch", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(1023).cast("long"), F.lit(64).cast("long"))).alias("j"))
    return asked.select("g", "j", A.sketch_get("sketch", "j").alias("r"))


@query("q_udtf_registers", f"with {with_regs(src_sql('texts'))} select g, j, r from regs")
def udtf_registers(spark, d):
    A.register(spark)
    _blobs(spark, d).createOrReplaceTempView("splitcount_blobs")
    return spark.sql("select g, j, r from splitcount_blobs, lateral explode_registers(sketch) where r > 0")


@query("q_explode_registers", f"with {with_regs(src_sql('texts'))} select g, j, r from regs")
def explode_registers(spark, d):
    return A.explode_registers(_blobs(spark, d), G).where("r > 0").select("g", "j", "r")


@query("q_udaf_sketch", _EST)
def udaf_sketch(spark, d):
    """A blob per task and group, merged in two rounds."""
    blobs = A.distinct_sketch(src(spark, d, "texts"), G, "v", P, form="partial")
    return blobs.select("g", F.round(A.sketch_estimate("sketch"), 4).alias("est"))


@query("q_sql_agg", _EST)
def sql_agg(spark, d):
    """The aggregate under its SQL name, over registers."""
    A.register(spark)
    regs_of(spark, d, "texts").createOrReplaceTempView("splitcount_registers")
    return spark.sql("select g, round(sketch_estimate(s), 4) as est from (select g, sketch_agg(j, r, 10) as s from splitcount_registers group by g)")


@query("q_blob_rollup", f"with {with_est(src_sql('orderkeys'))} select est from est")
def blob_rollup(spark, d):
    """Per-flag blobs merged to one."""
    merged = A.rollup_sketches(_blobs(spark, d, "orderkeys_by_flag"), [])
    return merged.select(F.round(A.sketch_estimate("sketch"), 4).alias("est"))


@query("q_blob_merge2", f"with {with_est(src_sql('orderkeys_by_flag') + ' where l_returnflag <> ' + chr(39) + 'R' + chr(39), cols='g')}, regs2 as (select j, max(r) as r from regs group by j) select count(*) as n_nonzero, cast(sum(r) as bigint) as sum_r from regs2")
def blob_merge2(spark, d):
    """Two blobs merged by the scalar function."""
    b = _blobs(spark, d, "orderkeys_by_flag")
    one = b.where("g = 'A'").select(F.lit(1).alias("k"), F.col("sketch").alias("a"))
    two = b.where("g = 'N'").select(F.lit(1).alias("k"), F.col("sketch").alias("b"))
    both = one.join(two, "k").select(A.sketch_merge2("a", "b").alias("sketch"))
    return A.explode_registers(both, []).where("r > 0").agg(F.count("*").alias("n_nonzero"), F.sum("r").alias("sum_r"))


@query("q_blob_header", f"with {with_base(src_sql('texts'))} select g, cast({P} as bigint) as p, cast(3 as bigint) as kappa, b, sparse from base")
def blob_header(spark, d):
    """Header fields read off the bytes without unpacking."""
    at = lambda k: F.conv(F.hex(F.substring("sketch", k, 1)), 16, 10).cast("long")
    s = sum((at(17 + i) * (1 << 8 * i) for i in range(4)), F.lit(0).cast("long"))
    return _blobs(spark, d).select("g", at(2).alias("p"), at(3).alias("kappa"), at(4).alias("b"), s.alias("sparse"))


@query("q_blob_equal_forms", f"with {with_base(src_sql('texts'))} select g, true as same from base")
def blob_equal_forms(spark, d):
    """Packed at the end, or per task and merged: the same bytes."""
    partial = A.distinct_sketch(src(spark, d, "texts"), G, "v", P, form="partial").withColumnRenamed("sketch", "s2")
    return _blobs(spark, d).join(partial, "g").select("g", (F.col("sketch") == F.col("s2")).alias("same"))


# ------------------------------------------------------------------ sequential runs

_TRACE_P = 6


def _trace(spark, d, make, read, schema: str, p: int = _TRACE_P):
    """One ordered stream, events by id.  The rows that raise a register are found in parallel; only they, at most 64 m,
    change a sketch, and are read in order by one task."""
    from splitcount.functions.hashing import pairs
    from splitcount.operators.baselines import raising

    rows = raising(pairs(table(spark, d, "events"), ["event_id"], F.col("event_id").cast("string"), p), "event_id")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        t = make(p)
        for b in batches:
            for j, r in zip(b["j"].tolist(), b["r"].tolist(), strict=True):
                t.offer(j, r)
        yield pd.DataFrame([read(t)])

    return rows.repartition(1).sortWithinPartitions("event_id").mapInPandas(run, schema)


_COUNTS = "variant string, changed long, compress_calls long, rebases long, b long, sparse long, bits long, low long"


def _counted(t: Trace) -> dict:
    c = t.counters
    return {"variant": t.variant, "changed": c.changed, "compress_calls": c.compress_calls, "rebases": c.rebases, "b": t.base, "sparse": t.sparse, "bits": t.bits, "low": t.low}


def _trace_sql(last: str) -> str:
    """Every change of a register in order, and the list of how many registers hold each value after it."""
    m = 1 << _TRACE_P
    return f"""with recursive {with_pairs("select event_id, cast(event_id as varchar) as v from events", _TRACE_P, cols="event_id")},
f as (select j, r, min(event_id) as id from pairs group by j, r),
u as (select id, j, r, coalesce(max(r) over (partition by j order by id rows between unbounded preceding and 1 preceding), 0) as b from f),
c as (select row_number() over (order by id) as i, r, b from u where r > b),
d as (select i, v, sum(case when v = r then 1 when v = b then -1 else 0 end) as d from c, range(0, 65) t(v) group by i, v),
n as (select i, v, cast(case when v = 0 then {m} else 0 end + sum(d) over (partition by v order by i) as bigint) as n from d),
h as (select i, list(n order by v) as h from n group by i),
best as (select a.i, a.v as b, (select cast(sum(x.n) as bigint) from n x where x.i = a.i and x.v between a.v and a.v + 7) as dense from n a where a.n > 0),
opt as (select i, arg_min(b, {m + 1} * ({m} - dense) + b) as b, {m} - max(dense) as sparse from best group by i),
low as (select i, min(v) as b from n where n > 0 group by i),
lazy(i, base, calls, moves) as (
  select cast(0 as bigint), cast(0 as bigint), cast(0 as bigint), cast(0 as bigint)
  union all
  select i, case when moved then nxt else base end, calls + grows, moves + moved::int
  from (select *, grows = 1 and nxt is not null and list_sum(h[nxt + 1:nxt + 8]) > list_sum(h[base + 1:base + 8]) as moved
        from (select c.i, base, calls, moves, h, list_filter(range(base + 1, 65), lambda x: h[x + 1] > 0)[1] as nxt,
                     case when c.r >= base + 8 and c.b between base and base + 7 then 1 else 0 end as grows
              from lazy join c on c.i = lazy.i + 1 join h on h.i = c.i))),
z as (select max(i) as i from c), last_low as (select b as low from low join z using (i))
{last}"""


def _row_sql(variant: str, calls: str, moves: str, b: str, sparse: str, source: str) -> str:
    m = 1 << _TRACE_P
    return f"select '{variant}' as variant, z.i as changed, cast({calls} as bigint) as compress_calls, cast({moves} as bigint) as rebases, cast({b} as bigint) as b, cast({sparse} as bigint) as sparse, cast({3 * m} + ({sparse}) * {_TRACE_P + 6} as bigint) as bits, cast(low as bigint) as low from z, last_low, {source}"


_OPT_SQL = _trace_sql(_row_sql("opt", "z.i", "x.moves", "x.b", "x.sparse", "(select arg_max(b, i) as b, arg_max(sparse, i) as sparse, sum(case when b <> before then 1 else 0 end) as moves from (select *, coalesce(lag(b) over (order by i), 0) as before from opt)) x"))
_MIN_SQL = _trace_sql(_row_sql("min", "x.moves", "x.moves", "low", f"{1 << _TRACE_P} - x.dense", "(select y2.moves, b2.dense from (select sum(case when b <> before then 1 else 0 end) as moves from (select *, coalesce(lag(b) over (order by i), 0) as before from low)) y2, (select best.dense from best join z using (i) join low on low.i = best.i and low.b = best.b) b2) x"))
_LAZY_SQL = _trace_sql(_row_sql("lazy", "x.calls", "x.moves", "x.base", f"{1 << _TRACE_P} - x.dense", "(select calls, moves, base, list_sum(h[base + 1:base + 8]) as dense from lazy join z using (i) join h using (i)) x"))


@query("q_opt_trace", _OPT_SQL)
def opt_trace(spark, d):
    return _trace(spark, d, lambda p: Trace(p, variant="opt"), _counted, _COUNTS)


@query("q_lazy_trace", _LAZY_SQL)
def lazy_trace(spark, d):
    return _trace(spark, d, lambda p: Trace(p, variant="lazy"), _counted, _COUNTS)


@query("q_min_trace", _MIN_SQL)
def min_trace(spark, d):
    return _trace(spark, d, lambda p: Trace(p, variant="min"), _counted, _COUNTS)


@query("q_zstd_trace", _trace_sql("select z.i as decodes, z.i as encodes, cast(low as bigint) as low from z, last_low"))
def zstd_trace(spark, d):
    """The coded array is decoded and coded again at every change."""
    read = lambda t: {"decodes": t.decodes, "encodes": t.encodes, "low": t.low}
    return _trace(spark, d, CodedTrace, read, "decodes long, encodes long, low long")


@F.pandas_udf(T.LongType())
def _zstd_bits(blobs: pd.Series) -> pd.Series:
    return blobs.map(lambda b: 8 * len(coded_registers(Sketch.from_bytes(b).to_registers())))


_DEEP = ["kappa", "base", "sparse", "bits", "plain_sparse_bits"]


@F.pandas_udf(T.StructType([T.StructField(c, T.LongType()) for c in _DEEP]))
def _deep(blobs: pd.Series) -> pd.DataFrame:
    return pd.DataFrame([deep_size(Sketch.from_bytes(b)) for b in blobs], columns=_DEEP)


@query("q_zstd_size")
def zstd_size(spark, d):
    """Bits of byte-aligned registers under Zstandard, per group."""
    return _blobs(spark, d, "four").select("g", _zstd_bits("sketch").alias("bits"))


_DEEP_WIDTH = min(6, max(1, bits_deep(P)["bits"]))


@query(
    "q_deep_size",
    f"with {with_base(src_sql('four'), kappa=_DEEP_WIDTH)} select g, cast({_DEEP_WIDTH} as bigint) as kappa, b as base, sparse, cast({_DEEP_WIDTH << P} + case when sparse > 0 then sparse * (2 + ceil(log2({64 << P}.0 / sparse))) else 0 end as bigint) as bits, bits as plain_sparse_bits from base",
)
def deep_sizes(spark, d):
    """The narrower window with its coded sparse part, beside the plain sparse part."""
    got = _blobs(spark, d, "four").select("g", _deep("sketch").alias("x"))
    return got.select("g", "x.*")
