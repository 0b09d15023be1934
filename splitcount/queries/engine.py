"""Sources, sinks and streams: each runs end to end in a folder of its own below the shared one."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from splitcount.operators import aggregate as A
from splitcount.operators import estimate as E
from splitcount.operators import registers as R
from splitcount.queries.applications import _est
from splitcount.queries.methods import G, regs_of
from splitcount.queries.registry import P, query, src, src_sql, with_est
from splitcount.session import cut, shared_dir, table
from splitcount.sources import pairs_source
from splitcount.sources.store import FORMATS, SketchStore, load, save
from splitcount.streaming import panes


def _folder(spark, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


#: Parts in time order, and files of each; a batch takes a whole part.
_PARTS, _FILES = 4, 4
#: The last part of a stream that is closed: one event this long after all others, so that every window before it ends.
_CLOSING = "interval 60 days"


def _staged(spark, d, closing: bool = False) -> str:
    """Events as parts that appear in time order, as a stream would find them, each written by several tasks."""
    path = _folder(spark, "events")
    ev = table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    span = ev.agg(F.unix_micros(F.min("ts")).alias("lo"), F.unix_micros(F.max("ts")).alias("hi")).first()
    lo, hi = span["lo"] or 0, span["hi"] or 0
    part = F.least(F.lit(_PARTS - 1), F.floor((F.unix_micros("ts") - lo) * _PARTS / (hi - lo + 1)))
    for k in range(_PARTS):
        # Even shares, so that each part has as many files as a batch takes.
        ev.where(part == k).repartition(_FILES).write.mode("append").parquet(path)
    if closing:
        last = spark.range(1).select(F.lit(-1).cast("long").alias("event_id"), (F.timestamp_micros(F.lit(hi)) + F.expr(_CLOSING)).alias("ts"), F.lit(-1).cast("long").alias("user_id"))
        last.withColumns({c: F.lit(None).cast(t) for c, t in ev.dtypes if c not in last.columns}).select(*ev.columns).write.mode("append").parquet(path)
    return path


def _events(spark, d, closing: bool = False):
    return panes.source(spark, _staged(spark, d, closing), files_per_batch=_FILES)


def _run(spark, stream, mode: str, name: str):
    """All that is there, batch by batch, to a Parquet table."""
    path = _folder(spark, f"{name}-out")
    out = stream.writeStream.outputMode(mode).option("checkpointLocation", _folder(spark, name)).trigger(availableNow=True)
    if mode == "append":
        q = out.format("parquet").option("path", path).start()
    else:
        q = out.foreachBatch(lambda batch, k: batch.write.mode("overwrite").parquet(f"{path}/batch={k}")).start()  # a replay writes the same place
    try:
        q.awaitTermination()
    finally:
        q.stop()
    return spark.read.schema(stream.schema).parquet(path)


_DAILY = f"with {with_est('select cast(ts as date) as g, cast(user_id as varchar) as v from events')} select strftime(g, '%Y-%m-%d') as pane, est from est"


@query("q_store_upsert", _DAILY)
def store_upsert(spark, d):
    """Two overlapping batches of daily sketches, the second one replayed; the store equals one pass."""
    store = SketchStore(spark, _folder(spark, "store"))
    write = panes.publish(store, "user_id", P)
    ev = table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    write(ev.where("event_id % 3 <> 0"), 0)
    for again in (1, 1):
        write(ev.where("event_id % 3 <> 1"), again)
    return store.read().select(F.date_format("pane", "yyyy-MM-dd").alias("pane"), F.round(A.sketch_estimate("sketch"), 4).alias("est"))


@query("q_store_asof", f"with {with_est('select event_type, cast(ts as date) as g, cast(user_id as varchar) as v from events', cols='event_type, g')}, k as (select event_type, max(g) as g from est where g <= date '2024-01-15' group by event_type) select event_type, strftime(g, '%Y-%m-%d') as pane, est from est join k using (event_type, g)")
def store_asof(spark, d):
    store = SketchStore(spark, _folder(spark, "store"), ("event_type",))
    panes.publish(store, "user_id", P)(table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp")), 0)
    return store.asof("2024-01-15").select("event_type", F.date_format("pane", "yyyy-MM-dd").alias("pane"), F.round(A.sketch_estimate("sketch"), 4).alias("est"))


@query("q_src_roundtrip", f"with {with_est(src_sql('texts'))}, f as (select unnest(['parquet', 'orc', 'json', 'csv', 'text']) as format) select format, g, est from est, f")
def src_roundtrip(spark, d):
    blobs = cut(A.pack_registers(regs_of(spark, d, "texts"), G, P))
    out = None
    for fmt in FORMATS:
        path = _folder(spark, fmt)
        save(blobs, path, fmt)
        one = load(spark, path, "g string, sketch binary", fmt).select(F.lit(fmt).alias("format"), "g", F.round(A.sketch_estimate("sketch"), 4).alias("est"))
        out = one if out is None else out.unionByName(one)
    return out


@query("q_src_pairs")
def src_pairs(spark, d):
    """Every event takes the generated pair of its id, by event type."""
    pairs_source.register(spark)
    events = table(spark, d, "events").select(F.col("event_id").alias("id"), F.col("event_type").alias("g"))
    n = (events.agg(F.max("id")).first()[0] or 0) + 1
    rows = spark.read.format("splitcount_pairs").option("n", n).option("p", P).load()
    return _est(R.from_pairs(events.join(rows, "id").select("g", "j", "r"), G), G)


@query("q_stream_tumbling", f"with {with_est('select cast(ts as date) as g, event_type, cast(user_id as varchar) as v from events', cols='g, event_type')} select strftime(g, '%Y-%m-%d') as pane, event_type, est from est")
def stream_tumbling(spark, d):
    """Registers as streaming state; the last update of each register counts."""
    regs = panes.tumbling_registers(_events(spark, d), ["event_type"], "user_id", P, "1 day", "40 days")
    got = R.from_pairs(_run(spark, regs, "update", "tumbling"), ["pane", "event_type"])
    return _est(got, ["pane", "event_type"]).select(F.date_format("pane", "yyyy-MM-dd").alias("pane"), "event_type", "est")


@query("q_stream_closed", _DAILY)
def stream_closed(spark, d):
    """Estimates of panes once they close, by two chained streaming aggregations."""
    got = _run(spark, panes.tumbling_moments(_events(spark, d, closing=True), [], "user_id", P, "1 day", "1 hour"), "append", "closed")
    return got.select(F.date_format("pane", "yyyy-MM-dd").alias("pane"), F.round("est", 4).alias("est"))


@query(
    "q_stream_sliding",
    f"with {with_est("select g, v from (select unnest([ts::date, ts::date - 1, ts::date - 2]) as g, cast(user_id as varchar) as v from events)")} select strftime(g, '%Y-%m-%d') as pane, est from est",
)
def stream_sliding(spark, d):
    regs = _run(spark, panes.tumbling_registers(_events(spark, d), [], "user_id", P, "1 day", "40 days"), "update", "sliding")
    wide = panes.sliding(R.from_pairs(regs, ["pane"]), [], "1 day", 3)
    return _est(wide, ["pane"]).select(F.date_format("pane", "yyyy-MM-dd").alias("pane"), "est")


_SESSIONS = """select start::date as g, cast(user_id as varchar) as v from (
  select user_id, s, min(ts) as start from (
    select user_id, ts, sum(case when before is null or ts >= before + interval 12 hour then 1 else 0 end) over (partition by user_id order by ts) as s
    from (select user_id, ts, lag(ts) over (partition by user_id order by ts) as before from events)) group by user_id, s)"""


@query("q_stream_sessions", f"with {with_est(_SESSIONS)} select strftime(g, '%Y-%m-%d') as pane, est from est")
def stream_sessions(spark, d):
    """Closed sessions per user, then distinct users with a session that starts on a day."""
    s = _run(spark, panes.sessions(_events(spark, d, closing=True), "user_id", "12 hours", "1 hour"), "append", "sessions")
    rows = s.select(F.col("start").cast("date").alias("pane"), F.col("user_id").cast("string").alias("v"))
    return _est(R.build(rows, ["pane"], "v", P), ["pane"]).select(F.date_format("pane", "yyyy-MM-dd").alias("pane"), "est")


@query("q_stream_state", f"with {with_est('select event_type as g, cast(user_id as varchar) as v from events')} select g as event_type, est from est")
def stream_state(spark, d):
    """One packed sketch per key as state; the last update of each key."""
    got = _run(spark, panes.blob_state(_events(spark, d), "event_type", "user_id", P), "update", "state")
    last = got.groupBy("event_type").agg(F.max_by("est", "n_changed").alias("est"))
    return last.select("event_type", F.round("est", 4).alias("est"))


@query("q_stream_late", _DAILY)
def stream_late(spark, d):
    """Files out of order: late rows merge into the store, since merging asks for no order."""
    path = _folder(spark, "late")
    ev = table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    ev.repartition(3, F.pmod(F.xxhash64("event_id"), F.lit(3))).write.parquet(path)
    store = SketchStore(spark, _folder(spark, "store"))
    q = panes.source(spark, path).writeStream.foreachBatch(panes.publish(store, "user_id", P)).option("checkpointLocation", _folder(spark, "late-log")).trigger(availableNow=True).start()
    q.awaitTermination()
    return store.read().select(F.date_format("pane", "yyyy-MM-dd").alias("pane"), F.round(A.sketch_estimate("sketch"), 4).alias("est"))


@query("q_stream_exact", "select count(distinct user_id) as n from events")
def stream_exact(spark, d):
    got = _run(spark, panes.exact_rival(_events(spark, d).select("ts", "user_id"), "user_id", "60 days"), "append", "exact")
    return got.agg(F.count("*").alias("n"))


@query("q_builtin_rsd")
def builtin_rsd(spark, d):
    """The engine's own sketch beside ours and the exact count, per group."""
    rows = src(spark, d, "four")
    theirs = rows.groupBy("g").agg(F.approx_count_distinct("v", 0.0325).alias("builtin"), F.count_distinct("v").alias("n"))
    ours = E.from_registers(R.build(rows, G, "v", P), G, P).select("g", F.round("est", 4).alias("est"))
    return theirs.join(ours, "g")
