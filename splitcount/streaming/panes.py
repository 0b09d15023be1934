"""Streams of events to sketches per pane: registers as state, blobs as state, and publishing.

Registers as state keep one row per (pane, keys, j) with the largest rank, a plain streaming aggregation;
blobs as state keep one value per key, and reject ranks that cannot change it before unpacking.  Sliding
windows merge panes of the slide's length; sessions are found per user before anything is counted.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from splitcount.functions.hashing import pairs
from splitcount.operators import estimate as E
from splitcount.operators import registers as R
from splitcount.operators.aggregate import pack_registers
from splitcount.operators.codec import Sketch
from splitcount.sources.store import SketchStore

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def source(spark: SparkSession, path: str, schema: str = EVENTS, files_per_batch: int = 1) -> DataFrame:
    """Events that arrive as Parquet files."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def tumbling_registers(events: DataFrame, keys: list[str], value: str, p: int, window: str, watermark: str, ts: str = "ts") -> DataFrame:
    """(pane, keys.., j, r): streaming maximum per register and pane; update or append mode."""
    timed = events.withWatermark(ts, watermark)
    rows = pairs(timed, [ts, *keys], F.col(value).cast("string"), p)
    return rows.groupBy(F.window(ts, window).alias("_w"), *keys, "j").agg(F.max("r").alias("r")).select(F.col("_w.start").alias("pane"), *keys, "j", "r")


def tumbling_moments(events: DataFrame, keys: list[str], value: str, p: int, window: str, watermark: str, ts: str = "ts") -> DataFrame:
    """(pane, keys.., est) once a pane closes: a second streaming aggregation over the first, append mode."""
    timed = events.withWatermark(ts, watermark)
    rows = pairs(timed, [ts, *keys], F.col(value).cast("string"), p)
    regs = rows.groupBy(F.window(ts, window).alias("_w"), *keys, "j").agg(F.max("r").alias("r"))
    m = 1 << p
    per = regs.groupBy(F.window(F.window_time("_w"), window).alias("_v"), *keys).agg((F.sum(F.pow(F.lit(2.0), -F.col("r"))) + (m - F.count("*"))).alias("s"), (m - F.count("*")).alias("v"))
    return per.select(F.col("_v.start").alias("pane"), *keys, E.piecewise(p).alias("est"))


def sliding(registers: DataFrame, keys: list[str], slide: str, panes: int) -> DataFrame:
    """(pane, keys.., j, r): windows of ``panes`` slides from panes of one slide each; batch or per micro-batch."""
    starts = F.explode(F.array(*(F.col("pane") - F.expr(f"interval {slide}") * x for x in range(panes))))
    return R.from_pairs(registers.select(starts.alias("_p"), *keys, "j", "r").withColumnRenamed("_p", "pane"), ["pane", *keys])


def sessions(events: DataFrame, user: str, gap: str, watermark: str, ts: str = "ts") -> DataFrame:
    """(start, end, user): session bounds per user; the sketch comes after, over the closed sessions."""
    timed = events.withWatermark(ts, watermark)
    return timed.groupBy(F.session_window(ts, gap).alias("_w"), user).agg(F.count("*").alias("n")).select(F.col("_w.start").alias("start"), F.col("_w.end").alias("end"), user, "n")


def blob_state(events: DataFrame, key: str, value: str, p: int, kappa: int = 3, variant: str = "lazy") -> DataFrame:
    """(key, n_changed, est, bits) in update mode: one packed sketch per key as state."""
    rows = pairs(events, [key], F.col(value).cast("string"), p)

    def step(k: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        blob, low, changed = state.get if state.exists else (None, 0, 0)
        now = None
        for b in batches:
            high = b[b["r"] > low]  # nothing else can raise a register
            if len(high):
                if now is None:
                    now = Sketch.from_bytes(bytes(blob)) if blob is not None else Sketch.empty(p, kappa, variant=variant)
                now, n = now.offer_many(high["j"], high["r"])
                changed += n
        if now is not None:
            blob, low = now.to_bytes(), now.low
            state.update((blob, low, changed))
        s = now or Sketch.from_bytes(bytes(blob)) if blob is not None else Sketch.empty(p, kappa)
        yield pd.DataFrame({key: [k[0]], "n_changed": [changed], "est": [s.estimate()], "bits": [s.bits]})

    kind = dict(rows.dtypes)[key]
    return rows.groupBy(key).applyInPandasWithState(step, f"{key} {kind}, n_changed long, est double, bits long", "blob binary, low long, changed long", "update", GroupStateTimeout.NoTimeout)


def publish(store: SketchStore, value: str, p: int, ts: str = "ts"):
    """A foreachBatch function: daily sketches of the batch merge into the store; replays change nothing."""

    def run(batch: DataFrame, batch_id: int) -> None:
        keys = ["pane", *store.keys]
        rows = batch.withColumn("pane", F.col(ts).cast("date"))
        store.upsert(pack_registers(R.build(rows, keys, F.col(value).cast("string"), p), keys, p))

    return run


def exact_rival(events: DataFrame, value: str, watermark: str, ts: str = "ts") -> DataFrame:
    """Distinct items within the watermark, every one of them kept as state."""
    return events.withWatermark(ts, watermark).dropDuplicatesWithinWatermark([value])
