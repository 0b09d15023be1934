"""Exact top-k inner-product search by distributed histogram selection.

Every candidate is scored against a block of queries (a stated query set, taken in blocks of bounded
size).  Nothing is sorted globally: each round counts scores into per-query histogram bins over the
range still open, adds the counts of all tasks, and keeps the one bin that holds the k-th value, until
a bin is a single score.  A last pass keeps the rows above that score, plus per task the k smallest ids
that tie with it, and a ranking of those few rows gives the answer.

A task reports only its topmost bins up to its own k-th score; lower bins cannot hold the global k-th
value, so the counts that decide are complete while a task sends at most k bins per query.

Defined results: vectors that are null or hold a null or non-finite component take no part; of two
vectors of different lengths the shorter counts as padded with zeros; rows that repeat an id are rows
of their own (a query skips only its own row); products too large for exact double arithmetic are
computed with whole numbers and scores clip to the range of a long; no rows, or no queries, give an
empty result.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from splitcount.llm.common import cut

_TILE = 2048
_LONG = 1 << 63


def _blocks(id_col: str, vec_col: str, rows: int):
    """Vectors packed into dense tiles; the wire format between the rounds."""

    def tile(part: list[tuple[int, np.ndarray]]) -> pd.DataFrame:
        d = max(len(v) for _, v in part)
        m = np.zeros((len(part), d))
        for i, (_, v) in enumerate(part):
            m[i, : len(v)] = v
        with np.errstate(over="ignore"):
            top = float(np.abs(np.floor(256.0 * m)).max(initial=0))
        ids = np.array([i for i, _ in part], np.int64)
        return pd.DataFrame({"n": [len(part)], "d": [d], "top": [top], "ids": [ids.tobytes()], "m": [m.astype("<f8").tobytes()]})

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        part: list[tuple[int, np.ndarray]] = []
        for b in batches:
            for i, v in zip(b["i"], b["v"], strict=True):
                part.append((int(i), np.asarray(v, np.float64)))
                if len(part) == rows:
                    yield tile(part)
                    part = []
        if part:
            yield tile(part)

    return run


def _units(m: np.ndarray, whole: bool) -> np.ndarray:
    """floor(256 x), as exact doubles or as Python integers."""
    if not whole:
        return np.floor(256.0 * m)
    out = np.empty(m.shape, object)
    for at, x in np.ndenumerate(m):
        out[at] = int(x) * 256 if abs(x) > 2.0**53 else math.floor(256 * x)
    return out


class _Queries:
    """One block of queries as every task sees it; size bounded by the block length."""

    def __init__(self, rows: list, top_candidate: float, d_all: int):
        self.ids = [r["id"] for r in rows]
        self.own: dict[int, list[tuple[int, int]]] = {}
        for q, r in enumerate(rows):
            self.own.setdefault(r["block"], []).append((q, r["at"]))
        d = max(len(r["v"]) for r in rows)
        m = np.zeros((len(rows), d))
        for q, r in enumerate(rows):
            m[q, : len(r["v"])] = r["v"]
        with np.errstate(over="ignore"):
            top = float(np.abs(np.floor(256.0 * m)).max(initial=0))
        bound = top * top_candidate * max(1, min(d, d_all))
        self.whole = not bound < 2.0**52
        self.f4 = bound < 2.0**23
        u = _units(m, self.whole)
        self.m = u.astype(np.float32) if self.f4 else u
        self.bound = _LONG if self.whole else int(bound) + 1

    def scores(self, block: int, n: int, d: int, raw: bytes) -> tuple[np.ndarray, np.ndarray]:
        """Scores (queries x tile) as whole numbers, and which of them count."""
        c = _units(np.frombuffer(raw, "<f8").reshape(n, d), self.whole)
        w = min(d, self.m.shape[1])
        if self.f4:
            c = c.astype(np.float32)
        s = self.m[:, :w] @ c[:, :w].T if w else np.zeros((len(self.ids), n))
        if self.whole:
            s = np.array([[max(-_LONG, min(_LONG - 1, int(x))) for x in r] for r in s], np.int64).reshape(len(self.ids), n)
        else:
            s = s.astype(np.int32 if self.f4 else np.int64)
        ok = np.ones(s.shape, bool)
        for q, at in self.own.get(block, ()):
            ok[q, at] = False
        return s, ok


def _histogram(q: _Queries, lo: np.ndarray, shift: np.ndarray, need: np.ndarray, bins: int):
    """Counts per query and bin of [lo, lo + bins << shift), topmost bins first, as far as ``need``."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        counts = np.zeros(len(q.ids) * bins, np.int64)
        row = (np.arange(len(q.ids)) * bins)[:, None]
        wide = np.int64 if q.bound >= 1 << 30 else np.int32
        low, by = lo.astype(wide)[:, None], shift.astype(wide)[:, None]
        for b in batches:
            for block, n, d, raw in zip(b["block"], b["n"], b["d"], b["m"], strict=True):
                s, ok = q.scores(block, n, d, raw)
                if q.whole:  # the distance from lo may pass a signed long
                    ok &= s >= low
                    at = ((s.astype(np.uint64) - low.astype(np.uint64)) >> by.astype(np.uint64)).astype(np.uint64)
                    ok &= at < bins
                    at = at.astype(np.int64)
                else:
                    at = (s - low) >> by
                    ok &= (at >= 0) & (at < bins)
                counts += np.bincount((at + row)[ok], minlength=len(counts))
        counts = counts.reshape(len(q.ids), bins)
        above = np.cumsum(counts[:, ::-1], axis=1)[:, ::-1] - counts
        i, j = np.nonzero((counts > 0) & (above < need[:, None]))
        yield pd.DataFrame({"q": i, "bin": j, "c": counts[i, j]})

    return run


def _survivors(q: _Queries, kth: np.ndarray, k: int):
    """Rows above the k-th score, and per task and query the k smallest ids among its ties."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        tq = np.empty(0, np.int64)
        ti = np.empty(0, np.int64)
        for b in batches:
            for block, n, d, ids, raw in zip(b["block"], b["n"], b["d"], b["ids"], b["m"], strict=True):
                s, ok = q.scores(block, n, d, raw)
                ids = np.frombuffer(ids, np.int64)
                i, j = np.nonzero(ok & (s > kth[:, None]))
                if len(i):
                    yield pd.DataFrame({"q": i, "vec_id": ids[j], "score": s[i, j].astype(np.int64)})
                i, j = np.nonzero(ok & (s == kth[:, None]))
                tq, ti = np.concatenate((tq, i)), np.concatenate((ti, ids[j]))
                order = np.lexsort((ti, tq))
                tq, ti = tq[order], ti[order]
                if len(tq):
                    start = np.flatnonzero(np.r_[True, tq[1:] != tq[:-1]])
                    place = np.arange(len(tq)) - np.repeat(start, np.diff(np.r_[start, len(tq)]))
                    tq, ti = tq[place < k], ti[place < k]
        yield pd.DataFrame({"q": tq, "vec_id": ti, "score": kth[tq].astype(np.int64)})

    return run


def top_k(vectors: DataFrame, is_query, id_col: str = "vec_id", vec_col: str = "embedding", k: int = 5, query_block: int = 4096, bins: int = 512) -> DataFrame:
    """(query_id, rank, vec_id, score); ``is_query`` is a condition on the columns of ``vectors``."""
    spark: SparkSession = vectors.sparkSession
    v = F.col(vec_col)
    finite = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    usable = vectors.where(F.col(id_col).isNotNull() & v.isNotNull() & finite).select(
        F.col(id_col).cast("long").alias("i"), v.cast("array<double>").alias("v"), F.coalesce(is_query, F.lit(False)).alias("ask")
    )
    schema = "n int, d int, top double, ids binary, m binary"
    tiles = cut(usable.select("i", "v").mapInPandas(_blocks("i", "v", _TILE), schema).withColumn("block", F.monotonically_increasing_id()))
    asked = usable.where("ask").select("i").distinct()
    # Queries are found again in the tiles, where they have a place (block, at).
    known = tiles.select("block", "n", "d", "ids", "m").mapInPandas(_unpack, "block long, at int, id long, v array<double>")
    asks = cut(known.join(asked.withColumnRenamed("i", "id"), "id", "left_semi"))
    n = asks.count()
    empty = spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    if not n:
        return empty
    seen = tiles.agg(F.sum("n"), F.max("top"), F.max("d")).first()
    parts = -(-n // query_block)
    made = None
    for part in range(parts):
        rows = asks.where(F.pmod(F.xxhash64("block", "at"), F.lit(parts)) == part).collect()
        if not rows:
            continue
        one = _select(tiles, _Queries(rows, seen[1], seen[2]), int(seen[0]) - 1, k, bins)
        made = one if made is None else made.unionByName(one)
    return empty if made is None else made


def _unpack(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    for b in batches:
        for block, n, d, ids, raw in zip(b["block"], b["n"], b["d"], b["ids"], b["m"], strict=True):
            m = np.frombuffer(raw, "<f8").reshape(n, d)
            yield pd.DataFrame({"block": block, "at": np.arange(n, dtype=np.int32), "id": np.frombuffer(ids, np.int64), "v": list(m)})


def _select(tiles: DataFrame, q: _Queries, candidates: int, k: int, bins: int) -> DataFrame:
    """Refine the bins of one query block to its k-th scores, then filter and rank."""
    spark = tiles.sparkSession
    nq = len(q.ids)
    have = min(k, candidates)
    lowest = -min(q.bound, _LONG)
    lo = np.full(nq, lowest, np.int64)
    open_bits = max(1, (2 * min(q.bound, _LONG) - 1).bit_length())
    step = bins.bit_length() - 1
    need = np.full(nq, have, np.int64)
    while open_bits > 0 and have:
        wide, open_bits = open_bits, max(0, open_bits - step)
        shift = np.full(nq, open_bits, np.int64)
        counts = tiles.mapInPandas(_histogram(q, lo, shift, need, 1 << (wide - open_bits)), "q int, bin int, c long").groupBy("q", "bin").agg(F.sum("c").alias("c"))
        above = F.coalesce(F.sum("c").over(W.partitionBy("q").orderBy(F.desc("bin")).rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
        want = spark.createDataFrame([(i, int(x)) for i, x in enumerate(need)], "q int, need long")
        found = counts.withColumn("above", above).join(F.broadcast(want), "q").where("above < need and above + c >= need").select("q", "bin", "above").collect()
        for r in found:  # one row per query of the block
            lo[r["q"]] = int(lo[r["q"]]) + (r["bin"] << open_bits)
            need[r["q"]] -= r["above"]
    kept = tiles.mapInPandas(_survivors(q, lo, k), "q int, vec_id long, score long")
    names = spark.createDataFrame(list(enumerate(q.ids)), "q int, query_id long")
    rank = F.row_number().over(W.partitionBy("q").orderBy(F.desc("score"), "vec_id"))
    ranked = kept.withColumn("rank", rank).where(F.col("rank") <= k)
    return ranked.join(F.broadcast(names), "q").select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def op4_topk_search(spark, sf_dir: str) -> DataFrame:
    rows = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    return top_k(rows, F.col("vec_id") % 50 == 0)


OP4_SQL = """
with e as (
  select vec_id, list_transform(embedding, lambda x: floor(256 * cast(x as double))) as v
  from embeddings
  where embedding is not null and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0
), s as (
  select q.vec_id as query_id, c.vec_id as vec_id, cast(list_inner_product(q.v, c.v) as bigint) as score
  from e q join e c on q.vec_id <> c.vec_id where q.vec_id % 50 = 0
), r as (
  select *, row_number() over (partition by query_id order by score desc, vec_id) as rk from s
)
select query_id, cast(rk as integer) as rank, vec_id, score from r where rk <= 5
"""
