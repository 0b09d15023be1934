"""SimHash near-duplicate classes through banded BK-trees.

Fingerprints are 64-bit majority votes over the XXH64 values of word shingles.  Distinct fingerprints
are grouped before anything else, so a text that a third of all rows share is one entry.  Two
fingerprints within ``radius`` bits agree in at least one of ``radius + 1`` disjoint bit bands, hence
every link meets inside a (band, band value) shard.  Each shard is one BK-tree: a node's children are
keyed by their integer Hamming distance to it, and a search follows only edges whose key lies within
the radius of the query's distance.  Trees are searched where they are built instead of being
broadcast, since their number and size grow with the data.

A shard of more than ``shard_rows`` fingerprints is cut into chunks; every chunk gets a tree and each
pair of chunks meets in a task of its own, so no task holds more than two chunks and no link is lost.

Defined results: a null text is the empty text; texts without a word have fingerprint zero and link
like any other; rows that repeat a doc_id stay separate rows; null doc_ids are never a class id unless
all members are null; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from splitcount.llm.common import cut, text_of

#: Shingles that are voted on at once; bounds the bit matrix at 8 MB.
_VOTE_BLOCK = 1 << 17


def shingle_hashes(text: str | None, width: int, seed: int) -> np.ndarray:
    """XXH64 values of the whole text's word shingles, repeats included."""
    import xxhash

    # On bytes, lower() touches A-Z alone and split() cuts at 0x20 and 0x09-0x0D alone.
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.empty(0, np.uint64)
    h = xxhash.xxh64_intdigest
    buf = b" ".join(words)
    if len(words) < width:
        return np.array([h(buf, seed)], np.uint64)
    # Shingle i is the slice from word i's start to word i+width-1's end.
    ends = np.flatnonzero(np.frombuffer(buf, np.uint8) == 32)
    starts = np.concatenate(([0], ends + 1)).tolist()
    ends = np.concatenate((ends, [len(buf)])).tolist()
    n = len(words) - width + 1
    return np.fromiter((h(buf[a:b], seed) for a, b in zip(starts[:n], ends[width - 1 :], strict=True)), np.uint64, n)


def majority(hashes: np.ndarray) -> int:
    """Bit b is 1 iff it is set in more than half of the values."""
    votes = np.zeros(64, np.int64)
    for at in range(0, len(hashes), _VOTE_BLOCK):
        part = hashes[at : at + _VOTE_BLOCK]
        bits = np.unpackbits(part.astype(">u8").view(np.uint8).reshape(-1, 8), axis=1)
        votes += bits.sum(axis=0, dtype=np.int64)
    out = 0
    for v in votes.tolist():
        out = out << 1 | (2 * v > len(hashes))
    return out


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 3, seed: int = 42) -> DataFrame:
    """(doc_id, fp): fp holds the fingerprint's bits as a signed long."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            fps = np.fromiter((majority(shingle_hashes(t, width, seed)) for t in b["t"]), np.uint64, len(b))
            yield pd.DataFrame({"doc_id": b["i"].astype("Int64"), "fp": fps.view(np.int64)})

    src = docs.select(F.col(id_col).cast("long").alias("i"), text_of(text_col).alias("t"))
    return src.mapInPandas(run, "doc_id long, fp long")


# ---------------------------------------------------------------- BK-trees over many shards at once


class Forest:
    """BK-trees of many shards, built and searched level by level on arrays.

    ``shard`` holds a tree number per item; the first item of each number is its root.
    """

    def __init__(self, fp: np.ndarray, shard: np.ndarray):
        self.fp = fp
        n = len(fp)
        self.parent, self.edge = np.full(n, -1), np.zeros(n, np.int64)
        roots = np.unique(shard, return_index=True)[1]
        self.root_of = dict(zip(shard[roots].tolist(), roots.tolist(), strict=True))
        at = roots[np.searchsorted(shard[roots], shard)] if n else np.empty(0, np.int64)
        items = np.setdiff1d(np.arange(n), roots)
        at = at[items]
        while len(items):
            d = np.bitwise_count(fp[items] ^ fp[at]).astype(np.int64)
            slot = at * 65 + d
            _, first, back = np.unique(slot, return_index=True, return_inverse=True)
            heads = items[first]
            self.parent[heads], self.edge[heads] = at[first], d[first]
            rest = np.ones(len(items), bool)
            rest[first] = False
            items, at = items[rest], heads[back[rest]]
        # Children sorted by (parent, edge): one slice per range of edges.
        self.kids = np.flatnonzero(self.parent >= 0)
        key = self.parent[self.kids] * 65 + self.edge[self.kids]
        order = np.argsort(key, kind="stable")
        self.kids, self.key = self.kids[order], key[order]

    def search(self, fp: np.ndarray, shard: np.ndarray, radius: int, block: int = 1 << 16) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Blocks of (query number, item number) within the radius."""
        roots = np.array([self.root_of.get(s, -1) for s in shard.tolist()], np.int64)
        for lo in range(0, len(fp), block):
            q = np.arange(lo, min(lo + block, len(fp)))
            at = roots[q]
            q, at = q[at >= 0], at[at >= 0]
            while len(q):
                nq, na = [], []
                for a in range(0, len(q), 1 << 20):  # bounds the frontier's scratch arrays
                    qq, aa = q[a : a + (1 << 20)], at[a : a + (1 << 20)]
                    d = np.bitwise_count(fp[qq] ^ self.fp[aa]).astype(np.int64)
                    hit = d <= radius
                    if hit.any():
                        yield qq[hit], aa[hit]
                    left = np.searchsorted(self.key, aa * 65 + np.maximum(d - radius, 0))
                    right = np.searchsorted(self.key, aa * 65 + np.minimum(d + radius, 64), side="right")
                    n = right - left
                    if n.sum():
                        nq.append(np.repeat(qq, n))
                        na.append(self.kids[np.repeat(left - np.cumsum(n) + n, n) + np.arange(n.sum())])
                q, at = (np.concatenate(nq), np.concatenate(na)) if nq else (q[:0], at[:0])


class Union:
    """Union-find over the rows of one task; turns its links into a spanning forest."""

    def __init__(self, n: int):
        self.up = list(range(n))

    def find(self, x: int) -> int:
        up = self.up
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    def join(self, a: int, b: int) -> None:
        a, b = self.find(a), self.find(b)
        if a != b:
            self.up[max(a, b)] = min(a, b)


def _shard_links(radius: int):
    """Rows sorted by (band, value, x, y): links inside a shard as edges of a spanning forest."""

    def one(fp: np.ndarray, shard: np.ndarray, build: np.ndarray, ask: np.ndarray) -> pd.DataFrame:
        bi, qi = np.flatnonzero(build), np.flatnonzero(ask)
        u = Union(len(fp))
        touched = set()
        for q, t in Forest(fp[bi], shard[bi]).search(fp[qi], shard[qi], radius):
            a, b = qi[q], bi[t]
            keep = a != b
            for x, y in zip(a[keep].tolist(), b[keep].tolist(), strict=True):
                u.join(x, y)
                touched.add(x)
                touched.add(y)
        got = [(x, u.find(x)) for x in touched if u.find(x) != x]
        s = fp.view(np.int64)
        return pd.DataFrame({"a": s[[g[0] for g in got]], "b": s[[g[1] for g in got]]}, dtype="int64")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        kept: list[pd.DataFrame] = []
        rows = 0

        def flush(frame: pd.DataFrame) -> pd.DataFrame:
            key = frame[["band", "value", "x", "y"]].to_numpy()
            new = np.ones(len(frame), bool)
            new[1:] = (key[1:] != key[:-1]).any(axis=1)
            shard = np.cumsum(new) - 1
            many = np.bincount(shard)[shard] > 1  # a lone fingerprint has no partner here
            return one(frame["fp"].to_numpy()[many].view(np.uint64), shard[many], frame["build"].to_numpy()[many], frame["ask"].to_numpy()[many])

        for b in batches:
            kept.append(b)
            rows += len(b)
            if rows >= 1 << 17:
                frame = pd.concat(kept, ignore_index=True)
                last = (frame[["band", "value", "x", "y"]].to_numpy() != frame[["band", "value", "x", "y"]].to_numpy()[-1]).any(axis=1)
                end = int(np.flatnonzero(last)[-1]) + 1 if last.any() else 0
                if end:
                    yield flush(frame.iloc[:end].reset_index(drop=True))
                kept = [frame.iloc[end:].reset_index(drop=True)]
                rows = len(kept[0])
        if rows:
            yield flush(pd.concat(kept, ignore_index=True))

    return run


def bands(n: int) -> list[tuple[int, int]]:
    """(shift, width) of n disjoint bands that cover 64 bits."""
    cuts = [round(64 * k / n) for k in range(n + 1)]
    return [(lo, hi - lo) for lo, hi in zip(cuts, cuts[1:], strict=False)]


def near_links(fps: DataFrame, radius: int = 2, shard_rows: int = 20_000) -> DataFrame:
    """Edges (a, b) between distinct fingerprints whose classes are those of all links within the radius."""
    distinct = fps.select("fp").distinct()
    rows = distinct.select(
        "fp",
        F.explode(
            F.array(
                *(
                    F.struct(F.lit(k).alias("band"), F.shiftrightunsigned("fp", s).bitwiseAND(F.lit((1 << w) - 1)).alias("value"))
                    for k, (s, w) in enumerate(bands(radius + 1))
                )
            )
        ).alias("s"),
    ).select("fp", "s.band", "s.value")
    # Chunks per shard, from counts; only shards above the bound are listed.
    big = rows.groupBy("band", "value").count().where(F.col("count") > shard_rows)
    big = big.select("band", "value", F.ceil(F.col("count") / shard_rows).cast("int").alias("parts"))
    chunk = F.pmod(F.xxhash64("fp"), F.coalesce("parts", F.lit(1)).cast("long")).cast("int")
    rows = rows.join(big, ["band", "value"], "left").withColumn("c", chunk).withColumn("parts", F.coalesce("parts", F.lit(1)))
    pair = F.explode(F.transform(F.sequence(F.lit(0), F.col("parts") - 1), lambda o: F.struct(F.least("c", o).alias("x"), F.greatest("c", o).alias("y"))))
    rows = rows.select("fp", "band", "value", "c", pair.alias("p")).select(
        "fp",
        "band",
        "value",
        F.col("p.x").alias("x"),
        F.col("p.y").alias("y"),
        (F.col("c") == F.col("p.x")).alias("build"),
        (F.col("c") == F.col("p.y")).alias("ask"),
    )
    n = int(fps.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = rows.repartition(n, "band", "value", "x", "y").sortWithinPartitions("band", "value", "x", "y", "fp")
    return rows.mapInPandas(_shard_links(radius), "a long, b long")


# ---------------------------------------------------------------- classes


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, root): smallest node of each connected class, for nodes that have an edge.

    Alternates two star contractions; each is an aggregation with map-side combine and one join, and
    each round's edges are cut to the shared folder.  Only a count returns to the driver.
    """

    def sum_of(e: DataFrame) -> tuple:
        return tuple(e.agg(F.count("*"), F.coalesce(F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")), F.lit(0).cast("decimal(38,0)"))).first())

    e = cut(edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    state = sum_of(e)
    if not state[0]:
        return e.select(F.col("u").alias("node"), F.col("v").alias("root"))
    for _ in range(max_rounds):
        both = e.select("u", "v").unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        e2 = large.where("u <> v").unionByName(low.where("u <> m").select("u", F.col("m").alias("v"))).distinct()
        small = e2.groupBy("u").agg(F.min("v").alias("m"))
        e3 = e2.join(small, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v")
        e3 = e3.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).unionByName(small.select("u", F.col("m").alias("v")))
        e = cut(e3.distinct())
        before, state = state, sum_of(e)
        if state == before:
            break
    else:
        raise RuntimeError(f"classes did not settle in {max_rounds} rounds")
    roots = e.groupBy("u").agg(F.min("v").alias("root")).select(F.col("u").alias("node"), "root")
    return roots.unionByName(roots.select(F.col("root").alias("node"), "root").distinct())


def near_classes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 3, seed: int = 42, radius: int = 2) -> DataFrame:
    """(doc_id, fp, component_id): smallest doc_id that links reach from each document."""
    fps = cut(fingerprints(docs, id_col, text_col, width, seed))
    firsts = fps.groupBy("fp").agg(F.min("doc_id").alias("first"))
    linked = cut(components(near_links(fps, radius)).select(F.col("node").alias("fp"), "root"))
    with_root = firsts.join(linked, "fp", "left").select("fp", "first", F.coalesce("root", "fp").alias("root"))
    least = with_root.groupBy("root").agg(F.min("first").alias("component_id"))
    known = with_root.join(least, "root").select("fp", "component_id")
    return fps.join(known, "fp").select("doc_id", "fp", "component_id")


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **how) -> DataFrame:
    """The rows whose id leads their class by fingerprints.  Rows that share the leading id all stay."""
    classes = near_classes(docs, id_col, text_col, **how)
    ids = classes.where(F.col("doc_id").eqNullSafe(F.col("component_id"))).select(F.col("doc_id").alias("_lead")).distinct()
    return docs.join(ids, docs[id_col].cast("long").eqNullSafe(ids["_lead"]), "left_semi")


def fingerprint_text(fp: str = "fp"):
    return F.lpad(F.lower(F.hex(fp)), 16, "0")


def op9_simhash_dedup(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return near_classes(docs).select("doc_id", fingerprint_text().alias("fingerprint"), "component_id")
