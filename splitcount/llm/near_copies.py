"""Near-copy classes: SimHash fingerprints in BK-trees find pairs, whole shingle sets decide them.

A text is the set of its 5-word shingles, and its fingerprint the majority vote over them.  Texts of one set are
one node.  Links are found in three steps, and every one of them is decided by the exact similarity of its ends:

* fingerprints within ``NEAR`` bits, by the banded BK-trees of :mod:`splitcount.llm.simhash_dedup`;
* a pair of similarity 0.8 lies 9 bits apart on average and up to ``FAR``, beyond any radius that bands of bits can
  serve.  Bands of ``ROWS`` minima take their place as shards: such a pair shares one of the ``BANDS`` with
  probability 1 - (1 - 0.8^ROWS)^BANDS = 0.99993.  Each member of a shard is held against the smallest one;
* shards that still hold several classes are joined into pools, so a text is sent to one pool however many shards it
  shares.  Each pool is a BK-tree that is searched within ``FAR`` bits; what the tree finds in another class is
  decided where it is found, and only links that join two classes leave the task.

So no step makes a row for each pair of a large group.  A pool above ``crowd`` texts or ``_POOL`` shingles is cut into
chunks; every chunk has a tree and each pair of chunks meets in a task of its own.  Before a pool's pair is decided,
sets of too unequal sizes and sets that share none of their rarest shingles are passed over: two sets of
similarity 0.8 share one of the rarest fifth of either, so this loses no pair.

``FAR`` is 26 of 64 bits.  Over 30,000 drawn pairs of similarity 0.8, sets of 4 and 5 shingles lay 28 bits apart at
most, those of 16 and more 24.

Defined results: of each class one row stays, the one with the smallest doc_id (null ids last), whatever
its id shares with other rows; rows with null text all stay, as they are copies of nothing; all texts without
a word are one class; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from splitcount.llm.common import cut, text_of
from splitcount.llm.simhash_dedup import Forest, components, majority, near_links, shingle_hashes

BANDS, ROWS = 24, 5
#: Bits within which fingerprints are sought over the whole table, and within a pool.
NEAR, FAR = 2, 26
#: Shingles of one chunk of a pool, and queries that search its tree at once.
_POOL = 1 << 20
_ASKED = 64
_RNG = np.random.default_rng(5)
_A = _RNG.integers(0, 1 << 63, (BANDS * ROWS, 1), dtype=np.uint64) << np.uint64(1) | np.uint64(1)
_B = _RNG.integers(0, 1 << 63, (BANDS * ROWS, 1), dtype=np.uint64)
#: Shingles that are ranked at once; bounds the scratch array at 4 MB.
_BLOCK = 1 << 12
#: Rows that are given back at once, as their shingles take more room than their texts.
_SLICE = 500


def band_values(hashes: np.ndarray) -> list[int]:
    """One value for each band of minima."""
    import xxhash

    low = np.full(BANDS * ROWS, 2**64 - 1, np.uint64)
    for at in range(0, len(hashes), _BLOCK):
        low = np.minimum(low, (_A * hashes[at : at + _BLOCK] + _B).min(axis=1))
    return [xxhash.xxh64_intdigest(x.tobytes(), k) - 2**63 for k, x in enumerate(low.reshape(BANDS, ROWS))]


def _sets(texts: pd.Series, width: int, seed: int) -> list[np.ndarray]:
    return [np.unique(shingle_hashes(t, width, seed)) for t in texts]


def band_table(docs: DataFrame, row_col: str, text_col: str, width: int, seed: int) -> DataFrame:
    """(row, s, fp, bands): the shingle set's own hash, its fingerprint and its band values."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        import xxhash

        for b in batches:
            sets = _sets(b["t"], width, seed)
            names = [xxhash.xxh64_intdigest(x.tobytes(), seed) - 2**63 for x in sets]
            fps = np.fromiter((majority(x) for x in sets), np.uint64, len(sets)).view(np.int64)
            yield pd.DataFrame({"row": b["i"].to_numpy(), "s": names, "fp": fps, "bands": [band_values(x) if len(x) else [] for x in sets]})

    src = docs.select(F.col(row_col).alias("i"), text_of(text_col).alias("t"))
    return src.mapInPandas(run, "row long, s long, fp long, bands array<long>")


def shingle_sets(docs: DataFrame, name_col: str, text_col: str, width: int, seed: int) -> DataFrame:
    """(s, grams): the members of the sets, in order."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for whole in batches:
            for at in range(0, len(whole), _SLICE):
                b = whole.iloc[at : at + _SLICE]
                yield pd.DataFrame({"s": b["i"].to_numpy(), "grams": [x.view(np.int64) for x in _sets(b["t"], width, seed)]})

    src = docs.select(F.col(name_col).alias("i"), text_of(text_col).alias("t"))
    return src.mapInPandas(run, "s long, grams array<long>")


def similar(pairs: DataFrame, sets: DataFrame, least: float) -> DataFrame:
    """The pairs (a, b) whose sets have at least this similarity."""
    x = sets.select(F.col("s").alias("a"), F.col("grams").alias("x"))
    y = sets.select(F.col("s").alias("b"), F.col("grams").alias("y"))
    both = F.size(F.array_intersect("x", "y"))
    return pairs.join(x, "a").join(y, "b").where(both >= F.lit(least) * (F.size("x") + F.size("y") - both)).select("a", "b")


def _near(nodes: DataFrame) -> DataFrame:
    """(a, b): nodes (s, fp) whose fingerprints are equal or linked in the banded BK-trees."""
    low = nodes.groupBy("fp").agg(F.min("s").alias("b"))
    same = nodes.join(low, "fp").where("s <> b").select(F.col("s").alias("a"), "b")
    first, second = low.select(F.col("fp").alias("a"), F.col("b").alias("x")), low.select(F.col("fp").alias("b"), F.col("b").alias("y"))
    links = near_links(nodes.select("fp"), NEAR).distinct()
    return same.unionByName(links.join(first, "a").join(second, "b").select(F.col("x").alias("a"), F.col("y").alias("b")))


def _groups(rows: DataFrame) -> DataFrame:
    """(band, s, b): members of the band values that two sets or more share, with the smallest member."""
    low = rows.groupBy("band").agg(F.min("s").alias("b"), F.count("*").alias("n")).where("n > 1").select("band", "b")
    return cut(rows.join(low, "band"))


def _stars(groups: DataFrame) -> DataFrame:
    """(a, b): each member and the smallest one."""
    return groups.where("s <> b").select(F.col("s").alias("a"), "b").distinct()


def _pools(groups: DataFrame, edges: DataFrame) -> DataFrame:
    """(s, c, pool): members of the band values that hold several classes c; those that share a value share the pool."""
    known = components(edges).select(F.col("node").alias("s"), "root")
    member = cut(groups.join(known, "s", "left").select("band", "s", "b", F.coalesce("root", "s").alias("c")))
    mixed = member.groupBy("band").agg(F.min("c").alias("lo"), F.max("c").alias("hi")).where("lo <> hi").select("band")
    open_ = cut(member.join(mixed, "band", "left_semi"))
    pool = components(open_.select(F.col("s").alias("a"), "b")).select(F.col("node").alias("s"), F.col("root").alias("pool"))
    return open_.select("s", "c").distinct().join(pool, "s")


def _ranges(start: np.ndarray, size: np.ndarray) -> np.ndarray:
    """start[0], start[0] + 1, .., start[1], ..: size[k] places from each start."""
    return np.repeat(start - np.cumsum(size) + size, size) + np.arange(size.sum())


def _decided(least: float):
    """One chunk, or two, of a pool: the links that join classes, as (a, b)."""

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        n, s = len(frame), frame["s"].to_numpy()
        fp, c = frame["fp"].to_numpy().view(np.uint64), np.unique(frame["c"].to_numpy(), return_inverse=True)[1]
        size = np.fromiter(map(len, frame["grams"]), np.int64, n)
        start = np.cumsum(size) - size
        names, code, count = np.unique(np.concatenate(frame["grams"].to_list()), return_inverse=True, return_counts=True)
        # Each set's rarest shingles, as many as any set of the least similarity must share one of.
        owner = np.repeat(np.arange(n), size)
        order = np.lexsort((code, count[code], owner))
        rare = order[_ranges(start, size - np.ceil(least * size - 1e-9).astype(np.int64) + (size > 0))]
        rare = rare[count[code[rare]] > 1]
        mine = np.searchsorted(owner[rare], np.arange(n + 1))
        rare_code, rare_owner = code[rare], owner[rare]
        by_code = np.argsort(rare_code, kind="stable")
        of_code = np.searchsorted(rare_code[by_code], np.arange(len(names) + 1))
        build, ask = (np.flatnonzero(frame[k].to_numpy()) for k in ("build", "ask"))
        tree = Forest(fp[build], np.zeros(len(build), np.int64))
        one_chunk = len(build) == n
        mark, shares, got = np.zeros(len(names), bool), np.zeros(n, bool), []
        for at in range(0, len(ask), _ASKED):
            some = ask[at : at + _ASKED]
            found = list(tree.search(fp[some], np.zeros(len(some), np.int64), FAR))
            q, t = (np.concatenate([x[k] for x in found]) for k in (0, 1)) if found else (ask[:0], ask[:0])
            for k, i in enumerate(some.tolist()):
                x = rare_code[mine[i] : mine[i + 1]]
                near = rare_owner[by_code[_ranges(of_code[x], of_code[x + 1] - of_code[x])]]
                shares[near] = True
                j = build[t[q == k]]
                j = j[shares[j] & (c[j] != c[i]) & (np.minimum(size[j], size[i]) >= least * np.maximum(size[j], size[i]) - 1e-9)]
                shares[near] = False
                j = j[j < i] if one_chunk else j
                if len(j) == 0:
                    continue
                own = code[start[i] : start[i] + size[i]]
                mark[own] = True
                both = np.add.reduceat(mark[code[_ranges(start[j], size[j])]], np.cumsum(size[j]) - size[j], dtype=np.int64)
                mark[own] = False
                for y in j[both >= least * (size[i] + size[j] - both)].tolist():
                    if c[y] != c[i]:
                        c[c == c[y]] = c[i]
                        got.append((s[i], s[y]))
        return pd.DataFrame(got, columns=["a", "b"], dtype="int64")

    return run


def _tree_links(pools: DataFrame, nodes: DataFrame, grams: DataFrame, least: float, crowd: int) -> DataFrame:
    """(a, b): links between classes of one pool, from its BK-tree within ``FAR`` bits."""
    rows = cut(pools.join(nodes, "s").join(grams, "s"))
    most = F.greatest(F.ceil(F.count("*") / crowd), F.ceil(F.sum(F.size("grams")) / _POOL)).cast("int")
    rows = rows.join(rows.groupBy("pool").agg(most.alias("parts")), "pool")
    rows = rows.withColumn("k", F.pmod(F.xxhash64("s"), F.col("parts").cast("long")).cast("int"))
    pair = F.explode(F.transform(F.sequence(F.lit(0), F.col("parts") - 1), lambda o: F.struct(F.least("k", o).alias("x"), F.greatest("k", o).alias("y"))))
    rows = rows.select("pool", "s", "c", "fp", "grams", "k", pair.alias("p"))
    rows = rows.select("pool", "p.x", "p.y", "s", "c", "fp", "grams", (F.col("k") == F.col("p.x")).alias("build"), (F.col("k") == F.col("p.y")).alias("ask"))
    return rows.groupBy("pool", "x", "y").applyInPandas(_decided(least), "a long, b long")


def classes(docs: DataFrame, row_col: str, text_col: str = "text", width: int = 5, seed: int = 42, least: float = 0.8, crowd: int = 4096) -> tuple[DataFrame, DataFrame]:
    """(row, s, ..) and (s, root): each row's set, and the class of the sets that are linked; others are their own.

    ``row_col`` tells the rows of a written table apart.
    """
    rows = cut(band_table(docs, row_col, text_col, width, seed))
    nodes = cut(rows.groupBy("s").agg(F.min("row").alias(row_col), F.first("fp").alias("fp")))  # one set has one fingerprint
    near = cut(_near(nodes.select("s", "fp")))
    banded = _groups(rows.select("s", F.explode("bands").alias("band")).distinct())
    # One text of each set that has a candidate; the others need no set.
    ends = near.select(F.col("a").alias("s")).unionByName(near.select(F.col("b").alias("s")))
    asked = nodes.join(banded.select("s").unionByName(ends).distinct(), "s", "left_semi")
    grams = cut(shingle_sets(docs.select(row_col, text_col).join(asked.select(row_col, F.col("s").alias("_s")), row_col), "_s", text_col, width, seed))
    edges = cut(similar(near.unionByName(_stars(banded)).distinct(), grams, least))
    edges = cut(edges.unionByName(_tree_links(_pools(banded, edges), nodes.select("s", "fp"), grams, least, crowd)))
    roots = components(edges).select(F.col("node").alias("s"), "root")
    return rows, roots


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **how) -> DataFrame:
    """One row of each class, and every row without a text."""
    row = "_row"
    while row in docs.columns:
        row += "_"
    rows = cut(docs.withColumn(row, F.monotonically_increasing_id()))
    there = rows.where(F.col(text_col).isNotNull())
    ids = there.select(F.col(row).alias("row"), F.col(id_col).cast("long").alias("i"))
    sets, roots = classes(there, row, text_col, **how)
    # The first row of each set, then of each class: a set that many rows share is one row of the join.
    place = F.struct(F.col("i").isNull().alias("late"), "i", "row")
    firsts = sets.select("row", "s").join(ids, "row").groupBy("s").agg(F.min(place).alias("x"))
    leads = firsts.join(roots, "s", "left").groupBy(F.coalesce("root", "s").alias("root")).agg(F.min("x").alias("x"))
    kept = there.join(leads.select(F.col("x.row").alias(row)), row, "left_semi")
    return kept.unionByName(rows.where(F.col(text_col).isNull())).select(*(F.col(f"`{c}`") for c in docs.columns))
