"""The pipeline: each stage against brute force on its own input, and the whole run."""

import random
import re
from collections import Counter

import corpus_pipeline as cp

from splitcount.llm import near_copies as NC
from splitcount.llm import secret_scan as SS
from splitcount.llm import simhash_dedup as SD
from splitcount.llm.common import cut

from ..conftest import SF
from .test_operators import brute_lines, check_packing, lines_after, texts


def test_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    cols = docs.columns
    names = [n for n, _ in cp.STAGES]
    assert names == ["toxicity", "line_dedup", "simhash_dedup", "secret_scan", "bestfit_packing"]
    before = texts(docs)
    for name, stage in cp.STAGES:
        docs = cut(stage(spark, docs, SF))
        if name == "bestfit_packing":
            check_packing(docs.collect(), before)
            break
        assert docs.columns == cols
        after = texts(docs)
        if name == "toxicity":
            assert 0 < len(after) <= len(before) and set(after) <= set(before)
        elif name == "line_dedup":
            gone = brute_lines(before)
            assert Counter(after) == Counter((i, lines_after(t, gone.get((i, t), ()))) for i, t in before)
        elif name == "simhash_dedup":
            assert sorted(after) == sorted(before[k] for k in brute_leads(before))
        elif name == "secret_scan":
            g = SS.Guesser(SS.corpus_words(spark.createDataFrame(before, "doc_id long, text string")))
            assert dict(after) == {i: SS.redact(t, g) for i, t in before}
            assert not any(SS.base_spans(t) for _, t in after)
        before = after


def test_run_and_empty_tables(spark):
    whole = cp.run(spark, SF)
    assert whole.count() > 0 and whole.columns == ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"]
    none = spark.read.parquet(f"{SF}/documents.parquet").limit(0)
    for _, stage in cp.STAGES:
        assert stage(spark, none, SF).count() == 0


_SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def brute_leads(rows):
    """Numbers of the rows that stay: the one with the smallest id of each class of 5-word similarity 0.8, and all without text."""

    def shingles(t):
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t))
        return {tuple(w[i : i + 5]) for i in range(max(len(w) - 4, bool(w)))}

    sets = [shingles(t or "") for _, t in rows]
    u = SD.Union(len(rows))
    for i in range(len(rows)):
        for j in range(i):
            if rows[i][1] is not None and rows[j][1] is not None and (sets[i] == sets[j] or len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]) > 0):
                u.join(i, j)
    first = {}
    for i, (d, _) in enumerate(rows):
        first.setdefault(u.find(i), []).append((d is None, d or 0, i))
    return [min(x)[2] for x in first.values()]


def test_cuts_collect_a_grown_heap():
    """The driver's garbage is collected at a cut once the heap is beyond half of what it may take, and only then."""
    from types import SimpleNamespace as Of

    from splitcount.session import relieve

    for total, want in ((50, []), (51, ["gc"])):
        done = []
        heap = Of(totalMemory=lambda total=total: total, maxMemory=lambda: 100)
        jvm = Of(java=Of(lang=Of(Runtime=Of(getRuntime=lambda heap=heap: heap))), System=Of(gc=lambda done=done: done.append("gc")))
        assert relieve(Of(sparkContext=Of(_jvm=jvm))) == bool(want) and done == want


def test_null_texts_pass(spark):
    """Every null text stays through all stages, of repeated and empty texts one does."""
    rows = [(1, None), (2, None), (None, None), (3, ""), (4, "fine words"), (5, ""), (4, "fine words"), (6, " \n ")]
    docs = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in rows], _SCHEMA).repartition(3)
    for _, stage in cp.STAGES[:-1]:
        docs = cut(stage(spark, docs, SF))
    assert sorted((r["doc_id"] or 0, r["text"] or "") for r in docs.collect()) == [(0, ""), (1, ""), (2, ""), (3, ""), (4, "fine words")]
    packed = cp.STAGES[-1][1](spark, docs, SF).collect()
    assert len(packed) == 5 and sum(r["length"] for r in packed if r["doc_id"] != 4) == 4


def test_texts_around_one_passage(spark):
    """Many texts share a passage: their bands are crowded, and the rarest shingles find the copies among them."""
    rnd = random.Random(4)
    passage = [f"p{k}" for k in range(200)]
    rows = []
    for k in range(90):
        own = [f"o{rnd.randrange(10**6)}" for _ in range(60)]
        rows.append((k, " ".join(own + passage)))
        if k % 10 == 0:
            rows.append((1000 + k, " ".join([*own[:55], "x", *own[56:], *passage])))
    rows += [(2000 + k, rows[0][1]) for k in range(5)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    want = sorted(rows[k][0] for k in brute_leads(rows))
    assert len(want) == 90
    for crowd in (2, 64, 10_000):
        assert sorted(r["doc_id"] for r in NC.keep_one(df, crowd=crowd).collect()) == want


def test_near_copies_leave(spark):
    """Every pair of 5-word similarity 0.8 or more is one class, and no pair below is linked."""
    rnd = random.Random(2)
    rows = []
    for k in range(0, 120, 3):
        words = [f"w{rnd.randrange(900)}" for _ in range(rnd.randrange(40, 300))]
        close, far = list(words), list(words)
        for at in range(0, len(words), 60):  # at most 5 shingles of 60 change
            close[at] = "changed"
        for at in range(0, len(words), 12):
            far[at] = "changed"
        rows += [(k, " ".join(words)), (k + 1, " ".join(close)), (k + 2, " ".join(far))]
    sets = [{tuple(t.split()[i : i + 5]) for i in range(len(t.split()) - 4)} for _, t in rows]
    u = SD.Union(len(rows))
    for i in range(len(rows)):
        for j in range(i):
            if len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]):
                u.join(i, j)
    want = {i for i in range(len(rows)) if u.find(i) == i}
    assert want == {i for i in range(len(rows)) if i % 3 != 1}
    docs = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    assert {r["doc_id"] for r in cp.keep_one_of_each_group(spark, docs, SF).collect()} == want


def _variants(n, words, changed, seed):
    rnd = random.Random(seed)
    base = [f"w{k}" for k in range(words)]
    out = []
    for k in range(n):
        own = list(base)
        for at in rnd.sample(range(words), changed):
            own[at] = f"own{k}_{at}"
        out.append(" ".join(own))
    return out


def test_fingerprints_alone_find_copies(spark, monkeypatch):
    """The stage links by fingerprints in BK-trees: without any band of minima the closest copies are still found."""
    close = _variants(6, 900, 1, 3)
    rows = list(enumerate([*close, " ".join(f"other{k}" for k in range(300))]))
    fps = [SD.majority(NC._sets([t], 5, 42)[0]) for _, t in rows]
    u = SD.Union(len(rows))
    for i in range(len(rows)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= NC.NEAR:
                u.join(i, j)
    want = {i for i in range(len(rows)) if u.find(i) == i}
    assert 1 < len(want) < len(rows)
    monkeypatch.setattr(NC, "_groups", lambda r: cut(r.where("false").withColumn("b", r["s"]).select("band", "s", "b")))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert {r["doc_id"] for r in NC.keep_one(df).collect()} == want


def test_a_pool_gives_no_row_per_pair():
    """Texts around 0.8: the links that leave a pool join classes, however many pairs are similar, and miss no class."""
    import numpy as np
    import pandas as pd

    for changed in (2, 4, 6, 8):
        sets = NC._sets([t for k in range(3) for t in _variants(40, 200, changed, 10 * changed + k)], 5, 42)
        n = len(sets)
        u, pairs = SD.Union(n), 0
        for i in range(n):
            for j in range(i):
                both = len(np.intersect1d(sets[i], sets[j]))
                if both >= 0.8 * (len(sets[i]) + len(sets[j]) - both):
                    pairs += 1
                    u.join(i, j)
        frame = pd.DataFrame({"s": range(n), "c": range(n), "fp": np.array([SD.majority(x) for x in sets], np.uint64).view(np.int64), "grams": [x.view(np.int64) for x in sets], "build": True, "ask": True})
        half = np.arange(n) % 2 == 0
        across = frame.assign(build=half, ask=~half)
        got = [pd.concat([NC._decided(0.8)(frame)]), pd.concat([NC._decided(0.8)(x.reset_index(drop=True)) for x in (frame[half], frame[~half], across)])]
        for links in got:
            v = SD.Union(n)
            for a, b in links.itertuples(index=False):
                v.join(a, b)
            assert [v.find(i) for i in range(n)] == [u.find(i) for i in range(n)]
        assert len(got[0]) == n - len({u.find(i) for i in range(n)}) <= pairs
    assert pairs == 0 and len(got[0]) == 0
