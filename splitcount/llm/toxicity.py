"""Counterfactual-regularised toxicity classifier.

A logistic model over the presence of word features: the word itself, and each of its openings of 3 to
10 letters that goes on (``abc+``), so that new compounds of a known stem count.  Features are those at
least twice as common in toxic texts, beyond chance by a G-test, the most informative first.  Beside the usual shrinkage, training penalises the squared change of
the score when identity terms of a labelled sentence are swapped for others of their group, with a small
weight for every pair of terms in any case: neutral mentions of a group carry no score of their own.

The model is fitted on a bounded sample of labelled rows (``max_rows``, chosen by a hash of the id, the
same at every size); scoring covers every whole text.

Defined results: a null text is the empty text and scores the model's bias alone; without any labelled
row every score is 0; several labels of one doc_id count as toxic if any is; an empty table gives no rows.
"""

from __future__ import annotations

import re
import uuid
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from splitcount.llm.common import held_out, remembered, table, text_of

_WORDS = re.compile(r"[^\W\d_]+")
_SENTENCE = re.compile(r"[^.!?\n]+")
#: Groups of identity terms; a swap stays within its group.
IDENTITY_GROUPS = (
    ("women", "men", "girls", "boys"),
    ("woman", "man", "girl", "boy"),
    ("muslim", "christian", "jewish", "hindu", "buddhist", "catholic", "atheist"),
    ("muslims", "christians", "jews", "hindus", "buddhists", "catholics", "atheists"),
    ("black", "white", "asian", "latino", "african", "european"),
    ("gay", "straight", "lesbian", "bisexual", "transgender", "queer"),
    ("immigrants", "foreigners", "refugees", "natives", "locals"),
    ("frauen", "männer"),
    ("femmes", "hommes"),
    ("mujeres", "hombres"),
    ("disabled", "blind", "deaf", "elderly", "young"),
)
_SHORT, _LONG = 3, 10


def word_features(word: str) -> list[str]:
    return [word + "$", *(word[:k] + "+" for k in range(_SHORT, min(_LONG + 1, len(word))))]


def words_of(text: str) -> set[str]:
    return set(_WORDS.findall(text.lower()))


@dataclass
class ToxicModel:
    index: dict[str, int] = field(default_factory=dict)
    weight: np.ndarray = field(default_factory=lambda: np.zeros(0))
    bias: float | None = None
    name: str = field(default_factory=lambda: uuid.uuid4().hex)

    def features(self, text: str) -> set[int]:
        known, index = remembered(("toxic words", self.name, len(self.index)), dict), self.index
        if len(known) > 100_000:  # a bounded memory of words
            known.clear()
        out: set[int] = set()
        for w in words_of(text):
            got = known.get(w)
            if got is None:
                got = tuple(index[f] for f in word_features(w) if f in index)
                if len(w) <= 64:
                    known[w] = got
            if got:
                out.update(got)
        return out

    def score(self, text: str) -> float:
        if self.bias is None:
            return 0.0
        at = sorted(self.features(text))
        z = self.bias + float(self.weight[at].sum())
        return float(1 / (1 + np.exp(-np.clip(z, -40, 40))))


def labelled_sample(docs: DataFrame, labels: DataFrame, train: Column, max_rows: int) -> DataFrame:
    """(t, y) of at most ``max_rows`` labelled texts, those whose ids hash lowest."""
    y = labels.where(F.col("doc_id").isNotNull() & F.col("toxic").isNotNull()).where(train)
    y = y.groupBy(F.col("doc_id").cast("long").alias("i")).agg(F.max(F.col("toxic").cast("int")).alias("y"))
    y = y.orderBy(F.xxhash64(F.lit(7), "i"), "i").limit(max_rows)
    return docs.select(F.col("doc_id").cast("long").alias("i"), text_of().alias("t")).join(F.broadcast(y), "i").select("t", "y")


def _class_counts(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    seen: tuple[Counter, Counter] = (Counter(), Counter())
    for b in batches:
        for t, y in zip(b["t"], b["y"], strict=True):
            seen[y != 0].update({f for w in words_of(t) for f in word_features(w)})
    keys = list(seen[0].keys() | seen[1].keys())
    if keys:
        yield pd.DataFrame({"f": keys, "neg": [seen[0][k] for k in keys], "pos": [seen[1][k] for k in keys]})


def _information(pos: Column, neg: Column, p: int, n: int) -> Column:
    """Mutual information of a feature's presence with the label."""
    all_ = float(p + n)
    part = lambda c, row, col: F.when(c > 0, c / all_ * F.log(c * all_ / (row * col))).otherwise(0.0)
    on = (pos + neg).cast("double")
    return part(pos, on, F.lit(float(p))) + part(neg, on, F.lit(float(n))) + part(p - pos, all_ - on, F.lit(float(p))) + part(n - neg, all_ - on, F.lit(float(n)))


def swaps(text: str) -> list[tuple[str, str]]:
    """(term, replacement) pairs for the identity terms of each sentence."""
    out = []
    for m in _SENTENCE.finditer(text.lower()):
        words = _WORDS.findall(m[0])
        for g in IDENTITY_GROUPS:
            out += [(w, v) for w in words if w in g for v in g if v != w]
    return out


def train_weights(rows: list[list[int]], y: np.ndarray, pairs: list[tuple[list[int], list[int], float]], size: int, l2: float, swap_weight: float, rounds: int = 150) -> tuple[np.ndarray, float]:
    """Minimise mean log-loss + l2 |w|^2 / 2 + swap_weight * mean squared score change of the pairs."""
    lens = np.fromiter(map(len, rows), np.int64, len(rows))
    col = np.fromiter((c for r in rows for c in r), np.int64, int(lens.sum()))
    row = np.repeat(np.arange(len(rows)), lens)
    pl = np.array([len(a) + len(b) for a, b, _ in pairs], np.int64)
    pc = np.array([c for a, b, _ in pairs for c in (*a, *b)], np.int64)
    ps = np.array([s for a, b, _ in pairs for s in (*[-1.0] * len(a), *[1.0] * len(b))])
    pr = np.repeat(np.arange(len(pairs)), pl)
    pw = np.array([w for *_, w in pairs])
    pw = pw / pw.sum() if len(pw) else pw

    def value(v: np.ndarray) -> tuple[float, np.ndarray]:
        w, b = v[:-1], v[-1]
        z = np.bincount(row, weights=w[col], minlength=len(rows)) + b
        p = 1 / (1 + np.exp(-np.clip(z, -40, 40)))
        loss = float(np.mean(np.logaddexp(0, z) - y * z)) + l2 / 2 * float(w @ w)
        e = (p - y) / len(y)
        g = np.bincount(col, weights=e[row], minlength=size) + l2 * w
        if len(pairs):
            d = np.bincount(pr, weights=w[pc] * ps, minlength=len(pairs))
            loss += swap_weight * float(pw @ d**2)
            g += np.bincount(pc, weights=(2 * swap_weight * pw * d)[pr] * ps, minlength=size)
        return loss, np.append(g, e.sum())

    v = np.zeros(size + 1)
    v[-1] = np.log((y.sum() + 0.5) / (len(y) - y.sum() + 0.5))
    f, g = value(v)
    memory: list[tuple[np.ndarray, np.ndarray, float]] = []
    for _ in range(rounds):  # limited-memory quasi-Newton steps with backtracking
        q, steps = g.copy(), []
        for s, t, r in reversed(memory):
            a = r * (s @ q)
            q -= a * t
            steps.append(a)
        if memory:
            s, t, _ = memory[-1]
            q *= (s @ t) / (t @ t)
        for (s, t, r), a in zip(memory, reversed(steps), strict=True):
            q += (a - r * (t @ q)) * s
        size_step, slope = 1.0 if memory else min(1.0, 1 / np.abs(g).max(initial=1e-9)), -float(q @ g)
        while True:
            new = v - size_step * q
            f2, g2 = value(new)
            if f2 <= f + 1e-4 * size_step * slope or size_step < 1e-8:
                break
            size_step /= 2
        s, t = new - v, g2 - g
        if s @ t > 1e-12:
            memory = [*memory[-9:], (s, t, 1 / (s @ t))]
        moved = f - f2
        v, f, g = new, f2, g2
        if moved < 1e-8:
            break
    return v[:-1], float(v[-1])


def fit(docs: DataFrame, labels: DataFrame, train: Column, max_rows: int = 12_000, n_features: int = 8192, min_docs: int = 3, min_g: float = 14.0, l2: float = 3e-6, swap_weight: float = 1.0) -> ToxicModel:
    sample = labelled_sample(docs, labels, train, max_rows)
    sizes = {r["y"] != 0: r["n"] for r in sample.groupBy("y").agg(F.count("*").alias("n")).collect()}
    p, n = sizes.get(True, 0), sizes.get(False, 0)
    if not p + n:
        return ToxicModel()
    counts = sample.mapInPandas(_class_counts, "f string, neg long, pos long").groupBy("f").agg(F.sum("neg").alias("neg"), F.sum("pos").alias("pos"))
    counts = counts.where(F.col("neg") + F.col("pos") >= min_docs).where(F.col("pos") * n > 2 * F.col("neg") * p)
    g = F.round(2 * (p + n) * _information(F.col("pos"), F.col("neg"), p, n), 6)
    best = counts.where(g >= min_g).orderBy(g.desc(), "f").limit(n_features).select("f").collect()
    model = ToxicModel({r["f"]: i for i, r in enumerate(best)})
    ask = ToxicModel(dict(model.index), bias=0.0)

    def featured(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            yield pd.DataFrame({"y": b["y"], "x": [sorted(ask.features(t)) for t in b["t"]], "s": [[f"{a} {c}" for a, c in swaps(t)] for t in b["t"]]})

    rows = sample.mapInPandas(featured, "y int, x array<int>, s array<string>").collect()  # at most max_rows
    rows.sort(key=lambda r: (r["y"], r["x"]))
    weigh = Counter(tuple(s.split(" ")) for r in rows for s in r["s"])
    for g in IDENTITY_GROUPS:
        weigh.update({(a, c): 1 for a in g for c in g if a != c})
    of = lambda w: [model.index[f] for f in word_features(w) if f in model.index]
    pairs = [(x, z, float(k)) for (a, c), k in sorted(weigh.items()) if (x := of(a)) + (z := of(c))]
    y = np.array([float(r["y"] != 0) for r in rows])
    model.weight, model.bias = train_weights([r["x"] for r in rows], y, pairs, len(model.index), l2, swap_weight)
    return model


def score_column(docs: DataFrame, model: ToxicModel, text_col: str = "text") -> Column:
    sent = docs.sparkSession.sparkContext.broadcast(model)  # n_features entries at most

    @F.pandas_udf("double")
    def run(texts: pd.Series) -> pd.Series:
        return texts.map(lambda t: round(sent.value.score(t or ""), 6)).astype(float)

    return run(F.coalesce(F.col(text_col), F.lit("")))


def op10_toxicity(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = fit(docs, table(spark, sf_dir, "labels"), ~held_out("doc_id"))
    scored = docs.select(F.col("doc_id").cast("long").alias("doc_id"), held_out("doc_id").alias("held_out"), score_column(docs, model).alias("score"))
    return scored.withColumn("predicted", (F.col("score") >= 0.3).cast("int"))
