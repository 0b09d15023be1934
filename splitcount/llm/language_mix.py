"""Multilingual mixture inference.

A language is a distribution over hashed character trigrams of words.  A document is a mixture: each
word comes from one language, drawn by the document's proportions.  Expectation-maximisation estimates
the proportions from the words' trigram likelihoods; a language enters the document's set only if it
raises the log-likelihood by more than ``penalty * log(words)``, the best one first.  The prediction is
the language with the largest proportion, the score that proportion.

Trigram counts come from every labelled document outside the held-out fold.  The table that is sent to
the tasks has at most ``_TABLE`` languages x buckets cells, whatever the corpus size: 2^15 buckets up to 200
labels, and half as many with each further doubling of their number.  Texts are read in slices.

Defined results: a null text, and one without a letter, is ``und`` with score 0; documents with a null
label train nothing; without any labelled document everything is ``und``; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from splitcount.llm.common import cut, held_out, text_of

_BITS = 15
#: Cells of the model's table at most, and cells of it that are gathered at once for a slice of a text.
_TABLE, _CELLS = 200 << _BITS, 1 << 20


def _fold_table() -> np.ndarray:
    """Bytes as the trigrams see them: A-Z lowered, every ASCII non-letter one break (0)."""
    t = np.arange(256, dtype=np.uint32)
    t[65:91] += 32
    ascii_letters = np.zeros(256, bool)
    ascii_letters[97:123] = ascii_letters[65:91] = True
    ascii_letters[128:] = True
    t[~ascii_letters] = 0
    return t


_FOLD = _fold_table()


def slice_units(raw: np.ndarray, lo: int, hi: int) -> tuple[np.ndarray, np.ndarray, bool]:
    """(buckets, first, goes_on) of raw[lo:hi]: trigram buckets, where each word starts among them, and whether the
    first word began in the slice before.  Breaks flank words."""
    b = np.zeros(hi - lo + 2, np.uint32)
    a, z = max(lo - 1, 0), min(hi + 1, len(raw))
    b[a - lo + 1 : z - lo + 1] = _FOLD[raw[a:z]]
    mid = b[1:-1]
    inside = mid != 0
    code = (b[:-2] << np.uint32(16)) | (mid << np.uint32(8)) | b[2:]
    bucket = (code[inside] * np.uint32(2654435761)) >> np.uint32(32 - _BITS)
    goes_on = bool(inside[0]) and bool(b[0])
    first = np.flatnonzero((b[:-2] == 0)[inside])
    return bucket, np.append(0, first) if goes_on else first, goes_on


def units(text: str) -> np.ndarray:
    """Trigram buckets of the whole folded text."""
    raw = np.frombuffer(text.encode("utf-8", "replace"), np.uint8)
    return slice_units(raw, 0, len(raw))[0] if len(raw) else np.zeros(0, np.uint32)


def has_letter(text: str) -> bool:
    return any(map(str.isalpha, text))


def trigram_counts(docs: DataFrame, text_col: str, lang_col: str) -> DataFrame:
    """(lang, bucket, n) over all given documents; each task sends its sums only."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        sums: dict[str, np.ndarray] = {}
        for batch in batches:
            for t, lang in zip(batch["t"], batch["l"], strict=True):
                sums.setdefault(lang, np.zeros(1 << _BITS, np.int64))
                raw = np.frombuffer(t.encode("utf-8", "replace"), np.uint8)
                for lo in range(0, len(raw), 1 << 20):
                    sums[lang] += np.bincount(slice_units(raw, lo, min(lo + (1 << 20), len(raw)))[0], minlength=1 << _BITS)
        for lang, c in sums.items():
            at = np.flatnonzero(c)
            yield pd.DataFrame({"lang": lang, "bucket": at, "n": c[at]})

    src = docs.where(F.col(lang_col).isNotNull()).select(text_of(text_col).alias("t"), F.col(lang_col).cast("string").alias("l"))
    return src.mapInPandas(run, "lang string, bucket int, n long").groupBy("lang", "bucket").agg(F.sum("n").alias("n"))


class LanguageModel:
    """Log-probabilities (bucket x language) with add-``alpha`` smoothing."""

    def __init__(self, counts: dict[str, np.ndarray], alpha: float = 0.1):
        self.langs = sorted(counts)
        c = np.stack([counts[x] for x in self.langs], axis=1).astype(float) + alpha if counts else np.zeros((1 << _BITS, 0))
        self.logp = np.log(c / c.sum(axis=0)).astype(np.float32)
        #: The leading bits of a bucket number nest, so a coarser table needs a shift only.
        self.shift = np.uint32(_BITS - (len(self.logp).bit_length() - 1))

    def word_scores(self, text: str) -> tuple[np.ndarray, np.ndarray]:
        """(scores, times): a row of log-likelihoods for every word, equal rows gathered as they pile up.

        The text is read in slices, so what is held beside it grows with its different words alone.
        """
        raw = np.frombuffer(text.encode("utf-8", "replace"), np.uint8)
        rows, times = np.zeros((0, len(self.langs)), np.float32), np.zeros(0)
        step = max(1 << 10, _CELLS // max(len(self.langs), 1))
        gather = 1 << 17
        for lo in range(0, len(raw), step):
            bucket, first, goes_on = slice_units(raw, lo, min(lo + step, len(raw)))
            if not len(bucket):
                continue
            got = np.add.reduceat(self.logp[bucket >> self.shift], first, axis=0)
            weights = np.ones(len(got))
            if goes_on:  # the slice before ended inside a word; its row is the last one and stands alone
                rows[-1] += got[0]
                got, weights = got[1:], weights[1:]
            rows, times = np.concatenate((rows, got)), np.concatenate((times, weights))
            if len(rows) > gather:
                rows, times = _gathered(rows, times)
                gather = max(gather, 2 * len(rows))
        return rows, times


def _gathered(rows: np.ndarray, times: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Equal rows as one with their summed weights; the last row stays the last, alone."""
    body = np.ascontiguousarray(rows[:-1])
    _, first, back = np.unique(body.view(np.dtype((np.void, body.itemsize * body.shape[1]))).reshape(-1), return_index=True, return_inverse=True)
    return np.concatenate((body[first], rows[-1:])), np.append(np.bincount(back, weights=times[:-1]), times[-1])


def proportions(ll: np.ndarray, times: np.ndarray, rounds: int = 30, tol: float = 1e-4) -> tuple[np.ndarray, float]:
    """Mixture proportions of the columns by expectation-maximisation, and the log-likelihood."""
    top = ll.max(axis=1, keepdims=True)
    lik = np.exp((ll - top).astype(np.float64))
    total = times.sum()
    p = np.full(ll.shape[1], 1 / ll.shape[1])
    for _ in range(rounds):
        new = p * ((times / (lik @ p)) @ lik) / total
        moved = np.abs(new - p).max()
        p = new
        if moved < tol:
            break
    return p, float(times @ np.log(lik @ p) + times @ top[:, 0])


def infer(ll: np.ndarray, times: np.ndarray, penalty: float) -> dict[int, float]:
    """Languages of one document with their proportions, by forward selection."""
    n, k = float(times.sum()), ll.shape[1]
    fit = times @ ll.astype(np.float64)
    chosen = [int(np.argmax(fit))]
    p, best = np.ones(1), float(fit[chosen[0]])
    price = penalty * np.log(max(n, 2))
    while len(chosen) < k:
        # An upper bound on what a language can add: each word takes the better of old and new.
        now = np.log(np.exp((ll[:, chosen] - ll[:, chosen].max(axis=1, keepdims=True)).astype(np.float64)) @ p) + ll[:, chosen].max(axis=1)
        bound = times @ np.maximum(ll - now[:, None], 0)
        bound[chosen] = 0
        tried = []
        for c in np.flatnonzero(bound > price).tolist():
            q, value = proportions(ll[:, [*chosen, c]], times)
            tried.append((value, c, q))
        if not tried:
            break
        value, c, q = max(tried, key=lambda x: (x[0], -x[1]))
        if value - best <= price:
            break
        chosen.append(c)
        p, best = q, value
    return {c: float(x) for c, x in zip(chosen, p, strict=True)}


def table_bits(languages: int) -> int:
    """Bits of a bucket number: as many as keep languages x buckets within ``_TABLE`` cells."""
    bits = _BITS
    while bits > 1 and languages << bits > _TABLE:
        bits -= 1
    return bits


def fit(docs: DataFrame, train: Column, text_col: str = "text", lang_col: str = "lang") -> LanguageModel:
    counts = cut(trigram_counts(docs.where(train), text_col, lang_col))
    bits = table_bits(counts.select("lang").distinct().count())
    by_bucket = counts.groupBy("lang", F.shiftright("bucket", _BITS - bits).alias("bucket")).agg(F.sum("n").alias("n"))
    table: dict[str, np.ndarray] = {}
    # At most _TABLE cells, whatever the corpus and the number of its labels.
    for lang, cells in by_bucket.groupBy("lang").agg(F.collect_list(F.struct("bucket", "n")).alias("c")).collect():
        table[lang] = np.zeros(1 << bits, np.int64)
        table[lang][[c[0] for c in cells]] = [c[1] for c in cells]
    return LanguageModel(table)


def predict(docs: DataFrame, model: LanguageModel, id_col: str = "doc_id", text_col: str = "text", penalty: float = 4.0) -> DataFrame:
    """(doc_id, lang_pred, score, mix): mix lists the document's languages with their proportions."""
    sent = docs.sparkSession.sparkContext.broadcast(model)  # languages x buckets cells

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        m = sent.value
        for b in batches:
            rows = []
            for i, t in zip(b["i"].astype("Int64"), b["t"], strict=True):
                ll, times = m.word_scores(t) if m.langs and has_letter(t) else (np.zeros((0, 0)), None)
                if not len(ll):
                    rows.append((i, "und", 0.0, ""))
                    continue
                mix = sorted(infer(ll, times, penalty).items(), key=lambda x: (-x[1], x[0]))
                rows.append((i, m.langs[mix[0][0]], round(mix[0][1], 6), ",".join(f"{m.langs[c]}:{x:.3f}" for c, x in mix)))
            yield pd.DataFrame(rows, columns=["doc_id", "lang_pred", "score", "mix"]).astype({"doc_id": "Int64"})

    src = docs.select(F.col(id_col).cast("long").alias("i"), text_of(text_col).alias("t"))
    return src.mapInPandas(run, "doc_id long, lang_pred string, score double, mix string")


def op2_language_mix(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    model = fit(docs, ~held_out("doc_id"))
    return predict(docs, model).select("doc_id", held_out("doc_id").alias("held_out"), "lang_pred", "score", "mix")
