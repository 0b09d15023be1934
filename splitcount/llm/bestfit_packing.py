"""Hierarchical residual packing of tokenised documents into sequences of bounded length.

Every partition packs its pieces best-fit, longest first.  Bins that are nearly full are finished;
the others become items of the next round, in which fewer, merged partitions pack whole bins into one
another, again best-fit.  A round's partitions hold about ``round_rows`` bins each, so the last one is
bounded, and rounds end when one partition has seen all open bins or a round merges next to nothing.

Tokens come from a given tokenizer file.  Words between ASCII white space are encoded once per worker
and remembered in a bounded table: this tokenizer drops white space before anything else, so the ids of
a text are those of its words in order.

Defined results: a null or empty text is one piece that holds the end id alone; only texts longer than
a sequence are cut, in full pieces and a rest; rows that repeat are packed like any other; an empty table
gives no rows.
"""

from __future__ import annotations

import os
import re
import zlib
from array import array
from collections import deque
from collections.abc import Iterable, Iterator
from itertools import chain

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from splitcount.llm.common import cut, remembered, small_batches, text_of

CAPACITY = 4096
#: Words above so many bytes are not remembered, and words of so many bytes altogether make the table thin out.
_LONG, _BYTES = 256, 16 << 20


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


class _Places(dict):
    """Numbers words in the order they are first asked for, and lists the new ones."""

    def __init__(self, words: list[bytes]):
        super().__init__(zip(words, range(len(words)), strict=True))
        self.new: list[bytes] = []

    def __missing__(self, word: bytes) -> int:
        self.new.append(word)
        self[word] = at = len(self)
        return at


class WordIds:
    """Ids of white-space-free words, kept in one pool.

    At ``limit`` words the table keeps those met again since it was last thinned.  A new word of plain
    Latin text is lower-cased and cut as the tokenizer does, and its parts are looked up in turn; any
    other word goes to the tokenizer whole.
    """

    #: Words whose normal form and cuts need no more than ASCII and the Latin-1 letters.
    _PLAIN = re.compile(r"(?!.*<\|)[\x21-\x7e\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u00ff]+")
    #: The tokenizer's own cuts, for such lower-cased words.
    _CUTS = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[a-z\u00df-\u00f6\u00f8-\u00ff]+|[0-9]|[^a-z0-9\u00df-\u00f6\u00f8-\u00ff]+")

    def __init__(self, path: str, limit: int = 600_000):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tok, self.limit = Tokenizer.from_file(path), limit
        self.parts: dict[str, bytes] = {}
        self._keep([])

    def _keep(self, words: list[bytes]) -> None:
        old = [self.at[w] for w in words]
        n = self.len[old] if words else np.zeros(0, np.int64)
        ends = np.cumsum(n)
        self.pool = self.pool[np.repeat(self.off[old] - ends + n, n) + np.arange(n.sum())] if words else np.zeros(0, np.uint32)
        self.at, self.size = _Places(words), sum(map(len, words))
        self.len, self.off = n, np.append(0, ends)
        self.uses = np.zeros(len(words), np.int32)

    def _encode(self, words: list[str]) -> list[bytes]:
        """Ids of each word, four bytes each."""
        return [array("I", e.ids).tobytes() for e in self.tok.encode_batch_fast(words, add_special_tokens=False)]

    def _encode_parts(self, parts: list[str]) -> list[bytes]:
        """The same for cuts of words, many to a call: the tokenizer drops the blanks and tells the ids of one cut from the next."""
        out: list[bytes] = []
        for k in range(0, len(parts), 512):
            some = parts[k : k + 512]
            if max(map(len, some)) > _LONG:
                out += self._encode(some)
                continue
            got = self.tok.encode(" ".join(some), add_special_tokens=False)
            cut_of = np.array(got.word_ids, np.int64)
            ends = np.searchsorted(cut_of, np.arange(len(some) + 1))
            if len(cut_of) == 0 or cut_of[-1] != len(some) - 1 or (np.diff(ends) == 0).any():  # not cut as here
                out += self._encode(some)
                continue
            raw, ends = array("I", got.ids).tobytes(), (4 * ends).tolist()
            out += [raw[a:b] for a, b in zip(ends, ends[1:], strict=False)]
        return out

    def _ids_of(self, words: list[bytes]) -> list[bytes]:
        text = [w.decode("utf-8", "replace") for w in words]
        cuts = [self._CUTS.findall(t.lower()) if self._PLAIN.fullmatch(t) else None for t in text]
        if len(self.parts) > self.limit:
            self.parts.clear()
        parts = self.parts
        shared = {p for c in cuts if c and len(c) > 1 for p in c}
        new = sorted((shared | {c[0] for c in cuts if c and len(c) == 1}) - parts.keys())
        parts.update(zip(new, self._encode_parts(new), strict=True))
        odd = iter(self._encode([t for t, c in zip(text, cuts, strict=True) if c is None]))
        out = [next(odd) if c is None else parts[c[0]] if len(c) == 1 else b"".join(map(parts.__getitem__, c)) for c in cuts]
        for p in new:
            if len(p) > _LONG or p not in shared:  # long parts are forgotten at once, as are words that the table holds whole
                del parts[p]
        return out

    def _learn(self) -> None:
        got = self._ids_of(self.at.new)
        self.size += sum(map(len, self.at.new))
        self.at.new = []
        n = np.fromiter(map(len, got), np.int64, len(got)) // 4
        self.len = np.concatenate((self.len, n))
        self.off = np.concatenate((self.off, self.off[-1] + np.cumsum(n)))
        self.uses = np.concatenate((self.uses, np.zeros(len(got), np.int32)))
        self.pool = np.concatenate((self.pool, np.frombuffer(b"".join(got), np.uint32)))

    def ids(self, texts: Iterable[str]) -> Iterator[np.ndarray]:
        """Ids per text; texts are taken in groups so that a group's new words are encoded together."""
        group: list[list[bytes]] = []
        size = 0
        for t in texts:
            group.append(t.encode("utf-8", "replace").split())
            size += len(group[-1]) + len(t) // 64  # a text may be one long word
            if size > 400_000:
                yield from self._group(group)
                group, size = [], 0
        yield from self._group(group)

    def _group(self, group: list[list[bytes]]) -> Iterator[np.ndarray]:
        if len(self.at) > self.limit or self.size > _BYTES:
            uses = self.uses.tolist()
            self._keep([w for w, k in self.at.items() if uses[k] > 1 and len(w) <= _LONG])
        places = [np.fromiter(map(self.at.__getitem__, words), np.int64, len(words)) for words in group]
        self._learn()
        for at in places:
            self.uses[at] += 1
            n = self.len[at]
            ends = np.cumsum(n)
            total = int(ends[-1]) if len(n) else 0
            yield self.pool[np.repeat(self.off[at] - ends + n, n) + np.arange(total)]


def best_fit(sizes: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Best-fit, longest first: (bin, offset) per item and the fill per bin."""
    bins, offs = np.empty(len(sizes), np.int64), np.empty(len(sizes), np.int64)
    by_room: list[list[int]] = [[] for _ in range(capacity + 1)]
    free = 0  # bit r: some bin has room r
    fill: list[int] = []
    order = np.argsort(-sizes, kind="stable")
    for i, s in zip(order.tolist(), sizes[order].tolist(), strict=True):
        fits = free >> s
        if fits:
            room = s + (fits & -fits).bit_length() - 1
            k = by_room[room].pop()
            if not by_room[room]:
                free &= ~(1 << room)
        else:
            room, k = capacity, len(fill)
            fill.append(0)
        bins[i], offs[i] = k, fill[k]
        fill[k] += s
        if room > s:
            by_room[room - s].append(k)
            free |= 1 << (room - s)
    return bins, offs, np.array(fill, np.int64)


_PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long, bin long, offset long, open boolean"
_ARROW = pa.schema([(name, {"long": pa.int64(), "int": pa.int32(), "boolean": pa.bool_()}[kind]) for name, kind in map(str.split, _PIECES.split(", "))])
#: Rows of a batch that are Python strings at once.
_SLICE = 100


def _texts(batches: Iterator[pa.RecordBatch], docs: deque[int | None]) -> Iterator[str]:
    """The texts, a few of them outside Arrow at a time and no batch kept while the next one is read; their ids go to ``docs``."""
    while (batch := next(batches, None)) is not None:
        for at in range(0, batch.num_rows, _SLICE):
            docs.extend(batch["i"].slice(at, _SLICE).to_pylist())
            yield from batch["t"].slice(at, _SLICE).to_pylist()
        del batch


def _bin_numbers(round_no: int, n: int, first: int = 0) -> np.ndarray:
    """Numbers no other task or round gives out."""
    part = TaskContext.get().partitionId() if TaskContext.get() else 0
    return (np.int64(round_no) << 56) + (np.int64(part) << 32) + first + np.arange(n, dtype=np.int64)


def _pack_local(path: str, capacity: int, end_id: int, slack: int, hold: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows: list[tuple] = []
        used = 0

        def flush() -> pa.RecordBatch:
            nonlocal rows, used
            f = pd.DataFrame(rows, columns=["doc_id", "piece", "start", "length", "ids_crc32"])
            f["doc_id"] = f["doc_id"].astype("Int64")
            b, o, fill = best_fit(f["length"].to_numpy(), capacity)
            f["bin"], f["offset"] = _bin_numbers(0, len(fill), used)[b], o
            f["open"] = fill[b] < capacity - slack
            rows, used = [], used + len(fill)
            return pa.RecordBatch.from_pandas(f, _ARROW, preserve_index=False)

        docs: deque[int | None] = deque()
        texts = _texts(batches, docs)
        first = next(texts, None)
        if first is None:
            return
        for got in remembered(("word ids", path), lambda: WordIds(path)).ids(chain([first], texts)):
            doc, got = docs.popleft(), np.append(got, np.uint32(end_id)).astype("<u4")
            for k, at in enumerate(range(0, len(got), capacity)):
                part = got[at : at + capacity]
                rows.append((doc, k, at, len(part), zlib.crc32(part.tobytes())))
            if len(rows) >= hold:
                yield flush()
        if rows:
            yield flush()

    return run


def _pack_bins(round_no: int, capacity: int, slack: int):
    """Whole bins as items; offsets inside an item shift with it."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        got = list(batches)
        if not got:
            return
        f = pd.concat(got, ignore_index=True)
        keys, item = np.unique(f["bin"].to_numpy(), return_inverse=True)
        sizes = np.bincount(item, weights=f["length"].to_numpy()).astype(np.int64)
        b, o, fill = best_fit(sizes, capacity)
        f["bin"] = _bin_numbers(round_no, len(fill))[b[item]]
        f["offset"] = f["offset"].to_numpy() + o[item]
        f["open"] = fill[b[item]] < capacity - slack
        f["doc_id"] = f["doc_id"].astype("Int64")
        yield f

    return run


def pack(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    tokenizer: str | None = None,
    capacity: int = CAPACITY,
    end_id: int = 1,
    slack: int = 16,
    hold: int = 100_000,
    round_rows: int = 40_000,
) -> DataFrame:
    """One row per piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset.

    ``slack``: a bin with at most so much room is finished.  ``hold``: pieces that a task packs at once.
    ``round_rows``: pieces of open bins per task in the merge rounds.
    """
    src = docs.select(F.col(id_col).cast("long").alias("i"), text_of(text_col).alias("t"))
    with small_batches(docs.sparkSession):
        state = cut(src.mapInArrow(_pack_local(tokenizer or default_tokenizer(), capacity, end_id, slack, hold), _PIECES))
    done = [state.where(~F.col("open"))]
    left = state.where("open")
    bins_before = None
    for round_no in range(1, 64):
        rows, bins = left.agg(F.count("*"), F.count_distinct("bin")).first()
        if not rows:
            break
        parts = -(-rows // round_rows)
        if bins_before and bins_before[2] == parts and bins > 0.995 * bins_before[1]:
            break
        salted = F.xxhash64(F.lit(round_no), "bin")
        merged = cut(left.repartition(parts, salted).mapInPandas(_pack_bins(round_no, capacity, slack), _PIECES))
        bins_before = (rows, bins, parts)
        done.append(merged.where(~F.col("open")))
        left = merged.where("open")
        if parts == 1:
            break
    done.append(left)
    out = done[0]
    for more in done[1:]:
        out = out.unionByName(more)
    return out.select("doc_id", "piece", "start", "length", "ids_crc32", F.col("bin").alias("sequence_id"), "offset")


def op5_bestfit_packing(spark, sf_dir: str) -> DataFrame:
    return pack(spark.read.parquet(f"{sf_dir}/documents.parquet"))
