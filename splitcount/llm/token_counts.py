"""Edit-aware token counts.

A document is held as a segment tree over its pre-tokens: leaves are short runs of pre-tokens with their
text, lengths and token counts, inner nodes hold the sums.  An edit goes down the tree to the place it
touches, steps back over the few characters of context that a cut may depend on, and re-encodes from
there only until a new cut falls on an old one; sums change along the touched paths alone.

The pre-tokeniser matches from left to right and a match depends on its own text and at most two
characters after it (a contraction's letters), so everything before the context and after the first
shared cut keeps its tokens.  Counts after edits therefore equal those of encoding the new text anew.

Defined results: a null or empty text has no tokens and takes no edits; edits are given in the old
text's code points, must not overlap, and an edit without effect costs nothing.
"""

from __future__ import annotations

import base64
import re
from collections.abc import Callable, Iterator
from itertools import accumulate

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from splitcount.llm.common import remembered, text_of

_CONTEXT = 3
_RUN = 64
#: Longest pre-token that is remembered, in characters: bounds the memory of counts in bytes.
_KNOWN = 64
#: Texts whose letters, digits and spaces the short pattern below knows.
_PLAIN = re.compile(r"[\t\n\r\x20-\x7eÀ-ÖØ-öø-ÿ]*")
#: The tokenizer's cuts, for such texts.
_PLAIN_CUTS = re.compile(
    r"'s|'t|'re|'ve|'m|'ll|'d| ?[A-Za-zÀ-ÖØ-öø-ÿ]+| ?[0-9]+"
    r"| ?[^\t\n\r 0-9A-Za-zÀ-ÖØ-öø-ÿ]+|[\t\n\r ]+(?![^\t\n\r ])|[\t\n\r ]+"
)


def default_ranks() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken")


class PieceCounter:
    """Token counts of pre-tokens, remembered up to a bound."""

    def __init__(self, path: str, limit: int = 700_000):
        import public_tokenizers
        import regex
        import tiktoken

        with open(path, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in (x.split() for x in f if x.strip())}
        self.encoding = tiktoken.Encoding("counts", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
        self.cuts, self.limit = regex.compile(public_tokenizers.PATTERN), limit
        self.known: dict[str, int] = {}

    def pieces(self, text: str) -> list[str]:
        return (_PLAIN_CUTS if _PLAIN.fullmatch(text) else self.cuts).findall(text)

    def finditer(self, text: str, start: int):
        return (_PLAIN_CUTS if _PLAIN.fullmatch(text) else self.cuts).finditer(text, start)

    def count(self, piece: str) -> int:
        n = self.known.get(piece)
        if n is None:
            n = len(self.encoding.encode_ordinary(piece))
            if len(piece) <= _KNOWN:  # long pre-tokens seldom come again
                if len(self.known) > self.limit:
                    self.known.clear()
                self.known[piece] = n
        return n

    def counts(self, pieces: list[str]) -> list[int]:
        got = list(map(self.known.get, pieces))
        if None in got:
            got = [self.count(p) if n is None else n for p, n in zip(pieces, got, strict=True)]
        return got


class TokenTree:
    """Pre-tokens of one text under a tree of sums; node 1 is the root, leaf k is node ``size + k``.

    A leaf holds its stretch of the text, and the length and token count of each of its pre-tokens.  Nothing else
    holds the text, so an edit costs what it touches and a path to the root.
    """

    def __init__(self, text: str, counter: PieceCounter):
        self.counter, self.reencoded = counter, 0
        pieces = counter.pieces(text)
        self._lay(text, list(map(len, pieces)), counter.counts(pieces))

    def _lay(self, text: str, lens: list[int], counts: list[int]) -> None:
        cuts = range(0, max(len(lens), 1), _RUN)
        self.lens = [lens[i : i + _RUN] for i in cuts]
        self.counts = [counts[i : i + _RUN] for i in cuts]
        n = len(self.lens)
        self.size = 1 << (n - 1).bit_length()
        self.chars, self.tokens = [0] * (2 * self.size), [0] * (2 * self.size)
        self.chars[self.size : self.size + n] = map(sum, self.lens)
        self.tokens[self.size : self.size + n] = map(sum, self.counts)
        ends = list(accumulate(self.chars[self.size : self.size + n]))
        self.parts = [text[a:z] for a, z in zip([0, *ends], ends, strict=False)]
        for sums in (self.chars, self.tokens):
            for k in range(self.size - 1, 0, -1):
                sums[k] = sums[2 * k] + sums[2 * k + 1]

    @property
    def text(self) -> str:
        return "".join(self.parts)

    @property
    def total(self) -> int:
        return self.tokens[1]

    @property
    def n_pieces(self) -> int:
        return sum(map(len, self.lens))

    def _leaf_at(self, place: int) -> tuple[int, int]:
        """Leaf that holds character ``place`` (the last one for the end), and where it starts."""
        k, start = 1, 0
        while k < self.size:
            k *= 2
            if place >= start + self.chars[k] and self.chars[k + 1]:
                start += self.chars[k]
                k += 1
        return k - self.size, start

    def _read(self, start: int, end: int) -> str:
        """Characters start..end of the text."""
        if start >= end:
            return ""
        leaf, at = self._leaf_at(start)
        out = [self.parts[leaf][start - at : end - at]]
        at += len(self.parts[leaf])
        while at < end:
            leaf += 1
            out.append(self.parts[leaf][: end - at])
            at += len(self.parts[leaf])
        return "".join(out)

    def _touch(self, leaf: int) -> None:
        k = self.size + leaf
        self.chars[k], self.tokens[k] = sum(self.lens[leaf]), sum(self.counts[leaf])
        while k > 1:
            k //= 2
            self.chars[k] = self.chars[2 * k] + self.chars[2 * k + 1]
            self.tokens[k] = self.tokens[2 * k] + self.tokens[2 * k + 1]

    def replace(self, start: int, end: int, new: str) -> None:
        """Replace characters start..end by ``new`` and bring the counts up to date."""
        if self._read(start, end) == new:
            return
        shift, old_length = len(new) - (end - start), self.chars[1]
        edited = start + len(new)  # where the edit ends in the new text

        def after(a: int, z: int) -> str:
            """Characters a..z of the new text."""
            return self._read(a, min(z, start)) + new[max(a - start, 0) : max(z - start, 0)] + self._read(max(a, edited) - shift, z - shift)

        # First pre-token that ends within the context before the edit.
        leaf, at = self._leaf_at(max(0, start - _CONTEXT))
        begin, piece = at, 0
        while piece < len(self.lens[leaf]) - 1 and at + self.lens[leaf][piece] <= start - _CONTEXT:
            at += self.lens[leaf][piece]
            piece += 1
        first_leaf, first_piece, cut = leaf, piece, at
        # Old cuts from the end of the edit on, walked in step with the new ones.
        old = at
        lens, counts, found = [], [], []

        def step() -> bool:
            """Move the old cut past one pre-token."""
            nonlocal leaf, piece, old
            while leaf < len(self.lens) and piece >= len(self.lens[leaf]):
                leaf, piece = leaf + 1, 0
            if leaf >= len(self.lens):
                return False
            old += self.lens[leaf][piece]
            piece += 1
            return True

        met = False
        for token in self._cuts_from(after, old_length + shift, at):
            lens.append(len(token))
            counts.append(self.counter.count(token))
            found.append(token)
            at += len(token)
            while old < end or old + shift < at:
                if not step():
                    break
            if old >= end and old + shift == at:
                met = True
                break
        self.reencoded += len(lens)
        if not met:  # the new cuts ran to the end of the text
            while old < old_length and step():
                pass
        if leaf < len(self.lens):
            left = sum(self.lens[leaf][piece:])
            rest = (self.lens[leaf][piece:], self.counts[leaf][piece:], self.parts[leaf][len(self.parts[leaf]) - left :])
        else:
            leaf, rest = len(self.lens) - 1, ([], [], "")
        head = (self.lens[first_leaf][:first_piece], self.counts[first_leaf][:first_piece], self.parts[first_leaf][: cut - begin])
        for k in range(first_leaf, leaf + 1):
            self.lens[k], self.counts[k], self.parts[k] = [], [], ""
        self.lens[first_leaf], self.counts[first_leaf], self.parts[first_leaf] = head[0] + lens, head[1] + counts, head[2] + "".join(found)
        if leaf == first_leaf:
            self.lens[leaf] += rest[0]
            self.counts[leaf] += rest[1]
            self.parts[leaf] += rest[2]
        else:
            self.lens[leaf], self.counts[leaf], self.parts[leaf] = rest
        if len(self.lens[first_leaf]) > 8 * _RUN:  # an overgrown leaf: lay the leaves out anew, without encoding
            self._lay(self.text, [x for r in self.lens for x in r], [x for r in self.counts for x in r])
        else:
            for k in range(first_leaf, leaf + 1):
                self._touch(k)

    def _cuts_from(self, read: Callable[[int, int], str], length: int, at: int) -> Iterator[str]:
        """The pre-tokens from the cut ``at`` on; reads windows, doubling as needed."""
        width = 256
        while at < length:
            stop = min(length, at + width)
            window = read(at, stop)
            done = 0
            for m in self.counter.finditer(window, 0):
                # Near a window's end a match could still grow or change.
                if stop < length and m.end() > len(window) - _CONTEXT:
                    break
                yield m[0]
                done = m.end()
            at += done
            width = width * 2 if not done else 256


_EDITS = re.compile(r"[\w.+-]+@[\w-]+(?:\.[\w-]+)+|\d{8,}|([#*$%&!])\1{2,}")


def cleaning_edits(text: str) -> list[tuple[int, int, str]]:
    """Edits of a cleaning pass: mail addresses and long numbers become marks, runs of a sign one sign."""
    out = []
    for m in _EDITS.finditer(text):
        new = m[1] if m[1] else "<mail>" if "@" in m[0] else "<number>"
        out.append((m.start(), m.end(), new))
    return out


def counts_with_edits(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", edits=cleaning_edits, ranks: str | None = None) -> DataFrame:
    """(doc_id, n_pieces, n_tokens, n_edits, n_reencoded, n_tokens_after); ``edits`` maps a text to its edits."""
    path = ranks or default_ranks()

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        counter = remembered(("piece counts", path), lambda: PieceCounter(path))
        for b in batches:
            rows = []
            for i, t in zip(b["i"].astype("Int64"), b["t"], strict=True):
                tree = TokenTree(t, counter)
                before, pieces = tree.total, tree.n_pieces
                todo = edits(t)
                for a, z, new in reversed(todo):  # from the back, so that places stay those of the old text
                    tree.replace(a, z, new)
                rows.append((i, pieces, before, len(todo), tree.reencoded, tree.total))
            yield pd.DataFrame(rows, columns=["doc_id", "n_pieces", "n_tokens", "n_edits", "n_reencoded", "n_tokens_after"]).astype({"doc_id": "Int64"})

    src = docs.select(F.col(id_col).cast("long").alias("i"), text_of(text_col).alias("t"))
    return src.mapInPandas(run, "doc_id long, n_pieces long, n_tokens long, n_edits long, n_reencoded long, n_tokens_after long")


def op7_token_counts(spark, sf_dir: str) -> DataFrame:
    return counts_with_edits(spark.read.parquet(f"{sf_dir}/documents.parquet"))
