"""SentencePiece encoding with seeded merge-dropout, and lossless decoding.

Pieces are merged by an agenda, best piece first and leftmost among equals.  With dropout, every popped
candidate is skipped with the given rate, by draws keyed on (seed, document id, place of the unit in its
text, number of the pop): each occurrence of a word is cut on its own, and the same key always gives the
same segmentation.  The draws of an occurrence are its gaps between skips, of geometric law.  What a unit
becomes depends on nothing but which of its pops are skipped, so a worker remembers units by that (in
bounded arrays, in which all occurrences of a group of texts go from skip to skip together), and what it
remembers never changes a result.  Rate 0 is the plain encoding.

The text is cut into units at spaces and at characters that no piece holds; no piece spans such a cut, so
unit by unit encoding is exact.  Characters without a piece become byte pieces; so does the character
U+2581, which pieces use for a space, and decoding gives back every text exactly.

Defined results: a null or empty text has no pieces and decodes to the empty text; rows that repeat get
equal pieces; an empty table gives no rows.
"""

from __future__ import annotations

import contextlib
import gc
import heapq
import math
import re
import zlib
from array import array
from collections.abc import Iterable, Iterator
from itertools import chain, compress, repeat

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from splitcount.llm.common import remembered, text_of

_SPACE = "▁"
_NEVER = float("inf")
#: Step between places, and the multipliers of the keyed hash.
_STEP, _MIX_A, _MIX_B = 0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9, 0x94D049BB133111EB
#: Units above so many characters take the heap, and are not remembered; places in the others fit six bits.
_LONG = 48
#: Skips of pops from here on are not remembered: the pops of remembered skips fit six bits.
_DEEP = 64
#: Units whose agendas run in step, and units of texts that go together.
_GROUP, _TOGETHER = 4096, 1 << 17
#: An agenda's place without a candidate.
_LAST = np.int32(2**31 - 1)
_UNITS = re.compile(f" +[^ \\n{_SPACE}]*|[^ \\n{_SPACE}]+|[\\n{_SPACE}]")


def default_model() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


class _Table:
    """Numbers by keys, neither below 0: slots in arrays, asked and filled many at a time."""

    def __init__(self, room: int = 1024):
        self.n = 0
        self._lay(room)

    def _lay(self, room: int) -> None:
        bits = max(4, (4 * room - 1).bit_length())
        self.shift, self.wrap = np.uint64(64 - bits), (1 << bits) - 1
        self.keys, self.values = np.full(1 << bits, -1, np.int64), np.full(1 << bits, -1, np.int64)

    def _slot(self, key: np.ndarray) -> np.ndarray:
        return ((key.view(np.uint64) * np.uint64(_STEP)) >> self.shift).view(np.int64)

    def put(self, key: np.ndarray, value: np.ndarray) -> None:
        """Keys that differ and are not there yet."""
        self.n += len(key)
        if 2 * self.n > len(self.keys):
            old = self.keys >= 0
            key, value = np.concatenate([self.keys[old], key]), np.concatenate([self.values[old], value])
            self._lay(self.n)
        at = self._slot(key)
        while len(key):
            free = self.keys[at] < 0
            self.keys[at[free]] = key[free]  # of several for one slot, one gets it
            got = self.keys[at] == key
            self.values[at[got]] = value[got]
            key, value, at = key[~got], value[~got], at[~got] + 1 & self.wrap

    def find(self, key: np.ndarray) -> np.ndarray:
        """-1 where there is none."""
        at = self._slot(key)
        found = self.keys[at]
        open_ = np.flatnonzero((found != key) & (found >= 0))
        while len(open_):
            at[open_] = at[open_] + 1 & self.wrap
            found = self.keys[at[open_]]
            open_ = open_[(found != key[open_]) & (found >= 0)]
        return np.where(self.keys[at] == key, self.values[at], -1)


def _stretches(at: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Every place of the stretches that start at ``at``, in a row."""
    ends = np.cumsum(size)
    return np.repeat(at - ends + size, size) + np.arange(ends[-1] if len(ends) else 0)


def _with(have: np.ndarray, n: int, more: np.ndarray) -> np.ndarray:
    """``have`` with ``more`` from place n on, in a larger array where it is full."""
    if n + len(more) > len(have):
        have = np.concatenate([have[:n], np.empty(n + len(more), have.dtype)])
    have[n : n + len(more)] = more
    return have


class Pieces:
    """Vocabulary, encoder and decoder of one model file."""

    def __init__(self, path: str, rate: float = 0.1, seed: int = 2024, limit: int = 400_000):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        n = sp.get_piece_size()
        self.byte = [0] * 256
        self.order: dict[str, float] = {}
        self.ids: dict[str, int] = {}
        self.raw: list[bytes] = [b""] * n
        for i in range(n):
            name = sp.id_to_piece(i)
            if sp.is_byte(i):
                self.byte[int(name[1:-1], 16)] = i
                self.raw[i] = bytes([int(name[1:-1], 16)])
            elif not (sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i)):
                self.order[name], self.ids[name] = -sp.get_score(i), i
                self.raw[i] = name.replace(_SPACE, " ").encode()
        self.rate, self.seed, self.limit = rate, seed, limit
        self._merges()
        #: Rate 1 leaves no gap.
        self.per_gap = 1 / math.log1p(-rate) if 0 < rate < 1 else 0.0
        self.raw_size = np.array(list(map(len, self.raw)), np.int64)
        self.raw_at, self.raw_all = np.cumsum(self.raw_size) - self.raw_size, np.frombuffer(b"".join(self.raw), np.uint8)
        self._empty()

    def _empty(self) -> None:
        """No form is remembered.

        A form is what a unit becomes when certain of its pops are skipped.  Forms have numbers: units have those of
        their forms without skips, and a step leads from a form to that with one more, later skip.
        """
        self.known: dict[str, int] = {}
        self.steps = _Table()
        self.n = self.n_chars = self.n_ids = 0
        self.chars, self.ids_all = np.empty(0, np.int32), np.empty(0, np.int32)
        #: By form: its unit's stretch of chars, its skipped pops as bits, its stretch of ids, its pops and how often it was met.
        self.char_at, self.char_n, self.skips = np.empty(0, np.int64), np.empty(0, np.int32), np.empty(0, np.uint64)
        self.ids_at, self.ids_n, self.pops, self.met = np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0, np.int64)

    def _forget(self) -> None:
        """Keep the forms met twice or more since the last time, if those are not too many; the way to each was met as often."""
        n = self.n
        keep = self.met[:n] > 1
        if keep.sum() > 2 * self.limit:
            keep[:] = False
        to = np.cumsum(keep) - 1
        known, old = self.known, self.steps
        kept = {x: getattr(self, x)[:n][keep] for x in ("char_at", "char_n", "skips", "ids_at", "ids_n", "pops")}
        chars, ids = self.chars, self.ids_all
        self._empty()
        place = np.fromiter(known.values(), np.int64, len(known))
        self.known = dict(zip(compress(known, keep[place]), to[place[keep[place]]].tolist(), strict=True))
        from_ = old.keys[old.keys >= 0]
        into = old.values[old.keys >= 0]
        both = keep[from_ >> 6] & keep[into]
        self.steps.put(to[from_[both] >> 6] << 6 | from_[both] & 63, to[into[both]])
        # Forms of one unit share its characters.
        first, of = np.unique(kept["char_at"], return_index=True)
        size = kept["char_n"][of].astype(np.int64)
        self.chars, self.n_chars = chars[_stretches(first, size)], int(size.sum())
        kept["char_at"] = (np.cumsum(size) - size)[np.searchsorted(first, kept["char_at"])]
        self.ids_all, self.n_ids = ids[_stretches(kept["ids_at"], kept["ids_n"])], int(kept["ids_n"].sum())
        kept["ids_at"] = np.cumsum(kept["ids_n"]) - kept["ids_n"]
        for x, values in kept.items():
            setattr(self, x, values)
        self.n = len(kept["pops"])
        self.met = np.zeros(self.n, np.int64)

    def unit(self, unit: str, skips: int = 0) -> tuple[bytes, int]:
        """Piece ids of one unit, four bytes each, and its pops; bit k of ``skips`` drops pop k."""
        text = unit.replace(" ", _SPACE) if unit != _SPACE else ""
        if not text:
            return array("I", [self.byte[b] for b in _SPACE.encode()]).tobytes(), 0
        syms, pops = self._short(text, skips) if len(text) <= _LONG else self._long(text, skips)
        out = list(map(self.ids.get, syms))
        if None in out:
            out = [i for x, got in zip(syms, out, strict=True) for i in ([self.byte[c] for c in x.encode("utf-8", "replace")] if got is None else (got,))]
        return array("I", out).tobytes(), pops

    def _short(self, text: str, skips: int) -> tuple[list[str], int]:
        """The agenda as a list of the neighbours' orders; the smallest, leftmost one is next."""
        get = self.order.get
        syms, pops = list(text), 0
        agenda = [get(a + b, _NEVER) for a, b in zip(syms, syms[1:], strict=False)]
        while agenda:
            best = min(agenda)
            if best == _NEVER:
                break
            i = agenda.index(best)
            pops += 1
            if skips >> pops - 1 & 1:
                agenda[i] = _NEVER
                continue
            j = i + 1
            syms[i] = piece = syms[i] + syms[j]
            del syms[j], agenda[i]
            if j < len(syms):
                agenda[i] = get(piece + syms[j], _NEVER)
            if i:
                agenda[i - 1] = get(syms[i - 1] + piece, _NEVER)
        return syms, pops

    def _long(self, text: str, skips: int) -> tuple[list[str], int]:
        """The same with a heap, in time n log n."""
        drop = np.unpackbits(np.frombuffer(skips.to_bytes(skips.bit_length() // 8 + 1, "little"), np.uint8), bitorder="little").tolist()
        pop, last = 0, len(drop)
        n, get = len(text), self.order.get
        end = list(range(1, n + 1))  # end of the symbol that starts here; 0 once merged away
        back = list(range(-1, n - 1))  # start of the symbol before
        agenda = [(o, i, i + 2) for i in range(n - 1) if (o := get(text[i : i + 2])) is not None]
        heapq.heapify(agenda)
        while agenda:
            _, a, z = heapq.heappop(agenda)
            b = end[a]
            if not b or b >= z or end[b] != z:
                continue  # one of the two symbols has changed
            pop += 1
            if pop <= last and drop[pop - 1]:
                continue
            end[a], end[b] = z, 0
            if z < n:
                back[z] = a
                o = get(text[a : end[z]])
                if o is not None:
                    heapq.heappush(agenda, (o, a, end[z]))
            p = back[a]
            if p >= 0:
                o = get(text[p:z])
                if o is not None:
                    heapq.heappush(agenda, (o, p, z))
        return [text[a : end[a]] for a in range(n) if end[a]], pop

    def _merges(self) -> None:
        """What two neighbouring pieces become, by their ids in one number, and what characters are in an agenda."""
        made = {self.ids[a] << 32 | self.ids[b]: (o, self.ids[x]) for x, o in self.order.items() for k in range(1, len(x)) if (a := x[:k]) in self.ids and (b := x[k:]) in self.ids}
        # Orders as ranks, equal where they are.
        rank = np.unique([o for o, _ in made.values()], return_inverse=True)[1].astype(np.int64)
        self.merges = _Table(len(made))
        self.merges.put(np.array(list(made), np.int64), rank << 32 | np.array([i for _, i in made.values()], np.int64))
        #: Pieces, or below -1 what has none: -2 less the code point.
        self.piece_of = np.arange(-2, -2 - 0x110000, -1, dtype=np.int32)
        for x, i in self.ids.items():
            if len(x) == 1:
                self.piece_of[ord(x)] = i
        self.piece_of[ord(" ")], self.piece_of[ord(_SPACE)] = self.piece_of[ord(_SPACE)], -2 - ord(_SPACE)
        #: Characters of pieces that are none themselves; units of these go by their text.
        self.odd = {c for x in self.ids for c in x} - self.ids.keys()
        if _SPACE in self.odd:
            self.odd.add(" ")

    def _joined(self, left: np.ndarray, right: np.ndarray, place: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The agenda's number and the id of what the neighbours become; numbers go by order, then place."""
        key = left.astype(np.int64) << 32 | right
        key[right < 0] = -2
        found = self.merges.find(key)
        return np.where(found < 0, _LAST, (found >> 32 << 6 | place)).astype(np.int32), found.astype(np.int32)

    def _many(self, start: np.ndarray, size: np.ndarray, skips: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(ids in a row, their number, pops) of units, all agendas in step: every round is one pop of each.

        ``start`` and ``size`` are the units' stretches of characters; bit k of ``skips`` drops pop k.  Units are columns.
        A unit's pieces stay where they start and are chained, so a merge touches its neighbours alone.
        """
        n, width = len(size), int(size.max())
        rows = np.arange(width + 1)[:, None]
        inside = rows < size
        x = np.full((width + 1, n), -1, np.int32)  # the last place is the end of every chain
        x[inside] = self.chars[(start + rows)[inside]]
        agenda, made = self._joined(x[:-1].reshape(-1), x[1:].reshape(-1), np.repeat(rows[:-1, 0], n))
        by_row, x = agenda.reshape(width, n), x.reshape(-1)
        after, before = np.arange(n, n * (width + 2)), np.arange(-n, n * width)
        pops, pop, any_skip = np.zeros(n, np.int64), 0, bool(skips.any())
        while True:
            best = by_row.min(axis=0)
            going = np.flatnonzero(best != _LAST)
            if not len(going):
                break
            a = (best[going] & 63).astype(np.int64) * n + going
            pop += 1
            pops[going] = pop
            if any_skip and pop <= _DEEP:
                out = (skips[going] >> np.uint64(pop - 1) & np.uint64(1)).astype(bool)
                agenda[a[out]] = _LAST
                a = a[~out]
            b = after[a]
            c = after[b]
            x[a] = piece = made[a]
            # The second piece's own place in the agenda goes with it.
            x[b], agenda[b] = -1, _LAST
            after[a], before[c] = c, a
            p = before[a]
            has = np.flatnonzero(p >= 0)
            p = p[has]
            cell = np.concatenate([a, p])
            agenda[cell], made[cell] = self._joined(np.concatenate([piece, x[p]]), np.concatenate([x[c], piece[has]]), cell // n)
        x = x.reshape(width + 1, n).T
        alive = x != -1
        return x[alive], alive.sum(axis=1), pops

    def _learn(self, char_at: np.ndarray, char_n: np.ndarray, skips: np.ndarray) -> np.ndarray:
        """Numbers of new forms, whose agendas run in groups of like length."""
        new = np.arange(self.n, self.n + len(char_at))
        by_size = np.argsort(char_n, kind="stable")
        for lo in range(0, len(new), _GROUP):
            part = by_size[lo : lo + _GROUP]
            ids, lens, pops = self._many(char_at[part], char_n[part], skips[part])
            none = np.flatnonzero(ids < 0)
            if len(none):  # characters without a piece become byte pieces
                put = [[self.byte[b] for b in chr(c).encode("utf-8", "replace")] for c in (-2 - ids[none]).tolist()]
                each = np.ones(len(ids), np.int64)
                each[none] = list(map(len, put))
                ids, lens = np.repeat(ids, each), np.add.reduceat(each, np.cumsum(lens) - lens)
                ids[_stretches((np.cumsum(each) - each)[none], each[none])] = list(chain.from_iterable(put))
            self._add(char_at[part], char_n[part], skips[part], ids, lens, pops)
        out = np.empty_like(new)
        out[by_size] = new
        return out

    def _add(self, char_at: np.ndarray, char_n: np.ndarray, skips: np.ndarray, ids: np.ndarray, lens: np.ndarray, pops: np.ndarray) -> None:
        n = self.n
        self.char_at, self.char_n, self.skips = _with(self.char_at, n, char_at), _with(self.char_n, n, char_n), _with(self.skips, n, skips)
        self.ids_at, self.ids_n = _with(self.ids_at, n, np.cumsum(lens) - lens + self.n_ids), _with(self.ids_n, n, lens)
        self.pops, self.met = _with(self.pops, n, pops), _with(self.met, n, np.zeros(len(pops), np.int64))
        self.ids_all = _with(self.ids_all, self.n_ids, ids)
        self.n, self.n_ids = n + len(pops), self.n_ids + len(ids)

    def _meet(self, units: list[str]) -> None:
        """Make units known."""
        size = np.fromiter(map(len, units), np.int64, len(units))
        at = self.n_chars + np.cumsum(size) - size
        self.chars = _with(self.chars, self.n_chars, self.piece_of[np.frombuffer("".join(units).encode("utf-32-le", "surrogatepass"), "<u4")])
        self.n_chars += int(size.sum())
        self.known.update(zip(units, self._learn(at, size, np.zeros(len(units), np.uint64)).tolist(), strict=True))

    def _step(self, key: np.ndarray) -> np.ndarray:
        """The forms with one more skip, for (form, pop) as a number, where no step is known."""
        form = key >> 6
        to = self._learn(self.char_at[form], self.char_n[form], self.skips[form] | np.uint64(1) << (key & 63).astype(np.uint64))
        self.steps.put(key, to)
        return to

    def _gap(self, at: np.ndarray, nth: int | np.ndarray) -> np.ndarray:
        """The nth run of pops without a skip, of each key."""
        x = at + (np.uint64(nth * _MIX_B % 2**64) if isinstance(nth, int) else nth.astype(np.uint64) * np.uint64(_MIX_B))
        x = (x ^ x >> np.uint64(30)) * np.uint64(_MIX_A)
        x = (x ^ x >> np.uint64(27)) * np.uint64(_MIX_B)
        x ^= x >> np.uint64(31)
        # At most 53 bits and above 0, so the logarithm is finite.
        return (np.log(((x >> np.uint64(11)) + np.uint64(1)) * 2.0**-53) * self.per_gap).astype(np.int64)

    def _alone(self, unit: str, at: np.ndarray) -> np.ndarray:
        """The ids of one occurrence that is not remembered."""
        skips = 0
        if self.rate > 0:
            # A pop takes a candidate away; there is one between two characters, and a merge makes at most two.
            most = 3 * len(unit)
            bits, pop, nth = np.zeros(most, np.uint8), -1, 0
            while pop < most:
                to = pop + np.cumsum(1 + self._gap(at, np.arange(nth, nth + 1024)))
                bits[to[to < most]] = 1
                pop, nth = int(to[-1]), nth + 1024
            skips = int.from_bytes(np.packbits(bits, bitorder="little").tobytes(), "little")
        return np.frombuffer(self.unit(unit, skips)[0], np.uint32).astype(np.int32)

    def _together(self, units: list[str], at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids in a row, their number by unit) of occurrences, by the keys of their draws."""
        form = np.fromiter(map(self.known.get, units, repeat(-1)), np.int64, len(units))
        new = np.flatnonzero(form < 0)
        if len(new):
            names = list(map(units.__getitem__, new.tolist()))
            fresh = [u for u in dict.fromkeys(names) if len(u) <= _LONG and (not self.odd or self.odd.isdisjoint(u))]
            if fresh:
                self._meet(fresh)
            form[new] = np.fromiter(map(self.known.get, names, repeat(-1)), np.int64, len(names))
        alone = np.flatnonzero(form < 0)
        if self.n:
            np.add.at(self.met, form[form >= 0], 1)
        if self.rate > 0 and self.n:
            skip, nth = self._gap(at, 0), 0
            on = np.flatnonzero((skip < self.pops[form]) & (form >= 0))
            skip = skip[on]
            while len(on):
                deep = skip >= _DEEP
                if deep.any():
                    alone = np.concatenate([alone, on[deep]])
                    on, skip = on[~deep], skip[~deep]
                key = form[on] << 6 | skip
                to = self.steps.find(key)
                miss = np.flatnonzero(to < 0)
                if len(miss):
                    ask, back = np.unique(key[miss], return_inverse=True)
                    to[miss] = self._step(ask)[back]
                np.add.at(self.met, to, 1)
                form[on] = to
                nth += 1
                skip += 1 + self._gap(at[on], nth)
                more = skip < self.pops[to]
                on, skip = on[more], skip[more]
        if not len(alone):
            return self.ids_all[_stretches(self.ids_at[form], self.ids_n[form])], self.ids_n[form]
        rest = np.ones(len(units), bool)
        rest[alone] = False
        own = [self._alone(units[k], at[k : k + 1]) for k in alone.tolist()]
        start, lens = np.zeros(len(units), np.int64), np.zeros(len(units), np.int64)
        start[rest], lens[rest] = self.ids_at[form[rest]], self.ids_n[form[rest]]
        lens[alone] = size = np.array(list(map(len, own)), np.int64)
        start[alone] = self.n_ids + np.cumsum(size) - size
        return np.concatenate([self.ids_all[: self.n_ids], *own])[_stretches(start, lens)], lens

    def packed_all(self, items: Iterable[tuple[str, int | None]]) -> Iterator[bytes]:
        """Piece ids of every (text, document), four bytes each; texts go together so that their agendas run in step."""
        held: list[str] = []
        sizes: list[int] = []
        starts: list[int] = []
        for text, doc in items:
            units = _UNITS.findall(" " + text) if text else []
            name = f"{self.seed} {doc}".encode()
            held += units
            sizes.append(len(units))
            starts.append(zlib.crc32(name) << 32 | zlib.crc32(name, 1))
            if len(held) > _TOGETHER:
                yield from self._packed(held, sizes, starts)
                held, sizes, starts = [], [], []
        yield from self._packed(held, sizes, starts)

    def _packed(self, units: list[str], sizes: list[int], starts: list[int]) -> Iterator[bytes]:
        """The same for texts of units, by the starts of their keys."""
        if self.n > 4 * self.limit:
            self._forget()
        size = np.array(sizes, np.int64)
        ends = np.cumsum(size)
        place = np.arange(len(units)) - np.repeat(ends - size, size)
        ids, lens = self._together(units, (place.astype(np.uint64) + np.repeat(np.array(starts, np.uint64), size)) * np.uint64(_STEP)) if units else (np.empty(0, np.int32), size[:0])
        out = memoryview(ids.astype("<u4").tobytes())
        cuts = (4 * np.concatenate([[0], np.cumsum(lens)])[ends]).tolist()
        return (bytes(out[a:z]) for a, z in zip([0, *cuts], cuts, strict=False))

    def packed(self, text: str, doc: int | None = 0) -> bytes:
        return next(self.packed_all([(text, doc)]))

    def encode(self, text: str, doc: int | None = 0) -> list[int]:
        out = array("I")
        out.frombytes(self.packed(text, doc))
        return out.tolist()

    def decode(self, ids: list[int] | np.ndarray) -> str:
        ids = np.asarray(ids, np.int64)
        return self.raw_all[_stretches(self.raw_at[ids], self.raw_size[ids])].tobytes().decode("utf-8", "replace")[1:]


@contextlib.contextmanager
def _no_collection() -> Iterator[None]:
    """Python's cycle collector rests meanwhile: the tables of units hold no cycles, and it would walk them again and again."""
    on = gc.isenabled()
    gc.disable()
    try:
        yield
    finally:
        if on:
            gc.enable()


def _pieces(path: str, rate: float, seed: int) -> Pieces:
    return remembered(("pieces", path, rate, seed), lambda: Pieces(path, rate, seed))


def encode_table(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", rate: float = 0.1, seed: int = 2024, model: str | None = None) -> DataFrame:
    """(doc_id, ids): piece ids of every text."""
    path = model or default_model()

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        p = _pieces(path, rate, seed)
        for b in batches:
            with _no_collection():
                ids = [np.frombuffer(x, "<u4").astype(np.int32) for x in p.packed_all(zip(b["t"], b["i"].astype("Int64"), strict=True))]
            yield pd.DataFrame({"doc_id": b["i"].astype("Int64"), "ids": ids})

    src = docs.select(F.col(id_col).cast("long").alias("i"), text_of(text_col).alias("t"))
    return src.mapInPandas(run, "doc_id long, ids array<int>")


def decode_table(encoded: DataFrame, id_col: str = "doc_id", ids_col: str = "ids", model: str | None = None) -> DataFrame:
    """(doc_id, text) of piece ids."""
    path = model or default_model()

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        p = _pieces(path, 0.0, 0)
        for b in batches:
            yield pd.DataFrame({"doc_id": b["i"].astype("Int64"), "text": [p.decode([] if x is None else list(x)) for x in b["x"]]})

    return encoded.select(F.col(id_col).cast("long").alias("i"), F.col(ids_col).alias("x")).mapInPandas(run, "doc_id long, text string")


def digest(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", rate: float = 0.1, seed: int = 2024, model: str | None = None) -> DataFrame:
    """(doc_id, n_ids, ids_crc32, lossless): encoded, and decoded again, without moving the ids."""
    path = model or default_model()

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        p = _pieces(path, rate, seed)
        for b in batches:
            rows = []
            of = b["i"].astype("Int64")
            with _no_collection():
                for i, t, ids in zip(of, b["t"], p.packed_all(zip(b["t"], of, strict=True)), strict=True):
                    rows.append((i, len(ids) // 4, zlib.crc32(ids), p.decode(np.frombuffer(ids, "<u4")) == t))
            yield pd.DataFrame(rows, columns=["doc_id", "n_ids", "ids_crc32", "lossless"]).astype({"doc_id": "Int64"})

    src = docs.select(F.col(id_col).cast("long").alias("i"), text_of(text_col).alias("t"))
    return src.mapInPandas(run, "doc_id long, n_ids long, ids_crc32 long, lossless boolean")


def op8_piece_dropout(spark, sf_dir: str) -> DataFrame:
    return digest(spark.read.parquet(f"{sf_dir}/documents.parquet"))
