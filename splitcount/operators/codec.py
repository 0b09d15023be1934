"""One sketch in memory: build, look up, update under each variant, rebase, merge, store as bytes.

The Spark side uses this inside Arrow functions on rows that are already aggregated; the item-by-item
:class:`Trace` exists for the counters of a sequential run.
"""

from __future__ import annotations

import struct
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np

from splitcount.operators import bits
from splitcount.schema import HASH_IDS, VARIANT_IDS, check_kappa, registers_of

#: tag, p, kappa, base, hash, variant, smallest register, reserved, seed, sparse entries.
_HEADER = struct.Struct("<8BqI")
_TAG = 0xC5
VALUE_BITS = 6


@dataclass(frozen=True)
class BaseScan:
    base: int
    sparse: int
    visited: int


def best_base_scan(hist: dict[int, int] | np.ndarray, kappa: int) -> BaseScan:
    """Optimal base among existing register values, ascending, with an early stop.

    The registers under a candidate are sparse whatever lies above, so the scan ends once they are at
    least as many as the best candidate's sparse registers.
    """
    h = np.zeros(65, np.int64)
    if isinstance(hist, np.ndarray):
        h[: len(hist)] = hist
    else:
        for r, c in hist.items():
            h[r] = c
    upto = np.concatenate(([0], np.cumsum(h)))
    m, wide = int(upto[-1]), 1 << check_kappa(kappa)
    best, sparse, visited = 0, m + 1, 0
    for b in np.flatnonzero(h).tolist():
        if upto[b] >= sparse:
            break
        visited += 1
        s = m - int(upto[min(b + wide, 65)] - upto[b])
        if s < sparse:
            best, sparse = b, s
    return BaseScan(best, sparse if m else 0, visited)


#: Registers that are looked at together; whole words for every cell width.
BLOCK = 1 << 12


def lazy_base(hist: np.ndarray, kappa: int, base: int) -> int:
    """From ``base`` on to the next register value as long as that makes the sparse part smaller."""
    wide = 1 << kappa
    inside = lambda b: int(hist[b : b + wide].sum())
    for b in np.flatnonzero(hist).tolist():
        if b > base:
            if inside(b) <= inside(base):
                break
            base = b
    return base


def base_for(variant: str, hist: np.ndarray, kappa: int, base: int = 0) -> int:
    """The base that a variant takes for given registers; ``base`` is where the lazy one stands."""
    if variant == "min":
        return int(np.flatnonzero(hist)[0])
    if variant == "lazy":
        return lazy_base(hist, kappa, base)
    return best_base_scan(hist, kappa).base


@dataclass
class Sketch:
    """Split form: packed offsets of the registers in the base's window, and packed entries for the rest.

    ``cells`` holds 0 where the register is sparse; ``entries`` are (index << 6) | value, ascending.  Everything
    below works on this form; registers are spread out one block at a time.
    """

    p: int
    kappa: int
    base: int
    cells: bits.PackedArray
    entries: bits.PackedArray
    hash_id: int = HASH_IDS["md5_64"]
    seed: int = 0
    variant: str = "opt"

    # ---- conversions

    @classmethod
    def _of_blocks(cls, blocks: Iterator[np.ndarray], p: int, kappa: int, base: int, **tags) -> Sketch:
        """Split the blocks of registers, in order, at a given base."""
        check_kappa(kappa)
        cells, out, start = [], [], 0
        for regs in blocks:
            inside = (regs >= base) & (regs < base + (1 << kappa))
            cells.append(bits.pack(np.where(inside, regs - base, 0), kappa))
            at = np.flatnonzero(~inside)
            out.append((at + start << VALUE_BITS) | regs[at])
            start += len(regs)
        sparse = np.concatenate(out)
        width = p + VALUE_BITS
        return cls(p, kappa, base, bits.PackedArray(kappa, start, b"".join(cells)), bits.PackedArray(width, len(sparse), bits.pack(sparse, width)), **tags)

    @classmethod
    def from_registers(cls, regs: np.ndarray, kappa: int = 3, base: int | None = None, **tags) -> Sketch:
        regs = np.asarray(regs, np.int64)
        p = int(len(regs)).bit_length() - 1
        if registers_of(p) != len(regs):
            raise ValueError("the number of registers must be a power of two")
        if base is None:
            base = base_for(tags.get("variant", "opt"), np.bincount(regs, minlength=65), kappa)
        return cls._of_blocks((regs[at : at + BLOCK] for at in range(0, len(regs), BLOCK)), p, kappa, base, **tags)

    @classmethod
    def empty(cls, p: int, kappa: int = 3, **tags) -> Sketch:
        m, width = registers_of(p), p + VALUE_BITS
        return cls(p, check_kappa(kappa), 0, bits.PackedArray(kappa, m), bits.PackedArray(width), **tags)

    @classmethod
    def from_pairs(cls, p: int, j: np.ndarray, r: np.ndarray, kappa: int = 3, base: int | None = None, **tags) -> Sketch:
        s = cls.empty(p, kappa, **tags).offer_many(j, r, reject=False)[0]
        return s if base is None else s.rebase(base)

    def blocks(self) -> Iterator[np.ndarray]:
        """Register values, one block after the other: the cells, and the ordered entries that fall among them."""
        for start in range(0, len(self.cells), BLOCK):
            yield self.block(start)

    def block(self, start: int) -> np.ndarray:
        stop = min(start + BLOCK, len(self.cells))
        regs = self.cells.values(start, stop) + self.base
        if self.entries.n:
            got = self.entries.values(self.entries.find(start << VALUE_BITS), self.entries.find(stop << VALUE_BITS))
            regs[(got >> VALUE_BITS) - start] = got & (1 << VALUE_BITS) - 1
        return regs

    def to_registers(self) -> np.ndarray:
        return np.concatenate(list(self.blocks()))

    def iter_registers(self) -> Iterator[tuple[int, int]]:
        """(j, r) in order of j, without look-ups."""
        j = 0
        for regs in self.blocks():
            for r in regs.tolist():
                yield j, r
                j += 1

    def sparse_part(self) -> tuple[np.ndarray, np.ndarray]:
        """Indexes and values of the sparse registers."""
        e = self.entries.values()
        return e >> VALUE_BITS, e & (1 << VALUE_BITS) - 1

    # ---- reading

    def get(self, j: int) -> int:
        """Sparse value of register j by binary search, else base plus cell."""
        at = self.entries.find(j << VALUE_BITS)
        if at < self.entries.n and (e := self.entries[at]) >> VALUE_BITS == j:
            return e & (1 << VALUE_BITS) - 1
        return self.base + self.cells[j]

    @property
    def sparse(self) -> int:
        return self.entries.n

    @property
    def bits(self) -> int:
        return self.kappa * len(self.cells) + self.sparse * (self.p + VALUE_BITS)

    @property
    def low(self) -> int:
        """Smallest register: items that rank no higher cannot change the sketch."""
        return int(np.flatnonzero(self.counts())[0])

    def counts(self) -> np.ndarray:
        """How many registers hold each value."""
        return sum((np.bincount(x, minlength=65) for x in self.blocks()), np.zeros(65, np.int64))

    def histogram(self) -> dict[int, int]:
        h = self.counts()
        return {r: int(h[r]) for r in np.flatnonzero(h).tolist()}

    def estimate(self, range_bits: int | None = 64) -> float:
        from math import log

        from splitcount.operators.estimate import alpha

        m, h = len(self.cells), self.histogram()
        e = alpha(self.p) * m * m / sum(c * 2.0**-r for r, c in h.items())
        v = h.get(0, 0)
        if e <= 2.5 * m and v:
            return m * log(m / v)
        if range_bits and e > 2.0**range_bits / 30:
            return -(2.0**range_bits) * log(1 - e / 2.0**range_bits)
        return e

    # ---- changing

    def _tags(self) -> dict:
        return {"hash_id": self.hash_id, "seed": self.seed, "variant": self.variant}

    def put(self, j: int, r: int) -> bool:
        """Set one register at the present base; True if it was dense and is sparse now."""
        at = self.entries.find(j << VALUE_BITS)
        there = at < self.entries.n and self.entries[at] >> VALUE_BITS == j
        if self.base <= r < self.base + (1 << self.kappa):
            self.cells[j] = r - self.base
            if there:
                self.entries.delete(at)
            return False
        entry = j << VALUE_BITS | r
        if there:
            self.entries[at] = entry
        else:
            self.cells[j] = 0
            self.entries.insert(at, entry)
        return not there

    def rebase(self, base: int) -> Sketch:
        """Every register routed anew, in one pass."""
        return self if base == self.base else Sketch._of_blocks(self.blocks(), self.p, self.kappa, base, **self._tags())

    def compress(self) -> Sketch:
        return self.rebase(best_base_scan(self.counts(), self.kappa).base)

    def offer_many(self, j: np.ndarray, r: np.ndarray, reject: bool = True) -> tuple[Sketch, int]:
        """The sketch after many updates and how many registers changed; its base follows once, by the variant's rule.

        The lazy rule looks for a base only if a register became sparse that was not.
        """
        j, r = np.asarray(j, np.int64), np.asarray(r, np.int64)
        if reject and len(r):
            high = r > self.low
            j, r = j[high], r[high]
        order = np.argsort(j, kind="stable")
        j, r = j[order], r[order]
        hist, changed, grown = np.zeros(65, np.int64), 0, 0
        wide = 1 << self.kappa

        def after() -> Iterator[np.ndarray]:
            nonlocal changed, grown
            for start in range(0, len(self.cells), BLOCK):
                old = self.block(start)
                new = old.copy()
                a, b = np.searchsorted(j, (start, start + BLOCK))
                np.maximum.at(new, j[a:b] - start, r[a:b])
                up = new > old
                changed += int(up.sum())
                grown += int((up & (old >= self.base) & (old < self.base + wide) & (new >= self.base + wide)).sum())
                hist[:] += np.bincount(new, minlength=65)
                yield new

        now = Sketch._of_blocks(after(), self.p, self.kappa, self.base, **self._tags())
        if not changed:
            return self, 0
        if self.variant == "lazy" and not grown:
            return now, changed
        return now.rebase(base_for(self.variant, hist, self.kappa, self.base)), changed

    def fold(self, p: int) -> Sketch:
        """The sketch with fewer index bits; for indexes whose leading bits nest."""
        if p > self.p:
            raise ValueError("a sketch folds to fewer registers only")
        regs = self.to_registers().reshape(1 << p, -1).max(axis=1)
        return Sketch.from_registers(regs, self.kappa, **self._tags())

    # ---- bytes

    def to_bytes(self) -> bytes:
        head = _HEADER.pack(_TAG, self.p, self.kappa, self.base, self.hash_id, VARIANT_IDS[self.variant], self.low, 0, self.seed, self.sparse)
        return head + self.cells.to_bytes() + self.entries.to_bytes()

    @classmethod
    def from_bytes(cls, data: bytes) -> Sketch:
        tag, p, kappa, base, hash_id, variant, _, _, seed, s = _HEADER.unpack_from(data)
        if tag != _TAG:
            raise ValueError("not a sketch")
        m = registers_of(p)
        at = _HEADER.size
        sparse = at + -(-m * kappa // 64) * 8
        name = next(k for k, v in VARIANT_IDS.items() if v == variant)
        return cls(p, kappa, base, bits.PackedArray(kappa, m, data[at:sparse]), bits.PackedArray(p + VALUE_BITS, s, data[sparse:]), hash_id, seed, name)


def merge(sketches: list[Sketch]) -> Sketch:
    """Merged split form, from the split forms side by side, a block at a time.

    The blocks are split at the largest base, which bounds most registers of the result from below; one
    base search at the end, in full but for the smallest-base variant, which keeps its rule.
    """
    first = sketches[0]
    if any((s.p, s.hash_id, s.seed) != (first.p, first.hash_id, first.seed) for s in sketches):
        raise ValueError("sketches differ in registers, hash or seed")
    hist = np.zeros(65, np.int64)

    def largest() -> Iterator[np.ndarray]:
        for start in range(0, len(first.cells), BLOCK):
            regs = first.block(start)
            for s in sketches[1:]:
                np.maximum(regs, s.block(start), out=regs)
            hist[:] += np.bincount(regs, minlength=65)
            yield regs

    now = Sketch._of_blocks(largest(), first.p, first.kappa, max(s.base for s in sketches), **first._tags())
    return now.rebase(base_for("min" if first.variant == "min" else "opt", hist, first.kappa))


# ------------------------------------------------------------------ sequential updates with counters


@dataclass
class Counters:
    updates: int = 0
    rejected: int = 0
    lookups: int = 0
    changed: int = 0
    compress_calls: int = 0
    rebases: int = 0
    candidates: int = 0


@dataclass
class Trace:
    """Item-by-item updates of one packed sketch under a variant, counting what each costs.

    ``opt`` searches the base after every changed register; ``lazy`` only when a register would become
    sparse that was not, and then tries the next larger register value alone; ``min`` keeps the base at the
    smallest register with a count of the registers that hold it.  Beside the sketch there are 65 counts of
    register values and nothing else.
    """

    p: int
    kappa: int = 3
    variant: str = "opt"
    early_reject: bool = True
    prune: bool = True
    low: int = 0
    state: Sketch = None
    hist: list[int] = field(default_factory=list)
    counters: Counters = field(default_factory=Counters)

    def __post_init__(self):
        if self.variant not in ("opt", "lazy", "min"):
            raise ValueError(f"unknown variant {self.variant}")
        self.state = Sketch.empty(self.p, self.kappa, variant=self.variant)
        self.hist = [registers_of(self.p)] + [0] * 64

    @property
    def base(self) -> int:
        return self.state.base

    @property
    def sparse(self) -> int:
        return self.state.sparse

    @property
    def regs(self) -> list[int]:
        return self.state.to_registers().tolist()

    @property
    def bits(self) -> int:
        return self.state.bits

    def sketch(self) -> Sketch:
        return self.state

    def offer(self, j: int, r: int) -> bool:
        c = self.counters
        c.updates += 1
        if self.early_reject and r <= self.low:
            c.rejected += 1
            return False
        c.lookups += 1
        old = self.state.get(j)
        if r <= old:
            return False
        c.changed += 1
        grows = self.state.put(j, r)
        self.hist[old] -= 1
        self.hist[r] += 1
        if old == self.low and not self.hist[old]:
            self.low = next(k for k in range(old, 65) if self.hist[k])
        if self.variant == "opt":
            self._search()
        elif self.variant == "lazy":
            if grows:
                self._next()
        elif self.low > self.base:
            c.compress_calls += 1
            self._move(self.low)
        return True

    def _sparse_at(self, base: int) -> int:
        return len(self.state.cells) - sum(self.hist[base : base + (1 << self.kappa)])

    def _search(self) -> None:
        self.counters.compress_calls += 1
        if self.prune:
            found = best_base_scan(np.array(self.hist), self.kappa)
            best, visited = found.base, found.visited
        else:
            best, visited = max(range(64), key=lambda b: (-self._sparse_at(b), -b)), 64
        self.counters.candidates += visited
        # Equal sizes keep canonical bytes: the smallest base that exists.
        if best != self.base and self._sparse_at(best) <= self._sparse_at(self.base):
            self._move(best)

    def _next(self) -> None:
        self.counters.compress_calls += 1
        nxt = next((k for k in range(self.base + 1, 65) if self.hist[k]), None)
        if nxt is None:
            return
        self.counters.candidates += 1
        if self._sparse_at(nxt) < self._sparse_at(self.base):
            self._move(nxt)

    def _move(self, base: int) -> None:
        self.counters.rebases += 1
        self.state = self.state.rebase(base)


@dataclass
class CodedTrace:
    """Plain registers kept as a compressed byte array; decoded only for ranks that may change it."""

    p: int
    level: int = 1
    low: int = 0
    decodes: int = 0
    encodes: int = 0

    def __post_init__(self):
        self.data = coded_registers(np.zeros(registers_of(self.p), np.uint8), self.level)

    def offer(self, j: int, r: int) -> bool:
        if r <= self.low:
            return False
        regs = decoded_registers(self.data, self.p)
        self.decodes += 1
        if r <= regs[j]:
            return False
        regs[j] = r
        self.low = int(regs.min())
        self.data = coded_registers(regs, self.level)
        self.encodes += 1
        return True


def coded_registers(regs: np.ndarray, level: int = 1) -> bytes:
    """Byte-aligned registers under Zstandard."""
    import zstandard

    return zstandard.ZstdCompressor(level=level).compress(np.asarray(regs, np.uint8).tobytes())


def decoded_registers(data: bytes, p: int) -> np.ndarray:
    import zstandard

    return np.frombuffer(bytearray(zstandard.ZstdDecompressor().decompress(data, max_output_size=registers_of(p))), np.uint8)
