"""In-memory forms to compare with, updated item by item, stored as bytes and merged: registers of six or
eight bits, four-bit offsets with exceptions, and a bit matrix whose columns are coded."""

from __future__ import annotations

import struct
from dataclasses import dataclass

import numpy as np

from splitcount.operators.bits import PackedArray, pack
from splitcount.schema import registers_of

#: tag, p, cell width, reserved, smallest register's count, seed.
_HEADER = struct.Struct("<4BIq")
HEADER_BITS = 8 * _HEADER.size
_VALUE_BITS = 6
#: Four-bit offset that stands for an entry among the exceptions.
_ABOVE = 15


class PlainRegisters:
    """Every register in a cell of ``width`` bits; ``header`` puts the library's fields before them."""

    def __init__(self, p: int, width: int = 6, header: bool = False):
        self.p, self.header, self.cells = p, header, PackedArray(width, registers_of(p))

    def offer(self, j: int, r: int) -> bool:
        if r <= self.cells[j]:
            return False
        self.cells[j] = r
        return True

    def registers(self) -> np.ndarray:
        return self.cells.values()

    @property
    def bits(self) -> int:
        return self.cells.width * len(self.cells) + (HEADER_BITS if self.header else 0)

    def to_bytes(self) -> bytes:
        regs = self.registers()
        head = _HEADER.pack(0xA6, self.p, self.cells.width, 0, int((regs == regs.min()).sum()), 0) if self.header else b""
        return head + self.cells.to_bytes()

    @classmethod
    def from_bytes(cls, data: bytes, p: int, width: int = 6, header: bool = False) -> PlainRegisters:
        out = cls(p, width, header)
        out.cells = PackedArray(width, registers_of(p), data[_HEADER.size if header else 0 :])
        return out

    @classmethod
    def of(cls, regs: np.ndarray, width: int = 6, header: bool = False) -> PlainRegisters:
        p = len(regs).bit_length() - 1
        out = cls(p, width, header)
        out.cells = PackedArray(width, len(regs), pack(regs, width))
        return out

    def merge(self, other: PlainRegisters) -> PlainRegisters:
        return PlainRegisters.of(np.maximum(self.registers(), other.registers()), self.cells.width, self.header)


class FourBitOffsets:
    """Offsets of four bits from the smallest register; the top code points into a sorted list of exceptions."""

    def __init__(self, p: int):
        m = registers_of(p)
        self.p, self.base, self.at_base = p, 0, m
        self.cells, self.above = PackedArray(4, m), PackedArray(p + _VALUE_BITS)

    def get(self, j: int) -> int:
        off = self.cells[j]
        return self.base + off if off < _ABOVE else self.above[self.above.find(j << _VALUE_BITS)] & (1 << _VALUE_BITS) - 1

    def offer(self, j: int, r: int) -> bool:
        if r <= self.base:
            return False
        old = self.get(j)
        if r <= old:
            return False
        if r - self.base < _ABOVE:
            self.cells[j] = r - self.base
        else:
            at = self.above.find(j << _VALUE_BITS)
            if self.cells[j] == _ABOVE:
                self.above[at] = j << _VALUE_BITS | r
            else:
                self.cells[j] = _ABOVE
                self.above.insert(at, j << _VALUE_BITS | r)
        if old == self.base:
            self.at_base -= 1
            if not self.at_base:
                self._fill(self.registers())
        return True

    def _fill(self, regs: np.ndarray) -> None:
        self.base = int(regs.min())
        self.at_base = int((regs == self.base).sum())
        off = np.minimum(regs - self.base, _ABOVE)
        at = np.flatnonzero(off == _ABOVE)
        self.cells = PackedArray(4, len(regs), pack(off, 4))
        width = self.p + _VALUE_BITS
        self.above = PackedArray(width, len(at), pack(at << _VALUE_BITS | regs[at], width))

    @classmethod
    def of(cls, regs: np.ndarray) -> FourBitOffsets:
        out = cls(len(regs).bit_length() - 1)
        out._fill(np.asarray(regs, np.int64))
        return out

    def registers(self) -> np.ndarray:
        regs = self.cells.values() + self.base
        e = self.above.values()
        regs[e >> _VALUE_BITS] = e & (1 << _VALUE_BITS) - 1
        return regs

    @property
    def bits(self) -> int:
        return 4 * len(self.cells) + self.above.n * self.above.width

    def to_bytes(self) -> bytes:
        return _HEADER.pack(0xA4, self.p, self.base, 0, self.above.n, 0) + self.cells.to_bytes() + self.above.to_bytes()

    @classmethod
    def from_bytes(cls, data: bytes) -> FourBitOffsets:
        _, p, base, _, n, _ = _HEADER.unpack_from(data)
        out = cls(p)
        at = _HEADER.size + -(-4 * registers_of(p) // 64) * 8
        out.cells, out.above = PackedArray(4, registers_of(p), data[_HEADER.size : at]), PackedArray(p + _VALUE_BITS, n, data[at:])
        out.base = base
        out.at_base = int((out.registers() == base).sum())
        return out

    def merge(self, other: FourBitOffsets) -> FourBitOffsets:
        return FourBitOffsets.of(np.maximum(self.registers(), other.registers()))


# ------------------------------------------------------------------ bit matrix with coded columns


def rice_shift(m: int, count: int) -> int:
    """Low bits of a gap that are written as they are, for ``count`` marks among m places."""
    return max(0, ((m - count) // count).bit_length() - 1) if count else 0


@dataclass
class BitMatrix:
    """Which ranks every substream has seen: bit r - 1 of its word.

    Stored column by column up to the last one with a one: two flags, the number of marks in p + 1 bits, and the
    places of the rarer bit value as Rice-coded gaps, or the column as it is where that is shorter.
    """

    p: int
    rows: np.ndarray = None

    def __post_init__(self):
        if self.rows is None:
            self.rows = np.zeros(registers_of(self.p), np.uint64)

    def offer(self, j: int, r: int) -> bool:
        bit = np.uint64(1 << r - 1)
        if self.rows[j] & bit:
            return False
        self.rows[j] |= bit
        return True

    @property
    def ones(self) -> int:
        return int(np.bitwise_count(self.rows).sum())

    def estimate(self) -> float:
        from splitcount.operators.baselines import ones_to_count

        return ones_to_count(float(self.ones), len(self.rows)) if self.ones else 0.0

    def _columns(self):
        last = int(np.bitwise_or.reduce(self.rows)).bit_length()
        for k in range(last):
            yield (self.rows >> np.uint64(k) & np.uint64(1)).astype(np.uint8)

    def coded_bits(self) -> np.ndarray:
        """The coded form, one bit per entry."""
        m, out = len(self.rows), []
        number = lambda x, n: (x >> np.arange(n)[::-1] & 1).astype(np.uint8)
        for col in self._columns():
            ones = int(col.sum())
            inverted = 2 * ones > m
            at = np.flatnonzero(col != inverted)
            k = rice_shift(m, len(at))
            gaps = np.diff(at, prepend=-1) - 1
            size = int((gaps >> k).sum()) + len(at) * (1 + k)
            raw = size >= m
            out.append(np.array([raw, inverted], np.uint8))
            out.append(number(len(at), self.p + 1))
            if raw:
                out.append(col)
                continue
            code = np.zeros(size, np.uint8)
            stop = np.cumsum((gaps >> k) + 1 + k) - k - 1  # where the unary part ends
            code[stop] = 1
            for b in range(k):
                code[stop + 1 + b] = gaps >> (k - 1 - b) & 1
            out.append(code)
        return np.concatenate([number(sum(1 for _ in self._columns()), 7), *out])

    @property
    def bits(self) -> int:
        return len(self.coded_bits())

    def to_bytes(self) -> bytes:
        return bytes([self.p]) + np.packbits(self.coded_bits()).tobytes()

    @classmethod
    def from_bytes(cls, data: bytes) -> BitMatrix:
        p, m = data[0], registers_of(data[0])
        code = np.unpackbits(np.frombuffer(data, np.uint8, offset=1)).tobytes()
        at = 0

        def number(n: int) -> int:
            nonlocal at
            at += n
            return int.from_bytes(np.packbits(np.frombuffer(code[at - n : at], np.uint8)).tobytes(), "big") >> -n % 8 if n else 0

        rows = np.zeros(m, np.uint64)
        for k in range(number(7)):
            raw, inverted, marks = number(1), number(1), number(p + 1)
            if raw:
                col = np.frombuffer(code[at : at + m], np.uint8)
                at += m
            else:
                shift, place = rice_shift(m, marks), -1
                col = np.full(m, inverted, np.uint8)
                for _ in range(marks):
                    stop = code.index(1, at)
                    high, at = stop - at, stop + 1
                    place += 1 + (high << shift | number(shift))
                    col[place] = 1 - inverted
            rows |= col.astype(np.uint64) << np.uint64(k)
        return cls(p, rows)

    def merge(self, other: BitMatrix) -> BitMatrix:
        return BitMatrix(self.p, self.rows | other.rows)
