"""The deep variant: a narrower window and an Elias-Fano coded sparse part; for size reports."""

from __future__ import annotations

from dataclasses import dataclass
from math import ceil, log2

import numpy as np

from splitcount.functions.theory import bits_deep
from splitcount.operators import bits
from splitcount.operators.codec import Sketch


@dataclass(frozen=True)
class EliasFano:
    """Ascending numbers below ``universe``: low bits packed, high bits in unary."""

    n: int
    universe: int
    low_bits: int
    low: bytes
    high: bytes

    @classmethod
    def of(cls, values: np.ndarray, universe: int) -> EliasFano:
        v = np.asarray(values, np.int64)
        n = len(v)
        low_bits = max(0, int(log2(universe / n))) if n else 0
        low = bits.pack(v & (1 << low_bits) - 1, low_bits) if low_bits and n else b""
        high = np.zeros((universe >> low_bits) + n + 1, np.uint8)
        high[(v >> low_bits) + np.arange(n)] = 1
        return cls(n, universe, low_bits, low, np.packbits(high, bitorder="little").tobytes())

    def values(self) -> np.ndarray:
        ones = np.flatnonzero(np.unpackbits(np.frombuffer(self.high, np.uint8), bitorder="little"))[: self.n]
        high = ones - np.arange(self.n)
        low = bits.unpack(self.low, self.low_bits, self.n).astype(np.int64) if self.low_bits and self.n else 0
        return (high << self.low_bits) | low

    @property
    def bits(self) -> int:
        """The usual account: s (2 + ceil(log2(U / s)))."""
        return self.n * (2 + ceil(log2(self.universe / self.n))) if self.n else 0


def deep_size(sketch: Sketch) -> dict:
    """Cells of the deep width, the coded sparse part, and their bits, for a sketch's registers."""
    width = min(6, max(1, bits_deep(sketch.p)["bits"]))
    narrow = Sketch.from_registers(sketch.to_registers(), width)
    coded = EliasFano.of(narrow.entries.values(), len(narrow.cells) << 6)
    return {"kappa": width, "base": narrow.base, "sparse": narrow.sparse, "bits": width * len(narrow.cells) + coded.bits, "plain_sparse_bits": narrow.bits}
