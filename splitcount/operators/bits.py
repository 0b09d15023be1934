"""Arrays of narrow cells in 64-bit words; a cell may cross a word boundary."""

from __future__ import annotations

import numpy as np


def pack(values: np.ndarray, width: int) -> bytes:
    """n cells of ``width`` bits in ceil(n * width / 64) little-endian words, lowest bits first."""
    v = np.asarray(values, np.uint64)
    if not 1 <= width <= 64:
        raise ValueError("width must lie in 1..64")
    if width < 64 and len(v) and int(v.max()) >> width:
        raise ValueError(f"a value needs more than {width} bits")
    bits = (v[:, None] >> np.arange(width, dtype=np.uint64)) & np.uint64(1)
    flat = np.packbits(bits.astype(np.uint8).reshape(-1), bitorder="little")
    return flat.tobytes().ljust(-(-len(v) * width // 64) * 8, b"\0")


def unpack(data: bytes, width: int, n: int) -> np.ndarray:
    """The first n cells."""
    bits = np.unpackbits(np.frombuffer(data, np.uint8), count=n * width, bitorder="little").reshape(n, width)
    return (bits.astype(np.uint64) << np.arange(width, dtype=np.uint64)).sum(axis=1, dtype=np.uint64)


class PackedArray:
    """n cells of ``width`` bits (56 at most) that are read and changed in place.

    Cells that ascend also take searches, insertions and deletions; an insertion shifts the cells after it.
    """

    __slots__ = ("buf", "mask", "n", "width")

    def __init__(self, width: int, n: int = 0, data: bytes | None = None):
        if not 1 <= width <= 56:
            raise ValueError("width must lie in 1..56")
        self.width, self.n, self.mask = width, n, (1 << width) - 1
        size = -(-n * width // 64) * 8 + 8  # one spare word, so that any cell can be read as eight bytes
        self.buf = bytearray((data or b"")[: size - 8]).ljust(size, b"\0")

    def __len__(self) -> int:
        return self.n

    def __getitem__(self, k: int) -> int:
        at = k * self.width
        return int.from_bytes(self.buf[at >> 3 : (at >> 3) + 8], "little") >> (at & 7) & self.mask

    def __setitem__(self, k: int, value: int) -> None:
        at = k * self.width
        byte, off = at >> 3, at & 7
        word = int.from_bytes(self.buf[byte : byte + 8], "little")
        word ^= ((word >> off & self.mask) ^ value) << off
        self.buf[byte : byte + 8] = word.to_bytes(8, "little")

    def insert(self, k: int, value: int) -> None:
        at = k * self.width
        byte, off = at >> 3, at & 7
        rest = int.from_bytes(self.buf[byte:], "little")
        low = rest & (1 << off) - 1
        self.n += 1
        size = -(-self.n * self.width // 64) * 8 + 8
        self.buf[byte:] = (low | value << off | rest >> off << off + self.width).to_bytes(size - byte + 8, "little")[: size - byte]

    def delete(self, k: int) -> None:
        at = k * self.width
        byte, off = at >> 3, at & 7
        rest = int.from_bytes(self.buf[byte:], "little")
        self.n -= 1
        size = -(-self.n * self.width // 64) * 8 + 8
        kept = (rest & (1 << off) - 1) | rest >> off + self.width << off
        self.buf[byte:] = (kept & (1 << 8 * (size - byte)) - 1).to_bytes(size - byte, "little")

    def find(self, value: int) -> int:
        """Place of the first cell that is not below ``value``, among ascending cells."""
        lo, hi = 0, self.n
        while lo < hi:
            mid = (lo + hi) >> 1
            if self[mid] < value:
                lo = mid + 1
            else:
                hi = mid
        return lo

    def values(self, start: int = 0, stop: int | None = None) -> np.ndarray:
        """Cells start..stop as whole numbers."""
        n = (self.n if stop is None else stop) - start
        at = start * self.width
        raw = np.frombuffer(self.buf, np.uint8, (n * self.width + (at & 7) + 7) >> 3, at >> 3)
        flat = np.unpackbits(raw, bitorder="little")[at & 7 : (at & 7) + n * self.width]
        return flat.reshape(n, self.width) @ (np.int64(1) << np.arange(self.width, dtype=np.int64))

    def to_bytes(self) -> bytes:
        return bytes(self.buf[:-8])
