"""Size accounting of every sketch form, as columns and as plain numbers."""

from __future__ import annotations

from math import ceil, log2

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from splitcount.schema import registers_of

#: Fixed value: bits of a plain register.
REGISTER_BITS = 6
HEADER_BYTES = 20


def split_bits(p: int, sparse: int, kappa: int = 3, w: int = 64) -> int:
    return kappa * registers_of(p) + sparse * (p + int(log2(w)))


def logical_bits(variant: str, p: int, sparse: int = 0, kappa: int = 3, coded_bytes: int = 0, serialised_bytes: int = 0, w: int = 64) -> int:
    """Bits as the comparison counts them: plain 6m, split km + s(p + log2 w), 8 x coded bytes, 8m, 8 x serialised bytes."""
    if variant == "reg6":
        return REGISTER_BITS * registers_of(p)
    if variant in ("opt", "lazy", "min", "deep"):
        return split_bits(p, sparse, kappa, w)
    if variant == "reg_zstd":
        return 8 * coded_bytes
    if variant in ("reg8", "improved"):
        return 8 * registers_of(p)
    if variant == "library":
        return 8 * serialised_bytes
    raise ValueError(f"unknown variant {variant}")


def word_bits(p: int, sparse: int, kappa: int = 3) -> int:
    """Memory in whole 64-bit words: dense cells and sparse entries each packed by themselves."""
    return 64 * (ceil(kappa * registers_of(p) / 64) + ceil(sparse * (p + 6) / 64))


def blob_bytes(p: int, sparse: int, kappa: int = 3) -> int:
    return HEADER_BYTES + word_bits(p, sparse, kappa) // 8


def bits_per_register(bits: Column, p: int) -> Column:
    return bits / F.lit(float(registers_of(p)))


def reduction(bits: Column, p: int) -> Column:
    """Share of the plain sketch's bits that is saved."""
    return 1 - bits / F.lit(float(REGISTER_BITS * registers_of(p)))


def entropy_bits(hist: DataFrame, keys: list[str], p: int) -> DataFrame:
    """(keys.., bits): m times the empirical entropy of the register values."""
    share = F.col("c") / F.lit(float(registers_of(p)))
    return hist.groupBy(*keys).agg(F.sum(-F.col("c") * F.log2(share)).alias("bits"))
