"""Fixed schemas and limits of the sketch tables."""

from __future__ import annotations

from pyspark.sql import types as T

#: Index bits, cell bits and hash words that the sketches accept.
P_MIN, P_MAX = 4, 18
KAPPA_MIN, KAPPA_MAX = 1, 6
WORD_BITS = 64
MAX_RANK = 63

PAIRS = T.StructType([T.StructField("j", T.LongType()), T.StructField("r", T.LongType())])
HIST = T.StructType([T.StructField("r", T.LongType()), T.StructField("c", T.LongType())])

#: Numbers stored in a blob's header.
HASH_IDS = {"md5_64": 1, "xx64": 2, "mix64": 3, "sha_64": 4, "pairs": 5}
VARIANT_IDS = {"opt": 1, "lazy": 2, "min": 3, "deep": 4}


def registers_of(p: int) -> int:
    """m, the number of registers of a sketch with p index bits."""
    if not P_MIN <= p <= P_MAX:
        raise ValueError(f"p must lie in {P_MIN}..{P_MAX}, got {p}")
    return 1 << p


def check_kappa(kappa: int) -> int:
    if not KAPPA_MIN <= kappa <= KAPPA_MAX:
        raise ValueError(f"kappa must lie in {KAPPA_MIN}..{KAPPA_MAX}, got {kappa}")
    return kappa
