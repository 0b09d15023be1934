"""Helpers shared by the training-data operators.

Conventions for every operator in this subpackage:

* Only the columns an operator names are read; other columns, whatever they are called, never meet
  the operator's own names.
* A null text counts as the empty text; an empty table gives an empty result with the full schema.
* Intermediate results are cut with :func:`cut`, which writes Parquet below the folder named by
  ``spark.checkpoint.dir``; every executor can read it again after another one is lost.
"""

from __future__ import annotations

import contextlib
import ctypes
import gc
from collections.abc import Callable
from typing import TypeVar

import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F

from splitcount.session import cut, shared_dir, small_batches, table

__all__ = ["WORD", "cut", "held_out", "remembered", "shared_dir", "small_batches", "table", "text_of"]

T = TypeVar("T")
_REMEMBERED: dict = {}


def remembered(key: tuple, make: Callable[[], T]) -> T:
    """What a worker keeps from task to task: one operator's vocabulary and word memory at a time.

    Workers outlive stages; the next operator's tables take the place of the last one's instead of adding to them, and
    what the stages before have freed goes back to the system first.
    """
    if key not in _REMEMBERED:
        _REMEMBERED.clear()
        gc.collect()
        pa.default_memory_pool().release_unused()
        with contextlib.suppress(OSError, AttributeError):  # only some C libraries keep it and can let it go
            ctypes.CDLL(None).malloc_trim(0)
        _REMEMBERED[key] = make()
    return _REMEMBERED[key]


#: Fixed value: a word is a longest stretch without 0x20 and 0x09-0x0D.
WORD = r"[^\x20\x09-\x0D]+"


def held_out(doc_id: Column | str) -> Column:
    """True for the fold that no model may learn from: crc32 of the id's text, modulo 4, is 2."""
    c = F.col(doc_id) if isinstance(doc_id, str) else doc_id
    return F.coalesce(F.crc32(c.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def text_of(column: str = "text") -> Column:
    return F.coalesce(F.col(column), F.lit(""))
