"""SQL names of the sketch functions."""

from __future__ import annotations

from splitcount.operators.aggregate import register

__all__ = ["register"]
