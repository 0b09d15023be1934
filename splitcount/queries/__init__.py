"""Registered queries over the given tables, each with its DuckDB counterpart where SQL can say it."""

from splitcount.queries import applications, baseline_queries, blobs, engine, methods, theory_queries, workload_queries  # noqa: F401
from splitcount.queries.registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
