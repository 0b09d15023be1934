"""Physical choices and plan checks."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from splitcount.schema import registers_of

#: Bytes of one long-form register row in a shuffle, and of one register in a blob.
ROW_BYTES, CELL_BYTES = 24, 0.47


def shuffle_bytes(p: int, tasks: int, groups: int, rows_per_task: int) -> dict[str, float]:
    """What either form sends: rows of touched registers, or whole blobs."""
    m = registers_of(p)
    touched = min(m, max(1, rows_per_task // max(groups, 1)))
    return {"relational": tasks * groups * touched * ROW_BYTES, "partial": tasks * groups * m * CELL_BYTES}


def choose_form(p: int, tasks: int, groups: int, rows_per_task: int) -> str:
    """``relational`` unless blobs clearly send less."""
    sent = shuffle_bytes(p, tasks, groups, rows_per_task)
    return "partial" if sent["partial"] * 4 < sent["relational"] else "relational"


def input_figures(df: DataFrame, keys: list[str], groups: int | None = None) -> tuple[int, int, int]:
    """(tasks, groups, rows per task) of a scan of ``df``, from the optimiser's size of its plan.

    Only where there are keys and ``groups`` is not given does a job run: it reads the keys and counts them roughly.
    """
    spark = df.sparkSession
    stats = df._jdf.queryExecution().optimizedPlan().stats()
    size = int(str(stats.sizeInBytes()))
    width = sum(f.dataType.typeName() in ("string", "binary") and 20 or 8 for f in df.schema.fields) + 8
    rows = int(str(stats.rowCount().get())) if stats.rowCount().isDefined() else size // width
    split = spark._jsparkSession.sessionState().conf().filesMaxPartitionBytes()
    tasks = max(1, -(-size // split))
    if not keys:
        groups = 1
    elif groups is None:
        groups = max(1, df.select(F.approx_count_distinct(F.struct(*keys), 0.1)).first()[0])
    return tasks, groups, rows // tasks


def executed_plan(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def plan_stats(df: DataFrame) -> dict[str, int]:
    """Counts of plan nodes that cost: exchanges, joins, Python stages, pushed filters."""
    text = df._jdf.queryExecution().toString()
    physical = text.split("== Physical Plan ==")[-1]
    words = ("Exchange", "BroadcastExchange", "SortMergeJoin", "BroadcastHashJoin", "HashAggregate", "ObjectHashAggregate", "SortAggregate", "Window", "ArrowEvalPython", "MapInPandas", "BatchEvalPython", "CartesianProduct", "BroadcastNestedLoopJoin")
    return {w: sum(line.lstrip(" :+-").split(" ")[0].split("(")[0].lstrip("*") == w or f"- {w}" in line for line in physical.splitlines()) for w in words} | {"columns_read": physical.count("ReadSchema")}
