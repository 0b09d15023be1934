"""Session helpers; nothing here changes a setting that is fixed when a session starts."""

from __future__ import annotations

import contextlib
import gc
import os
import re
import tempfile
import uuid
import zipfile
from collections.abc import Iterator
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession


def local_session(cores: int = 8, partitions: int = 8, memory: str = "8g") -> SparkSession:
    """A local session for tests and the bench."""
    spark = (
        SparkSession.builder.master(f"local[{cores}]")
        .appName("splitcount")
        .config("spark.sql.shuffle.partitions", partitions)
        .config("spark.driver.memory", memory)
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.sql.adaptive.enabled", "true")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share.

    A session on one machine may name none and gets a temporary folder; on a cluster, whose executors would not
    see that one, it is an error.
    """
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        master = spark.sparkContext.master
        if not re.fullmatch(r"local(\[[^\]]*\])?", master):
            raise RuntimeError(f"spark.checkpoint.dir must name a folder that all executors of {master} share")
        found = tempfile.mkdtemp(prefix="splitcount-checkpoint-")
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def relieve(spark: SparkSession) -> bool:
    """Collect the driver's garbage once its heap has grown beyond half of what it may take; true if it had.

    What is behind a cut is garbage, but the JVM sees no need to look while there is room to grow: plans, broadcast
    blocks and, on the executors, the files of shuffles that nothing reads again stay until it does.
    """
    heap = spark.sparkContext._jvm.java.lang.Runtime.getRuntime()
    if 2 * heap.totalMemory() <= heap.maxMemory():
        return False
    gc.collect()  # Python's frames hold the JVM's plans
    spark.sparkContext._jvm.System.gc()
    return True


def cut(df: DataFrame) -> DataFrame:
    """Write ``df`` once to the shared folder and go on from the written table."""
    path = f"{shared_dir(df.sparkSession)}/cut-{uuid.uuid4().hex}"
    df.write.parquet(path)
    relieve(df.sparkSession)
    return df.sparkSession.read.schema(df.schema).parquet(path)


_BATCH = "spark.sql.execution.arrow.maxRecordsPerBatch"


@contextlib.contextmanager
def small_batches(spark: SparkSession, rows: int = 1000) -> Iterator[None]:
    """What is written meanwhile sends Python so many rows at a time at most; the session's own number holds again afterwards.

    All rows are sent; a batch of whole texts stands in the executor's and the worker's memory several times over.
    """
    before = spark.conf.get(_BATCH)
    if 0 < int(before) <= rows:
        yield
        return
    spark.conf.set(_BATCH, rows)
    try:
        yield
    finally:
        spark.conf.set(_BATCH, before)


_SHIPPED: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Send this package to the Python workers, once per application, unless their path holds it anyway."""
    root = Path(__file__).resolve().parent.parent
    on_path = [Path(p).resolve() for p in os.environ.get("PYTHONPATH", "").split(os.pathsep) if p]
    if root in on_path or Path.cwd() == root or spark.sparkContext.applicationId in _SHIPPED:
        return
    path = Path(tempfile.mkdtemp(prefix="splitcount-code-")) / "splitcount.zip"
    with zipfile.ZipFile(path, "w", zipfile.ZIP_DEFLATED) as z:
        for f in sorted((root / "splitcount").rglob("*.py")):
            z.write(f, f.relative_to(root))
    spark.sparkContext.addPyFile(str(path))
    _SHIPPED.add(spark.sparkContext.applicationId)
