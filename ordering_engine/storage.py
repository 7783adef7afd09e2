"""Shared storage for intermediate tables, and their removal."""

from __future__ import annotations

import atexit
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from contextvars import ContextVar

from pyspark import SparkContext
from pyspark.sql import DataFrame, SparkSession

#: Used only by sessions on one machine that name no shared folder (tests).
LOCAL_DEFAULT = "/tmp/checkpoints/ordering_engine"

#: Most rows and bytes of a batch that a Python worker gets while a table is staged: a worker holds a batch, its copies and its results.
BATCH_ROWS, BATCH_BYTES = 2_000, 4 << 20
ARROW = "spark.sql.execution.arrow."

_left: set[str] = set()
_inside: ContextVar[list[str] | None] = ContextVar("folders staged by the step that runs", default=None)


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; its place comes from the session. A cluster without one is an error."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if folder:
        return folder
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return LOCAL_DEFAULT


def folder(spark: SparkSession, label: str) -> str:
    """A new folder's path in shared storage; what is there when the process ends is removed."""
    path = f"{shared_dir(spark).rstrip('/')}/{label}-{uuid.uuid4().hex}"
    _left.add(path)
    return path


@contextmanager
def small_batches(spark: SparkSession) -> Iterator[None]:
    """Python workers get small batches from plans that run inside; the session's own bounds hold where they are lower, and again afterwards."""
    rows, size = spark.conf.get(f"{ARROW}maxRecordsPerBatch"), spark.conf.get(f"{ARROW}maxBytesPerBatch")
    most = spark._jsparkSession.sessionState().conf().arrowMaxBytesPerBatch()
    spark.conf.set(f"{ARROW}maxRecordsPerBatch", str(min(int(rows), BATCH_ROWS) if int(rows) > 0 else BATCH_ROWS))
    spark.conf.set(f"{ARROW}maxBytesPerBatch", str(min(most, BATCH_BYTES) if most > 0 else BATCH_BYTES))
    try:
        yield
    finally:
        spark.conf.set(f"{ARROW}maxRecordsPerBatch", rows)
        spark.conf.set(f"{ARROW}maxBytesPerBatch", size)


def staged(df: DataFrame, label: str = "stage") -> DataFrame:
    """``df`` written to the shared folder and read back. Lineage ends there, so a lost executor costs a reread.

    The folder is removed by the ``settled`` step around it, or when the driver's process ends.
    """
    spark = df.sparkSession
    path = folder(spark, f"tables/{label}")
    if (inside := _inside.get()) is not None:
        inside.append(path)
    with small_batches(spark):
        df.write.parquet(path)
    back = spark.read.schema(df.schema).parquet(path)
    back.staged_at = path
    return back


def settled(spark: SparkSession, make: Callable[[], DataFrame], label: str) -> DataFrame:
    """The result of ``make``, staged; every other folder that was staged meanwhile is removed."""
    mine: list[str] = []
    token = _inside.set(mine)
    try:
        out = staged(make(), label)
    finally:
        _inside.reset(token)
    for path in mine[:-1]:
        remove(path)
    if (outer := _inside.get()) is not None:
        outer.append(mine[-1])
    return out


@contextmanager
def passing(spark: SparkSession) -> Iterator[None]:
    """Every folder that is staged inside is removed at the end, and shuffle files with it: Spark drops those of plans that are collected."""
    mine: list[str] = []
    token = _inside.set(mine)
    try:
        yield
    finally:
        _inside.reset(token)
        for path in mine:
            remove(path)
        spark._jvm.System.gc()


def remove(path: str) -> None:
    jvm, context = SparkContext._gateway.jvm, SparkContext._active_spark_context
    where = jvm.org.apache.hadoop.fs.Path(path)
    config = context._jsc.hadoopConfiguration() if context else jvm.org.apache.hadoop.conf.Configuration()
    where.getFileSystem(config).delete(where, True)
    _left.discard(path)


@atexit.register
def _remove_what_is_left() -> None:
    for path in list(_left):
        try:
            remove(path)
        except Exception:  # the JVM may be gone before this process: then the folders stay
            return
