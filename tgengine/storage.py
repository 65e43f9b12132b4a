"""Intermediate tables in the folder that all executors share."""

from __future__ import annotations

import tempfile
import threading
import uuid

from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share; a local one only where the session names none (tests)."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        base = spark.sparkContext._jsc.sc().getCheckpointDir()
        base = base.get() if base.isDefined() else None
    if not base:
        base = "file://" + tempfile.mkdtemp(prefix="tgengine-")
        spark.sparkContext.setCheckpointDir(base)
    return base.rstrip("/")


_mine = threading.local()


def _open() -> list[list[str]]:
    """Of this thread: the paths stored within each `temporary` that it is in."""
    if not hasattr(_mine, "open"):
        _mine.open = []
    return _mine.open


@contextmanager
def temporary(spark: SparkSession) -> Iterator[None]:
    """Tables that this thread stores inside are removed at the end; nothing that reads them may leave."""
    _open().append([])
    try:
        yield
    finally:
        for path in _open().pop():
            remove(spark, path)


def remove(spark: SparkSession, path: str) -> None:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


def fresh(spark: SparkSession, kind: str = "stored") -> str:
    """A new path in the shared folder."""
    return f"{shared_dir(spark)}/{kind}-{uuid.uuid4().hex}"


#: Drops a query's shuffle files once it has ended; a setting of the running session.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


_inside, _before, _lock = 0, None, threading.Lock()


@contextmanager
def shuffles_dropped(spark: SparkSession) -> Iterator[None]:
    """Queries that end inside leave no shuffle files behind, instead of keeping them until the driver collects its garbage. The first thread inside sets it, the last one puts back what was."""
    global _inside, _before
    with _lock:
        if not _inside:
            _before = spark.conf.get(CLEANUP, None)
            spark.conf.set(CLEANUP, "true")
        _inside += 1
    try:
        yield
    finally:
        with _lock:
            _inside -= 1
            if not _inside:
                spark.conf.unset(CLEANUP) if _before is None else spark.conf.set(CLEANUP, _before)


def stored(df: DataFrame) -> DataFrame:
    """`df` written to the shared folder and read again: cuts lineage, survives lost executors. The files of its shuffles go once it is written."""
    spark = df.sparkSession
    path = fresh(spark)
    if _open():
        _open()[-1].append(path)
    with shuffles_dropped(spark):
        df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)
