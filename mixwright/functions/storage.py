"""Folders that executors and driver share."""

from __future__ import annotations

import ctypes
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Used only where the session names no folder, as in tests on one machine.
FALLBACK = "file:///tmp/checkpoints/mixwright"
#: Rows of a table that is broadcast.
MAX_ROWS = 2_000_000
_scopes: list[list[str]] = []


def scratch(spark: SparkSession, label: str) -> str:
    """A fresh folder below ``spark.checkpoint.dir``."""
    root = spark.conf.get("spark.checkpoint.dir", None) or FALLBACK
    path = f"{root.rstrip('/')}/{label}-{uuid.uuid4().hex}"
    for made in _scopes:
        made.append(path)
    return path


def removed(spark: SparkSession, *paths: str) -> None:
    """Delete folders, in whatever file system they are."""
    for p in paths:
        path = spark._jvm.org.apache.hadoop.fs.Path(p)
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


@contextmanager
def tidied(spark: SparkSession, keep: list[str]) -> Iterator[None]:
    """Delete, at the end, the folders that were made inside, but for those in ``keep``."""
    made: list[str] = []
    _scopes.append(made)
    try:
        yield
    finally:
        _scopes.remove(made)
        removed(spark, *(p for p in made if p not in keep))


#: Rows of whole texts that go to a worker at once; the JVM holds a batch several times beside its heap.
TEXT_ROWS = 1024
BATCH = "spark.sql.execution.arrow.maxRecordsPerBatch"


@contextmanager
def small_batches(spark: SparkSession, rows: int | None) -> Iterator[None]:
    """Arrow batches of at most ``rows`` rows for what is planned inside."""
    before = spark.conf.get(BATCH)
    if rows and not 0 < int(before) <= rows:
        spark.conf.set(BATCH, str(rows))
    try:
        yield
    finally:
        spark.conf.set(BATCH, before)


def kept(df: DataFrame, label: str, batch_rows: int | None = None) -> DataFrame:
    """Written once and reread, where several later steps would each compute it anew; ``stored_at`` tells where."""
    path = scratch(df.sparkSession, label)
    with small_batches(df.sparkSession, batch_rows):
        df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.stored_at = path
    return out


def checked(table: DataFrame, most: int = MAX_ROWS) -> DataFrame:
    """A stored table with a broadcast hint, if its counted rows are at most ``most``; else as it is, for a join by shuffle."""
    return F.broadcast(table) if table.count() <= most else table


def release_memory() -> None:
    """Give freed memory of a worker process back to the system; workers live on between tasks."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def _settle() -> None:
    """Large blocks of a worker apart from its heap, where each goes back by itself, Arrow's too."""
    pa.set_memory_pool(pa.system_memory_pool())
    try:
        ctypes.CDLL("libc.so.6").mallopt(-3, 16 << 20)  # M_MMAP_THRESHOLD
    except (OSError, AttributeError):
        pass


def lean(run: Callable) -> Callable:
    """A ``mapInArrow`` function that leaves no freed memory in its worker, which lives on between tasks."""

    def tidy(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _settle()
        try:
            yield from run(batches)
        finally:
            release_memory()

    return tidy


def lean_group(run: Callable) -> Callable:
    """The same for a function of one group's table."""

    def tidy(table: pa.Table) -> pa.Table:
        _settle()
        try:
            return run(table)
        finally:
            release_memory()

    return tidy


def lean_cogroup(run: Callable) -> Callable:
    """The same for a function of a key and two groups' tables."""

    def tidy(key: tuple, left: pa.Table, right: pa.Table) -> pa.Table:
        _settle()
        try:
            return run(key, left, right)
        finally:
            release_memory()

    return tidy
