"""What a Python worker keeps between tasks and gets at once: as little as possible, since an executor runs many of them beside its JVM."""

from __future__ import annotations

import ctypes
import gc
from collections.abc import Callable, Iterator
from contextlib import contextmanager

import pyarrow as pa
from pyspark.sql import SparkSession

_BATCH_ROWS = "spark.sql.execution.arrow.maxRecordsPerBatch"


def trimmed(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """run for mapInArrow, which gives freed memory back to the system when a task ends; idle workers then stay small."""

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pa.set_memory_pool(pa.system_memory_pool())
        try:
            yield from run(batches)
        finally:
            gc.collect()
            try:
                ctypes.CDLL(None).malloc_trim(0)
            except (AttributeError, OSError):
                pass  # another C library: it keeps what it keeps

    return task


@contextmanager
def batches_of(spark: SparkSession, rows: int) -> Iterator[None]:
    """What runs inside sends workers so many rows at once (or fewer, if the session does so): a batch of large rows stands in the JVM, outside its heap, and in the worker."""
    before = spark.conf.get(_BATCH_ROWS, None)
    if before is None or not 0 < int(before) <= rows:
        spark.conf.set(_BATCH_ROWS, str(rows))
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(_BATCH_ROWS)
        else:
            spark.conf.set(_BATCH_ROWS, before)
