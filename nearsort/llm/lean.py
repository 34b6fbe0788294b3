"""Memory of Python workers: Arrow batches are bounded by bytes, and what a task needed is given back when it ends."""

from __future__ import annotations

import ctypes
import gc
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import SparkSession

from . import textscan

#: Bytes of one Arrow batch sent to a worker; Spark's own bound of 64 MB is held several times over by both sides.
BATCH_BYTES = 4 << 20
_LIMIT = "spark.sql.execution.arrow.maxBytesPerBatch"


def bound_batches(spark: SparkSession) -> None:
    """Lower the session's bound on the bytes of an Arrow batch to BATCH_BYTES; a lower one stays. Results don't depend on it."""
    now = int(spark.conf.get(_LIMIT).rstrip("bB"))
    if not 0 < now <= BATCH_BYTES:
        spark.conf.set(_LIMIT, BATCH_BYTES)


def trim() -> None:
    """Give freed memory back to the system."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # only the GNU C library has it
        pass


def release() -> None:
    textscan.forget()
    gc.collect()
    trim()


def lean(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """``run`` for mapInArrow, taking bounded batches and returning its memory to the system at the end. Called on the driver."""
    bound_batches(SparkSession.active())

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            release()

    return whole
