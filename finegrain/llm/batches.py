"""Arrow batches of bounded size."""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

#: Most bytes of a batch that goes to Python. Only lowered where the session allows more: a batch of texts then costs both sides a
#: few megabytes, whatever the texts' length.
MOST_BYTES = 4 << 20
_SETTING = "spark.sql.execution.arrow.maxBytesPerBatch"


def release() -> None:
    """Give freed memory back to the system, where the C library can: Python workers live on from stage to stage, and what one operator has
    freed would count beside what the next one takes."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):
        pass


def releasing(function: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """``function``, with :func:`release` at the end of every partition."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from function(batches)
        finally:
            release()

    return run


def in_batches(df: DataFrame, function, schema) -> DataFrame:
    """``df.mapInArrow(function, schema)`` with batches of ``MOST_BYTES`` at most; its workers give back what they have freed."""
    now = df.sparkSession.conf.get(_SETTING).rstrip("b")
    size = int(now) if now.lstrip("-").isdigit() else -1
    if not 0 < size <= MOST_BYTES:
        df.sparkSession.conf.set(_SETTING, str(MOST_BYTES))
    return df.mapInArrow(releasing(function), schema)
