"""Arrow stages over selected columns."""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

Work = Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]


def input_bytes(df: DataFrame) -> int:
    """Spark's own estimate of the plan's size; only used to choose how finely work is dealt out."""
    size = int(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
    return size if size < 1 << 60 else 1 << 27  # a plan without files has no estimate


def give_back() -> None:
    """Hands memory that allocators hold, but nothing uses, back to the system: workers live on between tasks."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc only
    if trim:
        trim(0)


def tidy(work: Work) -> Work:
    """The same work; its task leaves no unused memory behind."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from work(batches)
        finally:
            give_back()

    return run


def arrow_stage(df: DataFrame, columns: list, work: Work, schema: str) -> DataFrame:
    """mapInArrow over the named columns only, so the scan reads no others."""
    return df.select(*columns).mapInArrow(tidy(work), schema)
