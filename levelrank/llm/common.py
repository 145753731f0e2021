"""Shared plumbing of the text operators."""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


_TRIM = getattr(ctypes.CDLL(None), "malloc_trim", None)


def release() -> None:
    """Give memory that Arrow and the C library hold for later back to the system: worker processes outlive their
    tasks, and what they keep counts against the executor."""
    pa.default_memory_pool().release_unused()
    if _TRIM:
        _TRIM(0)


#: Bytes of a batch that a task turns into Python objects at a time.
SLICE_BYTES = 4_000_000


def sliced(batches: Iterator[pa.RecordBatch], size: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """The same rows in batches of about ``size`` bytes, so a task's memory does not follow Arrow's row count."""
    for b in batches:
        step = max(1, b.num_rows * size // max(size, b.nbytes))
        for k in range(0, b.num_rows, step):
            yield b.slice(k, step)


def mapped(df: DataFrame, make: Callable[[Iterator[pa.RecordBatch]], Iterable], schema, size: int = SLICE_BYTES) -> DataFrame:
    """``mapInArrow`` over small batches; a task that ends gives its memory back."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from make(sliced(batches, size))
        release()

    return df.mapInArrow(run, schema)


def arrow_rows(df: DataFrame, columns: list[str], make: Callable[[Iterator[pa.RecordBatch]], Iterable], schema: str, size: int = SLICE_BYTES) -> DataFrame:
    """``mapped`` over the named columns only, so the scan reads nothing else."""
    return mapped(df.select(*columns), make, schema, size)


def texts(batch: pa.RecordBatch, name: str = "text") -> list[str]:
    """A batch's texts, null as the empty text."""
    return [t or "" for t in batch.column(name).to_pylist()]
