"""Shared plumbing of the training-data operators."""

from __future__ import annotations

import ctypes
from contextlib import contextmanager

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from pinflow.lineage import cut, discard, release, scratch_path
from pinflow.sources.tables import read_table

__all__ = ["cut", "discard", "numbered", "read_table", "release", "require_columns", "scratch_path", "shuffle_width", "small_batches", "trimmed"]


def trimmed(run):
    """An Arrow generator function that gives freed memory back when its task ends: workers outlive tasks."""

    def wrapper(batches):
        try:
            yield from run(batches)
        finally:
            pa.default_memory_pool().release_unused()
            try:
                ctypes.CDLL(None).malloc_trim(0)
            except (AttributeError, OSError):  # another C library
                pass

    return wrapper


@contextmanager
def small_batches(spark: SparkSession, rows: int = 500):
    """Arrow batches of few rows for the plans that run inside: their buffers count twice, in the JVM and in Python."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, str(rows))
    try:
        yield
    finally:
        spark.conf.set(name, before)


def numbered(df: DataFrame) -> DataFrame:
    """df with columns c0, c1, ...: Arrow functions can't take every name that a column may have."""
    return df.toDF(*[f"c{i}" for i in range(len(df.columns))])


def shuffle_width(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


def require_columns(df: DataFrame, *names: str) -> None:
    missing = [n for n in names if n not in df.columns]
    if missing:
        raise ValueError(f"missing columns: {missing}")
