"""Small helpers shared by the operators: table reading, checked broadcasts, memory; stored tables are the core's."""

from __future__ import annotations

import contextlib
import ctypes
import gc

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import forget, shared_dir, stored  # noqa: F401

#: Largest number of 8-byte keys that is sent to every executor (16 MB); above it joins shuffle.
BROADCAST_KEYS = 2_000_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tokenizer_path(name: str) -> str:
    """Default place of a public vocabulary file; operators take the path as a parameter."""
    import public_tokenizers

    return public_tokenizers.path(name)


def text_or_empty(column: str | Column) -> Column:
    return F.coalesce(F.col(column) if isinstance(column, str) else column, F.lit(""))


def small(df: DataFrame, rows: int, limit: int = BROADCAST_KEYS) -> DataFrame:
    """Mark for broadcast only if the counted rows are within the limit; else leave a shuffle join."""
    return F.broadcast(df) if rows <= limit else df


def release() -> None:
    """Give memory that a finished task no longer needs back to the system: Python workers live on."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL("libc.so.6").malloc_trim(0)
