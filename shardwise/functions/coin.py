"""Deterministic coins: the same on a retried task, on any number of partitions and in other SQL engines."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

FULL = 1 << 32


def _column(x) -> Column:
    return x if isinstance(x, Column) else F.col(x) if isinstance(x, str) else F.lit(x)


def coin(*parts, mode: str = "portable") -> Column:
    """Integer in [0, 2^32) from the parts' text joined by '#'.

    portable: from an md5 digest, equal in any engine that has md5. fast: the engine's own 64-bit hash.
    """
    if mode == "fast":
        return F.shiftrightunsigned(F.xxhash64(*map(_column, parts)), 32)
    text = F.concat_ws("#", *[_column(p).cast("string") for p in parts])
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("long")


def coin_sql(*parts: str) -> str:
    """The same for DuckDB; parts are SQL expressions."""
    text = ", '#', ".join(parts)
    return f"CAST(concat('0x', substr(md5(concat({text})), 1, 8)) AS BIGINT)"
