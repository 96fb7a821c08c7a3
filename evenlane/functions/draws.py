"""Reproducible draws from md5, the same in Spark and in other SQL engines."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def text(seed: int, *parts: Column | str) -> Column:
    """seed|part|part... as text."""
    return F.concat_ws("|", F.lit(str(seed)), *[(F.col(p) if isinstance(p, str) else p).cast("string") for p in parts])


def draw31(x: Column) -> Column:
    """31 random bits of a text."""
    return F.conv(F.substring(F.md5(x), 1, 8), 16, 10).cast("long") % 2147483648


def sql_draw31(x: str) -> str:
    """The same in DuckDB."""
    return f"(('0x' || substr(md5({x}), 1, 8))::BIGINT % 2147483648)"
