"""Sides of joins: broadcast behind a size check, since a broadcast table is held whole by the driver and every executor."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Rows of a few numbers or short strings that may be broadcast (about 100 bytes each as a hash table).
MOST_ROWS = 1_000_000


def small(df: DataFrame, most: int | None = None) -> bool:
    return df.count() <= (MOST_ROWS if most is None else most)


def hinted(df: DataFrame, hint: str) -> DataFrame:
    """df with a join hint; a table too large to broadcast is left to a join by shuffle."""
    return if_small(df) if hint == "broadcast" else df.hint(hint)


def if_small(df: DataFrame) -> DataFrame:
    """df, broadcast if its size allows."""
    return F.broadcast(df) if small(df) else df
