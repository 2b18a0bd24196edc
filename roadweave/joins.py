"""Joins whose small side is broadcast only after its rows are counted."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

#: Rows of narrow keys that a broadcast may hold; beyond it the join shuffles.
BROADCAST_ROWS = 200_000


def small(df: DataFrame, limit: int = BROADCAST_ROWS) -> bool:
    """Whether ``df`` has at most ``limit`` rows; reads no further than that."""
    return df.limit(limit + 1).count() <= limit


def key_join(left: DataFrame, keys: DataFrame, on: list[str] | Column, how: str, limit: int = BROADCAST_ROWS) -> DataFrame:
    """Join with a materialised table of narrow keys, broadcast if it is small, else by shuffle."""
    return left.join(F.broadcast(keys) if small(keys, limit) else keys, on, how)
