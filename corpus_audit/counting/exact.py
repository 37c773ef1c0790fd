"""Exact tallies: one hash aggregate with partial combine."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def tally(df: DataFrame, keys: list[str], measures: list[Column] | None = None) -> DataFrame:
    """``keys`` and their measures (default: ``cnt``, the number of rows)."""
    return df.groupBy(*keys).agg(*(measures or [F.count("*").alias("cnt")]))


def top(tallied: DataFrame, k: int, key: str = "gram", count: str = "cnt") -> DataFrame:
    """The k most frequent keys; ties by key, so the answer is unique."""
    return tallied.orderBy(F.desc(count), F.asc(key)).limit(k)


def bottom(tallied: DataFrame, k: int, key: str = "gram", count: str = "cnt") -> DataFrame:
    return tallied.orderBy(F.asc(count), F.asc(key)).limit(k)
