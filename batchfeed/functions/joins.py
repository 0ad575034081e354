"""Joins that look at sizes first."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F


def with_small(left: DataFrame, right: DataFrame, on: str | list[str], how: str = "inner", most_rows: int = 100_000) -> DataFrame:
    """Join with `right` broadcast if it has at most most_rows rows, by an ordinary join beyond."""
    few = right.limit(most_rows + 1).count() <= most_rows
    return left.join(F.broadcast(right) if few else right, on, how)
