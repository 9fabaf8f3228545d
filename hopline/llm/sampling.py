"""Bounded samples by hash: what reaches the driver doesn't grow with the table or its partitions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SLACK = 4


def distinct_draws(rows: DataFrame, draw: str) -> int:
    """About how many different draws there are: copies share one and count once."""
    return rows.agg(F.approx_count_distinct(draw, 0.02)).first()[0]


def thinned(rows: DataFrame, draw: str, size: int, total: int) -> DataFrame:
    """Rows of least ``draw`` (a uniform 64-bit hash): about ``SLACK * size`` of ``total`` different draws, all if there are fewer."""
    if total <= SLACK * size:
        return rows
    return rows.where(F.col(draw) < int(-(2**63) + 2**64 * (SLACK * size / total)))
