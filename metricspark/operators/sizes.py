"""Broadcasts behind a check of their size."""
from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

MOST_ROWS = 100_000  # rows of queries and the like that are broadcast
MOST_BYTES = 64 << 20


def sized(df: DataFrame, most_rows: int = MOST_ROWS) -> DataFrame:
    """`df`, broadcast if it has at most `most_rows` rows (counted up to there); else Spark chooses the join."""
    return F.broadcast(df) if df.select(F.lit(1)).limit(most_rows + 1).count() <= most_rows else df
