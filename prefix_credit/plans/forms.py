"""Physical choices made from cheap checks of size."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def bounded_broadcast(df: DataFrame, rows: int = 200_000) -> DataFrame:
    """The table with a broadcast hint if it has at most `rows` rows, else as it is, for a shuffled join."""
    return F.broadcast(df) if df.limit(rows + 1).count() <= rows else df
