"""Broadcasting only what is small: a checked size, with an ordinary join beyond it."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

MAX_ROWS = 100_000


def small(df: DataFrame, max_rows: int = MAX_ROWS) -> DataFrame:
    return F.broadcast(df) if df.limit(max_rows + 1).count() <= max_rows else df
