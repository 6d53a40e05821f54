"""Broadcasts behind a check of their size."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Rows up to which a narrow table may be sent to every executor.
BROADCAST_ROWS = 100_000


def at_most(df: DataFrame, rows: int) -> bool:
    """Whether ``df`` has ``rows`` rows or fewer; stops counting there."""
    return df.limit(rows + 1).count() <= rows


def small_side(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """``df`` with a broadcast hint if it is small, else as it is, so that the join shuffles."""
    return F.broadcast(df) if at_most(df, rows) else df
