"""Ranks and running sums inside groups of any size, in two levels.

A window over a group that holds a third of all rows is one task. Here a group is cut into
cells by the leading hex digits of a hash that also is the order; cells are summed with partial
aggregation, the small table of cell sums gets the windows over whole groups, and each row adds
its place inside its own cell.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Rows that one cell may hold on average; decides the number of hex digits.
CELL_ROWS = 20_000


def order_digits(rows: int, cell_rows: int = CELL_ROWS) -> int:
    """Hex digits of the order hash that make a cell."""
    return max(2, math.ceil(math.log(max(rows, 1) / cell_rows, 16))) if rows > cell_rows else 2


def place_in_group(df: DataFrame, keys: list[str], order: str, ties: list[str], digits: int, value: Column | None = None, rank: str = "rank0", before: str | None = None) -> DataFrame:
    """Add ``rank`` (rows of the group that come before this one) and, with ``value``, ``before``
    (their summed value). ``order`` names a column of lower-case hex text, ties go by ``ties``.
    Null keys form a group of their own; ``value`` must be a non-null long.
    """
    cell = "_cell"
    own = df.withColumn(cell, F.substring(order, 1, digits))
    amount = value if value is not None else F.lit(0).cast("long")
    own = own.withColumn("_amount", amount)
    cells = own.groupBy(*keys, cell).agg(F.count(F.lit(1)).alias("_rows"), F.sum("_amount").alias("_sum"))
    ahead = Window.partitionBy(*keys).orderBy(cell).rowsBetween(Window.unboundedPreceding, -1)
    starts = cells.select(*(F.col(k).alias(f"_k{i}") for i, k in enumerate(keys)), F.col(cell).alias("_kcell"), F.coalesce(F.sum("_rows").over(ahead), F.lit(0)).alias("_rows0"), F.coalesce(F.sum("_sum").over(ahead), F.lit(0)).alias("_sum0"))
    match = F.col(cell) == F.col("_kcell")
    for i, k in enumerate(keys):
        match = match & F.col(k).eqNullSafe(F.col(f"_k{i}"))
    inside = Window.partitionBy(*keys, cell).orderBy(order, *ties)
    placed = own.join(starts, match, "left").withColumn(rank, F.col("_rows0") + F.row_number().over(inside) - 1)
    if before:
        placed = placed.withColumn(before, F.col("_sum0") + F.coalesce(F.sum("_amount").over(inside.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    return placed.drop(cell, "_amount", "_kcell", "_rows0", "_sum0", *(f"_k{i}" for i in range(len(keys))))
