"""Validation in tiers of rising cost."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

MIN_SIDE, MAX_ASPECT = 64, 4.0


def decodable(payload: Column) -> Column:
    """Not empty and without control bytes up front."""
    return payload.isNotNull() & (F.char_length(payload) > 0) & ~F.substring(payload, 1, 4).rlike(r"[\x00-\x08]")


def positive_geometry(w: Column, h: Column) -> Column:
    return F.coalesce((w > 0) & (h > 0), F.lit(False))


def magic_matches(declared: Column, magic: Column) -> Column:
    return declared == magic


def min_side(w: Column, h: Column, px: int = MIN_SIDE) -> Column:
    return F.least(w, h) >= px


def aspect(w: Column, h: Column) -> Column:
    return F.greatest(w / h, h / w)


def aspect_ok(w: Column, h: Column, most: float = MAX_ASPECT) -> Column:
    return aspect(w, h) <= most


def mean(grid: Column) -> Column:
    return F.aggregate(grid, F.lit(0.0), lambda s, x: s + x) / F.size(grid)


def variance(grid: Column) -> Column:
    m = mean(grid)
    return F.aggregate(grid, F.lit(0.0), lambda s, x: s + (x - m) * (x - m)) / F.size(grid)


def near_monochrome(grid: Column, eps: float = 1e-4) -> Column:
    return variance(grid) < eps


def histogram(df: DataFrame, grid: str, bins: int = 8, low: float = -0.5, high: float = 0.5) -> DataFrame:
    """Values per bin over all grids; values outside go to the end bins."""
    cell = F.least(F.lit(bins - 1), F.greatest(F.lit(0), F.floor((F.col("v") - low) / ((high - low) / bins)).cast("int")))
    return df.select(F.explode(grid).alias("v")).groupBy(cell.alias("bin")).agg(F.count(F.lit(1)).alias("n"))


def border_fraction(grid: Column, side: int = 8) -> Column:
    """Share of a grid's energy that lies on its border."""
    edge = [r * side + c for r in range(side) for c in range(side) if r in (0, side - 1) or c in (0, side - 1)]
    energy = lambda cells: sum((F.get(grid, F.lit(i)) * F.get(grid, F.lit(i)) for i in cells), F.lit(0.0))
    total = F.aggregate(grid, F.lit(0.0), lambda s, x: s + x * x)
    return F.when(total > 0, energy(edge) / total).otherwise(F.lit(0.0))


def orientation_map(tag: int, side: int = 8) -> list[int]:
    """Cell of the stored grid that each upright cell comes from, for the eight orientation tags."""
    n, out = side - 1, []
    for r in range(side):
        for c in range(side):
            y, x = {1: (r, c), 2: (r, n - c), 3: (n - r, n - c), 4: (n - r, c), 5: (c, r), 6: (n - c, r), 7: (n - c, n - r), 8: (c, n - r)}[tag]
            out.append(y * side + x)
    return out


def normalise_orientation(grid: Column, tag: Column, side: int = 8) -> Column:
    maps = F.array(*(F.array(*map(F.lit, orientation_map(t, side))) for t in range(1, 9)))
    return F.transform(F.get(maps, tag - 1), lambda i: F.get(grid, i))


def blur_score(grid: Column, side: int = 8) -> Column:
    """Share of energy in differences of neighbouring cells, the cheap stand-in for high frequencies: one
    Haar step in both directions."""
    low = F.lit(0.0)
    for r in range(0, side, 2):
        for c in range(0, side, 2):
            s = sum((F.get(grid, F.lit((r + i) * side + c + j)) for i in (0, 1) for j in (0, 1)), F.lit(0.0)) / 2
            low = low + s * s
    total = F.aggregate(grid, F.lit(0.0), lambda s, x: s + x * x)
    return F.when(total > 0, 1 - low / total).otherwise(F.lit(0.0))


def watermark_lines(docs: DataFrame, least: int = 3) -> DataFrame:
    """Lines that stand in ``least`` documents or more of one source."""
    lines = docs.select("doc_id", "source", F.explode(F.array_distinct(F.split("text", "\n"))).alias("line")).where("line <> ''")
    return lines.groupBy("source", "line").agg(F.count(F.lit(1)).alias("documents")).where(F.col("documents") >= least)


def run_tiers(df: DataFrame, tiers: list[Column]) -> DataFrame:
    """Survivors of each tier go on to the next; cheap predicates come first."""
    for t in tiers:
        df = df.where(t)
    return df


def tier_counts(df: DataFrame, tiers: list[tuple[str, Column]]) -> DataFrame:
    """Rows that reach the end of each tier, by name."""
    out, names = None, []
    for name, keep in tiers:
        names.append((name, keep))
        one = run_tiers(df, [k for _, k in names]).agg(F.lit(name).alias("tier"), F.count(F.lit(1)).alias("kept"))
        out = one if out is None else out.union(one)
    return out


def dct_basis(side: int = 8) -> list[list[float]]:
    return [[math.cos(math.pi * (2 * x + 1) * u / (2 * side)) * (math.sqrt(1 / side) if u == 0 else math.sqrt(2 / side)) for x in range(side)] for u in range(side)]
