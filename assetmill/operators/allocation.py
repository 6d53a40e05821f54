"""Maps over a square grid: bilinear upsampling, gradients, how uneven an allocation is."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def upsample(grid: Column, side: int, factor: int) -> Column:
    """Row-major grid of side·factor; cell centres are half a cell in, edges are held."""
    wide, last = side * factor, side - 1

    def place(k):
        at = F.greatest(F.lit(0.0), F.least(F.lit(float(last)), (k + 0.5) / factor - 0.5))
        low = F.floor(at).cast("int")
        return low, F.least(low + 1, F.lit(last)), at - low

    def one(k):
        (r, r1, v), (c, c1, h) = place(F.floor(k / wide)), place(k % wide)
        at = lambda a, b: F.get(grid, a * side + b).cast("double")
        return (at(r, c) * (1 - h) + at(r, c1) * h) * (1 - v) + (at(r1, c) * (1 - h) + at(r1, c1) * h) * v

    return F.transform(F.sequence(F.lit(0), F.lit(wide * wide - 1)), one)


def overlay(base: Column, heat: Column, share: float = 0.5) -> Column:
    """Blend of two grids of equal size."""
    return F.zip_with(base, heat, lambda b, h: (1 - share) * b + share * h)


def gradient(grid: Column, side: int) -> Column:
    """Size of the difference across each cell's neighbours, edges held."""

    def one(i):
        r, c, last = F.floor(i / side).cast("int"), i % side, F.lit(side - 1)
        at = lambda a, b: F.get(grid, a * side + b).cast("double")
        x = at(r, F.least(c + 1, last)) - at(r, F.greatest(c - 1, F.lit(0)))
        y = at(F.least(r + 1, last), c) - at(F.greatest(r - 1, F.lit(0)), c)
        return F.sqrt(x * x + y * y)

    return F.transform(F.sequence(F.lit(0), F.lit(side * side - 1)), one)


def gini(shares: Column) -> Column:
    """0 for an even allocation, near 1 if one cell has all; shares are positive."""
    n = F.size(shares)
    add = lambda s, x: s + x
    ranked = F.transform(F.array_sort(shares), lambda x, i: (2 * (i + 1) - n - 1) * x)
    return F.aggregate(ranked, F.lit(0.0), add) / (n * F.aggregate(shares, F.lit(0.0), add))
