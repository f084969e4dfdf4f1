"""Distances, cells and neighbour counts, as numbers and as column expressions."""

from __future__ import annotations

import math

from pyspark.sql import Column, functions as F


def reach(d: int) -> int:
    """Cells each way in one dimension that can hold points within eps."""
    return math.isqrt(d - 1) + 1 if d > 1 else 1


def safe_reach(d: int) -> int:
    """``reach``, one more where the root is whole and rounding could shift a border."""
    return math.isqrt(d) + 1


def cell_scale(d: int, eps: float) -> float:
    return math.sqrt(d) / eps


def box_offset_count(d: int) -> int:
    """Cells of the full box around a cell, itself included."""
    return (2 * reach(d) + 1) ** d


def reachable_offset_count(d: int) -> int:
    """Cells other than itself that can hold a point within eps of a cell's points.

    An offset counts if its gaps, max(|offset| - 1, 0), have squares that sum to less than d.
    """
    ways = [1] + [0] * (d - 1)
    for _ in range(d):
        new = [0] * d
        for total, n in enumerate(ways):
            gap = 0
            while n and total + gap * gap < d:
                new[total + gap * gap] += n * (3 if gap == 0 else 2)
                gap += 1
        ways = new
    return sum(ways) - 1


def cell_of(coord: Column, d: int, eps: float) -> Column:
    """The address of the cell of side eps / sqrt(d) that holds a point."""
    c = cell_scale(d, eps)
    return F.transform(coord, lambda x: F.floor(x.cast("double") * F.lit(c)))


def dist2(a: Column, b: Column, exact: bool = True) -> Column:
    zero = F.lit(0).cast("long") if exact else F.lit(0.0)
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), zero, lambda s, x: s + x)


def cell_gap2(a: Column, b: Column) -> Column:
    """Sum of squared cell gaps; below d the cells can hold points within eps of each other."""
    def gap(x: Column, y: Column) -> Column:
        g = F.greatest(F.abs(x - y) - 1, F.lit(0).cast("long"))
        return g * g

    return F.aggregate(F.zip_with(a, b, gap), F.lit(0).cast("long"), lambda s, x: s + x)


def box_gap2(lo_a: Column, hi_a: Column, lo_b: Column, hi_b: Column, exact: bool = True) -> Column:
    """Squared distance between two boxes."""
    zero = F.lit(0).cast("long") if exact else F.lit(0.0)
    ahead = F.zip_with(lo_a, hi_b, lambda x, y: F.greatest(x - y, zero))
    behind = F.zip_with(lo_b, hi_a, lambda x, y: F.greatest(x - y, zero))
    return F.aggregate(F.zip_with(ahead, behind, lambda x, y: F.greatest(x, y)), zero, lambda s, x: s + x * x)


def eps2(eps: float, exact: bool) -> float | int:
    """eps squared; for whole coordinates the largest whole number not above it."""
    return math.floor(eps * eps + 1e-9) if exact else eps * eps
