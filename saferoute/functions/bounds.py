"""Lower bounds of distance and time from pivots and positions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def lb_dist(u: Column, v: Column) -> Column:
    """The largest difference of two vectors of pivot distances: no path is shorter."""
    return F.coalesce(F.array_max(F.zip_with(u, v, lambda a, b: F.abs(a - b))), F.lit(0).cast("long"))


def ub_dist_pivot(u: Column, v: Column) -> Column:
    """The shortest way over a pivot: a bound only where there are no obstacles."""
    return F.array_min(F.zip_with(u, v, lambda a, b: a + b))


def lb_time(dist_mm: Column, vmax_mm_h: Column | float) -> Column:
    """Minutes that a distance takes at the highest speed of the network, rounded down."""
    return F.floor(60 * dist_mm / vmax_mm_h).cast("long")


def euclid(x1: Column, y1: Column, x2: Column, y2: Column) -> Column:
    return F.sqrt(((x1 - x2) * (x1 - x2) + (y1 - y2) * (y1 - y2)).cast("double"))
