"""Rectangles, Z-order codes and distances on integer coordinates."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def z_code(x: Column, y: Column, bits: int = 19) -> Column:
    """Bits of x (even places) and y (odd places) interleaved; coordinates below 2 ** bits."""

    def spread(c: Column) -> Column:
        c = c.cast("long")
        for shift, mask in ((16, 0x0000FFFF0000FFFF), (8, 0x00FF00FF00FF00FF), (4, 0x0F0F0F0F0F0F0F0F), (2, 0x3333333333333333), (1, 0x5555555555555555)):
            c = c.bitwiseOR(F.shiftleft(c, shift)).bitwiseAND(F.lit(mask).cast("long"))
        return c

    return spread(x).bitwiseOR(F.shiftleft(spread(y), 1))


def intersects(a: tuple[Column, ...], b: tuple[Column, ...]) -> Column:
    """Of rectangles (xmin, ymin, xmax, ymax)."""
    return (a[0] <= b[2]) & (b[0] <= a[2]) & (a[1] <= b[3]) & (b[1] <= a[3])


def contains(a: tuple[Column, ...], x: Column, y: Column) -> Column:
    return (a[0] <= x) & (x <= a[2]) & (a[1] <= y) & (y <= a[3])


def min_dist(a: tuple[Column, ...], x: Column, y: Column) -> Column:
    """From a point to a rectangle."""
    dx, dy = F.greatest(a[0] - x, x - a[2], F.lit(0)), F.greatest(a[1] - y, y - a[3], F.lit(0))
    return F.sqrt((dx * dx + dy * dy).cast("double"))


def haversine_miles(lon1: Column, lat1: Column, lon2: Column, lat2: Column) -> Column:
    """Great-circle distance of degrees; 3958.8 is the earth's mean radius in miles."""
    a = F.sin(F.radians(lat2 - lat1) / 2) ** 2 + F.cos(F.radians(lat1)) * F.cos(F.radians(lat2)) * F.sin(F.radians(lon2 - lon1) / 2) ** 2
    return 2 * 3958.8 * F.asin(F.sqrt(a))
