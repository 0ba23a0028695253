"""Column functions on points, borders and boxes."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def dist2(ax: Column, ay: Column, bx: Column, by: Column) -> Column:
    """Squared distance; exact for long coordinates below 2 ** 31."""
    return (ax - bx) * (ax - bx) + (ay - by) * (ay - by)


def hp_distance(d2_home: Column, d2_other: Column, d2_pivots: Column) -> Column:
    """Distance to the line halfway between two pivots, positive on the home side: squared distances to the home pivot, to the
    other one, and between the two."""
    return (d2_other - d2_home) / (F.lit(2.0) * F.sqrt(d2_pivots.cast("double")))


def micro(c: Column) -> Column:
    """A double at a millionth, rounded half up, so that engines agree."""
    return F.floor(c * 1e6 + 0.5) / 1e6


def box_disk_d2(x: Column, y: Column, x0: Column, y0: Column, x1: Column, y1: Column) -> Column:
    """Squared distance from a point to a closed box."""
    dx = F.greatest(x0 - x, x - x1, F.lit(0))
    dy = F.greatest(y0 - y, y - y1, F.lit(0))
    return dx * dx + dy * dy
