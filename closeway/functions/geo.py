"""Plane and sphere geometry as column expressions."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

EARTH_RADIUS_M = 6_371_008.8


def distance(x1: Column, y1: Column, x2: Column, y2: Column) -> Column:
    """Euclidean distance; sqrt of the sum of squares, so that every engine rounds alike."""
    dx, dy = x1 - x2, y1 - y2
    return F.sqrt((dx * dx + dy * dy).cast("double"))


def haversine(lon1: Column, lat1: Column, lon2: Column, lat2: Column) -> Column:
    """Great-circle distance in metres between two points in degrees."""
    a = F.pow(F.sin(F.radians(lat2 - lat1) / 2), 2) + F.cos(F.radians(lat1)) * F.cos(F.radians(lat2)) * F.pow(F.sin(F.radians(lon2 - lon1) / 2), 2)
    return 2 * EARTH_RADIUS_M * F.asin(F.sqrt(F.least(a, F.lit(1.0))))


def bearing(xr: Column, yr: Column, xl: Column, yl: Column) -> Column:
    """Counter-clockwise angle in [0, 2 pi) at the reference place from the x axis to the located place."""
    a = F.atan2((yl - yr).cast("double"), (xl - xr).cast("double"))
    return F.when(a < 0, a + 2 * math.pi).otherwise(a)


def in_ellipse(x: Column, y: Column, sx: Column, sy: Column, tx: Column, ty: Column, shape: str = "drawn", factor: float = 1.6) -> Column:
    """Whether a point lies in the query region of a trip from s to t.

    ``drawn``: centre half way, semi-axes 0.8 and 0.55 of the distance, turned to the line from s to t. ``confocal``:
    the distances to s and t add up to at most ``factor`` times theirs. ``box``: along the line between s and t, and at
    most half their distance off it. ``none``: everything. A trip from a place to itself has an empty region.
    """
    if shape == "none":
        return F.lit(True)
    dx, dy = (tx - sx).cast("double"), (ty - sy).cast("double")
    d = F.sqrt(dx * dx + dy * dy)
    if shape == "confocal":
        return (d > 0) & (distance(x, y, sx, sy) + distance(x, y, tx, ty) <= factor * d)
    px, py = x - (sx + tx) / 2, y - (sy + ty) / 2
    along, off = (px * dx + py * dy) / d, (py * dx - px * dy) / d
    if shape == "box":
        return (d > 0) & (F.abs(along) <= d / 2) & (F.abs(off) <= d / 2)
    if shape != "drawn":
        raise ValueError(f"unknown shape {shape}")
    return (d > 0) & (F.pow(along / (0.8 * d), 2) + F.pow(off / (0.55 * d), 2) <= 1)
