"""Plane geometry as column expressions over integer coordinates.

Edges run along an axis, so an edge, or a part of one, is its own bounding box:
box tests are exact for them, and are bounds for longer pieces.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def along(c0: str, c1: str, part: str, w: str) -> Column:
    """Coordinate after ``part`` of an edge of weight ``w`` from c0 to c1, rounded down."""
    return F.floor(F.expr(f"({c1} - {c0}) * {part}") / F.col(w)).cast("long") + F.col(c0)


def axis_gap(lo: Column, hi: Column, other_lo: Column, other_hi: Column) -> Column:
    """Distance between two intervals, 0 where they meet."""
    return F.greatest(F.lit(0), lo - other_hi, other_lo - hi)


def box_gap_squared(box: tuple, other: tuple) -> Column:
    """Squared distance between boxes (x0, y0, x1, y1) of columns with x0 <= x1 and y0 <= y1."""
    gx, gy = axis_gap(box[0], box[2], other[0], other[2]), axis_gap(box[1], box[3], other[1], other[3])
    return (gx * gx + gy * gy).cast("long")


def nearest_part(x: Column, y: Column, x0: Column, y0: Column, x1: Column, y1: Column) -> Column:
    """Where on a segment, as a share of it, the point nearest to (x, y) lies (double)."""
    dx, dy = x1 - x0, y1 - y0
    length = dx * dx + dy * dy
    return F.when(length == 0, F.lit(0.0)).otherwise(F.greatest(F.lit(0.0), F.least(F.lit(1.0), ((x - x0) * dx + (y - y0) * dy) / length)))


def point_segment_squared(x: Column, y: Column, x0: Column, y0: Column, x1: Column, y1: Column) -> Column:
    """Squared distance from a point to a segment of any direction (double)."""
    part = nearest_part(x, y, x0, y0, x1, y1)
    px, py = x0 + part * (x1 - x0), y0 + part * (y1 - y0)
    return (x - px) * (x - px) + (y - py) * (y - py)
