"""Integer-millimetre geometry as column expressions.

A leg is the Euclidean distance rounded up: sums of legs are exact integers and the triangle inequality holds.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _column(value) -> Column:
    return F.col(value) if isinstance(value, str) else value


def leg_mm(ax, ay, bx, by) -> Column:
    dx, dy = _column(ax) - _column(bx), _column(ay) - _column(by)
    return F.ceil(F.sqrt((dx * dx + dy * dy).cast("double"))).cast("long")


def rect_gap_mm(x, y, xmin, ymin, xmax, ymax) -> Column:
    """Least distance from a point to a rectangle, rounded down: a safe lower bound of every leg into it."""
    x, y = _column(x), _column(y)
    dx = F.greatest(_column(xmin) - x, x - _column(xmax), F.lit(0))
    dy = F.greatest(_column(ymin) - y, y - _column(ymax), F.lit(0))
    return F.floor(F.sqrt((dx * dx + dy * dy).cast("double"))).cast("long")


def rect_far_mm(x, y, xmin, ymin, xmax, ymax) -> Column:
    """Greatest distance from a point to a rectangle: the farthest corner."""
    return F.greatest(*[leg_mm(x, y, cx, cy) for cx in (xmin, xmax) for cy in (ymin, ymax)])


def contains(x, y, xmin="xmin", ymin="ymin", xmax="xmax", ymax="ymax") -> Column:
    """Half-open containment: cells that share an edge never share a point."""
    x, y = _column(x), _column(y)
    return (x >= _column(xmin)) & (x < _column(xmax)) & (y >= _column(ymin)) & (y < _column(ymax))
