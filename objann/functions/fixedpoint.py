"""Exact integer arithmetic shared by every engine that checks a result."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

POINT_SCALE = 1 << 16
DIRECTION_SCALE = 1 << 12


def q16(value: Column) -> Column:
    """A real as a fixed-point integer, halves upwards."""
    return F.floor(value.cast("double") * POINT_SCALE + 0.5).cast("long")


def floor_div(value: Column, by) -> Column:
    by = F.lit(by) if isinstance(by, int) else by
    return ((value - F.pmod(value, by)) / by).cast("long")


def sq_dist(a: Column, b: Column) -> Column:
    """Squared Euclidean distance of two integer vectors, as a SQL expression."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0).cast("long"), lambda acc, x: acc + x)


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0).cast("long"), lambda acc, x: acc + x)


def ceil_div(a: int, b: int) -> int:
    return -(-a // b)
