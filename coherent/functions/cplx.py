"""Complex numbers as pairs of columns (real, imaginary); Spark has no complex type."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

Pair = tuple[Column, Column]


def pair(prefix: str = "") -> Pair:
    return F.col(f"{prefix}re"), F.col(f"{prefix}im")


def mul(a: Pair, b: Pair) -> Pair:
    return a[0] * b[0] - a[1] * b[1], a[0] * b[1] + a[1] * b[0]


def conj(a: Pair) -> Pair:
    return a[0], -a[1]


def add(a: Pair, b: Pair) -> Pair:
    return a[0] + b[0], a[1] + b[1]


def scale(a: Pair, x: Column) -> Pair:
    return a[0] * x, a[1] * x


def abs2(a: Pair) -> Column:
    return a[0] * a[0] + a[1] * a[1]


def arg(a: Pair) -> Column:
    return F.atan2(a[1], a[0])


def total(a: Pair) -> list[Column]:
    """Sum of complex values as two aggregates named re and im."""
    return [F.sum(a[0]).alias("re"), F.sum(a[1]).alias("im")]


def clean(x: Column, digits: int = 6) -> Column:
    """Rounded for comparison; adding zero turns -0.0 into 0.0."""
    return F.round(x, digits) + F.lit(0.0)
