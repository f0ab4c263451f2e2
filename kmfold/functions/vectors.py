"""Vector algebra on array columns, by built-in higher-order functions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _col(x: Column | str) -> Column:
    return F.col(x) if isinstance(x, str) else x


def zero() -> Column:
    return F.lit(0.0)


def dot(x: Column | str, y: Column | str) -> Column:
    return F.aggregate(F.zip_with(_col(x), _col(y), lambda a, b: a * b), zero(), lambda s, v: s + v)


def squared_length(x: Column | str) -> Column:
    return F.aggregate(_col(x), zero(), lambda s, v: s + v * v)


def squared_distance(x: Column | str, y: Column | str) -> Column:
    return F.aggregate(F.zip_with(_col(x), _col(y), lambda a, b: (a - b) * (a - b)), zero(), lambda s, v: s + v)


def scale(x: Column | str, by: Column | float) -> Column:
    by = F.lit(by) if isinstance(by, (int, float)) else by
    return F.transform(_col(x), lambda v: v * by)


def lattice(x: Column | str, grid: int = 1000) -> Column:
    """Coordinates as longs on a grid: their sums do not depend on the order."""
    return F.transform(_col(x), lambda v: F.round(v.cast("double") * grid).cast("bigint"))
