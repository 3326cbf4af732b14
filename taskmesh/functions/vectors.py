"""Vector arithmetic on array columns, inside the JVM; sums run from the first coordinate on, so they are reproducible."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(a: Column | str, b: Column | str) -> Column:
    products = F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double"))
    return F.aggregate(products, F.lit(0.0), lambda s, p: s + p)


def norm2(a: Column | str) -> Column:
    """The squared length."""
    return dot(a, a)


def scale(a: Column | str, by: Column | float) -> Column:
    by = by if isinstance(by, Column) else F.lit(float(by))
    return F.transform(a, lambda x: x * by)


def add(a: Column | str, b: Column | str) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def axpy(by: Column | float, x: Column | str, y: Column | str) -> Column:
    """by * x + y."""
    by = by if isinstance(by, Column) else F.lit(float(by))
    return F.zip_with(x, y, lambda a, b: by * a + b)


def clip(a: Column, low: float, high: float) -> Column:
    return F.greatest(F.lit(low), F.least(F.lit(high), a))


def zeros(n: Column | int) -> Column:
    return F.array_repeat(F.lit(0.0), n)
