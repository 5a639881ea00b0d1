"""Column functions on arrays of doubles."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def total(a: Column) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda s, x: s + x)


def dot(a: Column, b: Column) -> Column:
    return total(F.zip_with(a, b, lambda x, y: x * y))


def axpy(c, a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: F.lit(c) * x + y)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def outer(a: Column, b: Column) -> Column:
    """Row-major products of all entries."""
    return F.flatten(F.transform(a, lambda x: F.transform(b, lambda y: x * y)))


def scatter(dims: Column, values: Column, d: int) -> Column:
    """Dense array of length d from sparse entries (the last value of a position wins, absent is 0)."""
    return F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda k: F.when(F.array_contains(dims, k), F.element_at(values, F.array_position(dims, k).cast("int"))).otherwise(F.lit(0.0)))
