"""Array algebra as column expressions, for factors kept as arrays."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, v: s + v)


def norm2(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def axpy(c: Column, a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: c * x + y)


def scale(a: Column, c: Column) -> Column:
    return F.transform(a, lambda x: x * c)


def argmax_component(a: Column) -> Column:
    """Place of the largest entry from 0, the first one of ties; null for an empty array."""
    return F.when(F.size(a) > 0, (F.array_position(a, F.array_max(a)) - 1).cast("int"))
