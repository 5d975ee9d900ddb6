"""Array algebra as Column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def scale(a: Column, c: Column) -> Column:
    return F.transform(a, lambda x: x * c)


def axpy(c: Column, a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: c * x + y)


def norm2(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def doubles(a: Column) -> Column:
    return F.transform(a, lambda x: x.cast("double"))
