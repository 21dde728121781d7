"""Array algebra as native expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def axpy(c: float | Column, a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x * c + y)


def norm2(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def literal(x) -> Column:
    return F.array(*[F.lit(float(v)) for v in x])
