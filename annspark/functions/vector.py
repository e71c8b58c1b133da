"""Vector arithmetic as column expressions; they compose and stay in the JVM."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _zero():
    return F.lit(0.0).cast("double")


def l2sq(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double"))), _zero(), lambda t, x: t + x)


def l2(a: Column, b: Column) -> Column:
    return F.sqrt(l2sq(a, b))


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), _zero(), lambda t, x: t + x)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / (norm(a) * norm(b))


def axpy(factor: float, a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x * F.lit(float(factor)) + y)


def matvec(rows: list[list[float]], a: Column) -> Column:
    return F.array(*[dot(F.array(*map(F.lit, map(float, row))), a) for row in rows])


def normalised(a: Column) -> Column:
    return F.transform(a, lambda x: x / norm(a))


def clamped(a: Column, low: float, high: float) -> Column:
    return F.transform(a, lambda x: F.greatest(F.lit(low), F.least(F.lit(high), x)))
