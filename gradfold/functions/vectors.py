"""Vector algebra on array<double> columns, inside the JVM."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F


def total(a: Column) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda s, v: s + v)


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda p, q: p * q), F.lit(0.0), lambda s, v: s + v)


def axpy(w: Column, c: Column, x: Column) -> Column:
    """w + c * x."""
    return F.zip_with(w, x, lambda p, q: p + c * q)


def scale(a: Column, c: Column) -> Column:
    return F.transform(a, lambda v: v * c)


def norm1(a: Column) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda s, v: s + F.abs(v))


def norm2(a: Column) -> Column:
    return F.sqrt(F.aggregate(a, F.lit(0.0), lambda s, v: s + v * v))


def cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / (norm2(a) * norm2(b))


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """body(value) with the value computed once: bound as the variable of a lambda."""
    return F.element_at(F.transform(F.array(value), body), 1)


def literal(values: list[float]) -> Column:
    return F.array(*(F.lit(float(v)) for v in values))


def zeros(d: int) -> Column:
    return F.array_repeat(F.lit(0.0), d)
