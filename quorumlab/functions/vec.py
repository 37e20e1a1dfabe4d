"""Vectors as array<double> columns, with built-in higher-order functions only."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def total(x: Column) -> Column:
    return F.aggregate(x, F.lit(0.0), lambda a, v: a + v)


def dot(x: Column, y: Column) -> Column:
    return total(F.zip_with(x, y, lambda a, b: a * b))


def axpy(alpha: Column | float, x: Column, y: Column) -> Column:
    """alpha x + y."""
    a = F.lit(alpha) if isinstance(alpha, (int, float)) else alpha
    return F.zip_with(x, y, lambda u, v: a * u + v)


def scale(alpha: Column | float, x: Column) -> Column:
    a = F.lit(alpha) if isinstance(alpha, (int, float)) else alpha
    return F.transform(x, lambda u: a * u)


def norm2(x: Column) -> Column:
    """Squared Euclidean length."""
    return dot(x, x)


def argmax(x: Column) -> Column:
    """Zero-based place of the first largest entry."""
    return (F.array_position(x, F.array_max(x)) - 1).cast("int")


def softmax(x: Column) -> Column:
    shifted = F.transform(F.array(x), lambda v: F.transform(v, lambda u: F.exp(u - F.array_max(v))))[0]
    return F.transform(F.array(shifted), lambda e: F.transform(e, lambda u: u / total(e)))[0]
