"""Vector expressions on array columns, all inside the JVM."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, v: s + v)


def norm(a: Column) -> Column:
    return F.sqrt(F.aggregate(F.transform(a, lambda x: x * x), F.lit(0.0), lambda s, v: s + v))


def scaled(a: Column, factor: Column | float) -> Column:
    return F.transform(a, lambda x: x * factor)


def sigmoid(x: Column) -> Column:
    """1 / (1 + e^-x) without overflow."""
    e = F.exp(-F.abs(x))
    return F.when(x >= 0, 1.0 / (1.0 + e)).otherwise(e / (1.0 + e))


def log1p_exp(x: Column) -> Column:
    """ln(1 + e^x) without overflow."""
    return F.greatest(x, F.lit(0.0)) + F.log1p(F.exp(-F.abs(x)))


def packed_frobenius(a: Column, d: int) -> Column:
    """Frobenius norm of a symmetric matrix from its packed triangle (i at column j's end is the diagonal)."""
    weights = F.array(*[F.lit(1.0 if i == j else 2.0) for j in range(d) for i in range(j + 1)])
    return F.sqrt(F.aggregate(F.zip_with(a, weights, lambda x, m: m * x * x), F.lit(0.0), lambda s, v: s + v))
