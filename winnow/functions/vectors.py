"""Arithmetic on array<double> columns."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F


def _c(x: Column | str) -> Column:
    return (F.col(x) if isinstance(x, str) else x).cast("array<double>")


def dot(a: Column | str, b: Column | str) -> Column:
    return F.aggregate(F.zip_with(_c(a), _c(b), lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column | str) -> Column:
    return F.sqrt(F.aggregate(_c(a), F.lit(0.0), lambda s, x: s + x * x))


def cosine(a: Column | str, b: Column | str) -> Column:
    """0 where either vector is zero."""
    n = norm(a) * norm(b)
    return F.when(n > 0, dot(a, b) / n).otherwise(F.lit(0.0))


def l2(a: Column | str, b: Column | str) -> Column:
    return F.sqrt(F.aggregate(F.zip_with(_c(a), _c(b), lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x))


def add(a: Column | str, b: Column | str) -> Column:
    return F.zip_with(_c(a), _c(b), lambda x, y: x + y)


def scale(a: Column | str, by: Column | float) -> Column:
    k = by if isinstance(by, Column) else F.lit(float(by))
    return F.transform(_c(a), lambda x: x * k)


def mean(vec: str, dims: int) -> list[Column]:
    """Aggregates for the element-wise mean of a fixed-width vector column, to be gathered with ``gathered``."""
    return [F.avg(F.element_at(_c(vec), i + 1)).alias(f"_v{i}") for i in range(dims)]


def gathered(dims: int) -> Column:
    return F.array(*[F.col(f"_v{i}") for i in range(dims)])


def against(vec: Column | str, fixed: list[float]) -> Column:
    """Dot product with a constant vector, unrolled so that it stays in generated code."""
    v = _c(vec)
    return reduce(lambda s, x: s + x, [F.element_at(v, i + 1) * F.lit(float(x)) for i, x in enumerate(fixed)])
