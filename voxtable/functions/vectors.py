"""Vector arithmetic as folds over arrays: one narrow stage, no explode."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column, b: Column) -> Column:
    """Null where a vector has no length."""
    return F.try_divide(dot(a, b), norm(a) * norm(b))


def squared_distance(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double"))), F.lit(0.0), lambda s, x: s + x)


def matrix(rows: Sequence[Sequence[float]]) -> Column:
    """A literal matrix; for small ones (the plan carries it)."""
    return F.array(*[F.array(*[F.lit(float(v)) for v in row]) for row in rows])


def project(v: Column, rows: Sequence[Sequence[float]]) -> Column:
    """Matrix times vector."""
    return F.transform(matrix(rows), lambda r: dot(r, v))
