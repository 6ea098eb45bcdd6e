"""Element-wise expressions on arrays of doubles."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def vec_add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def vec_sub(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x - y)


def vec_scale(a: Column, by: Column | float) -> Column:
    return F.transform(a, lambda x: x * by)


def vec_dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def vec_norm(a: Column) -> Column:
    return F.sqrt(F.aggregate(a, F.lit(0.0), lambda s, x: s + x * x))


def cosine(a: Column, b: Column) -> Column:
    """Null if one of the vectors is zero."""
    return F.try_divide(vec_dot(a, b), F.nullif(vec_norm(a) * vec_norm(b), F.lit(0.0)))


def vec_sum(column: str, n: int) -> Column:
    """Element-wise sum of a group's arrays of length ``n``: one plain sum for each place keeps hash aggregation."""
    return F.array(*[F.sum(F.col(column)[i]) for i in range(n)])


def flat(column: str, n: int, prefix: str) -> list[Column]:
    return [F.col(column)[i].alias(f"{prefix}{i}") for i in range(n)]
