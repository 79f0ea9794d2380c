"""Functions of dense vectors held as arrays (elements become doubles first)."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def wide(x: Column | str) -> Column:
    return F.transform(x, lambda v: v.cast("double"))


def dot(x: Column, y: Column) -> Column:
    return F.aggregate(F.zip_with(x, y, lambda a, b: a * b), F.lit(0.0), lambda acc, v: acc + v)


def norm(x: Column) -> Column:
    return F.sqrt(dot(x, x))


def cosine(x: Column, y: Column) -> Column:
    return dot(x, y) / (norm(x) * norm(y))
