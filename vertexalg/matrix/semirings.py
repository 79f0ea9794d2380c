"""Pairs of multiply and add."""

from __future__ import annotations

from pyspark.sql import functions as F

from vertexalg.program import Reduce

PLUS_TIMES = (lambda m, e: m * e, Reduce.sum())
MIN_PLUS = (lambda m, e: m + e, Reduce.min())
OR_AND = (lambda m, e: m & (e != 0), Reduce.any())
PLUS_PAIR = (lambda m, e: F.lit(1).cast("long"), Reduce.sum())
