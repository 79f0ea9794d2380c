"""Row partitioning of the matrix: hashed blocks, more blocks than cores, and blocks of equal numbers of edges."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def partition_rows(edges: DataFrame, partitions: int | None = None, key: str = "dst", factor: int = 1, balance: str = "hash") -> DataFrame:
    """Edges dealt by key. factor: blocks per core (1: no slack for the scheduler; 8: tasks are dealt as cores come free).

    balance 'edges': ranges of keys with about as many edges each, from per-key counts; a hub whose own edges exceed a
    block keeps one block here and is split by salted() where its reduction allows."""
    n = (partitions or edges.sparkSession.sparkContext.defaultParallelism) * factor
    if balance == "hash":
        return edges.repartition(n, key)
    weight = edges.groupBy(key).agg(F.count("*").alias("n"))
    total = weight.agg(F.sum("n")).first()[0] or 1
    # running sums per coarse range of keys first, so that no single task orders all keys
    coarse = weight.withColumn("g", F.col(key).bitwiseAND(~0xFFF))
    groups = coarse.groupBy("g").agg(F.sum("n").alias("s")).withColumn("base", F.coalesce(F.sum("s").over(W.orderBy("g").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
    upto = F.sum("n").over(W.partitionBy("g").orderBy(key).rowsBetween(W.unboundedPreceding, -1))
    placed = coarse.join(groups.select("g", "base"), "g").select(key, F.least(F.lit(n - 1), ((F.col("base") + F.coalesce(upto, F.lit(0))) * n / total).cast("int")).alias("block"))
    return edges.join(placed, key).repartition(n, "block")


def salted(contributions: DataFrame, key: str, value: str, fold, salts: int = 16) -> DataFrame:
    """Hub-safe reduction in two levels (fold must be commutative and associative)."""
    first = contributions.withColumn("_salt", F.pmod(F.monotonically_increasing_id(), F.lit(salts))).groupBy(key, "_salt").agg(fold(value).alias(value))
    return first.groupBy(key).agg(fold(value).alias(value))
