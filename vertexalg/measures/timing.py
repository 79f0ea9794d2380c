"""Times, ratios and their means."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable
from math import exp, log

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vertexalg.engine import ProgramResult
from vertexalg.graphs.graph import Graph


def clock(run: Callable[[], ProgramResult | DataFrame]) -> tuple[float, object]:
    """(seconds, result) of run, all of its rows computed."""
    began = time.perf_counter()
    out = run()
    finish(out)
    return time.perf_counter() - began, out


def timed_run(run: Callable[[Graph], ProgramResult | DataFrame], g: Graph, warm: int = 0, layouts: tuple[str, ...] = ("columns",)) -> tuple[float, object]:
    """(seconds, result) of run(g) with the graph's layouts in place before the clock starts: loading is no part of it."""
    g.persist(*layouts)
    for _ in range(warm):
        finish(run(g))
    return clock(lambda: run(g))


def finish(out) -> None:
    """Compute all rows of a frame; a program's result is already written."""
    if isinstance(out, DataFrame):
        out.write.format("noop").mode("overwrite").save()


def per_iteration(result: ProgramResult) -> float:
    """Mean seconds of a superstep."""
    return sum(s[6] for s in result.steps) / max(1, len(result.steps))


def geometric_mean(values: Iterable[float]) -> float:
    logs = [log(v) for v in values]
    return exp(sum(logs) / len(logs))


def geomean(column: str) -> Column:
    return F.exp(F.avg(F.log(column)))


def speedup(rows: DataFrame, base: str = "engine") -> DataFrame:
    """(system, algorithm, speedup) of rows (system, algorithm, dataset, seconds): the geometric mean over datasets of other / base;
    algorithm 'overall' is the geometric mean over algorithms. Above 1: base is faster."""
    own = rows.where(F.col("system") == base).select("algorithm", "dataset", F.col("seconds").alias("own"))
    ratio = rows.where(F.col("system") != base).join(own, ["algorithm", "dataset"]).withColumn("speedup", F.col("seconds") / F.col("own"))
    each = ratio.groupBy("system", "algorithm").agg(geomean("speedup").alias("speedup"))
    return each.unionByName(each.groupBy("system").agg(geomean("speedup").alias("speedup")).withColumn("algorithm", F.lit("overall")))


def slowdown(rows: DataFrame, native: str = "native", base: str = "engine") -> DataFrame:
    """How many times slower base is than native, by algorithm and overall."""
    return speedup(rows.where(F.col("system").isin(native, base)), base).select("algorithm", (1 / F.col("speedup")).alias("slowdown"))


def gains(seconds: dict[str, float]) -> dict[str, float]:
    """Times of a cumulative ablation (in order) as factors over the first."""
    first = next(iter(seconds.values()))
    return {k: first / v for k, v in seconds.items()}
