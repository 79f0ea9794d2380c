"""Connected components of an edge list by alternating star contractions (published by Kiveris et al., 2014).

Every step is one aggregation and one join on edge rows, which shrink towards stars; nothing comes to the
driver but two numbers per round.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vertexalg.llm import common as C


def _towards(edges: DataFrame, large: bool) -> DataFrame:
    """Each node's larger (large) or smaller neighbours and itself are tied to its least neighbour."""
    both = edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    seen = both if large else both.where("v < u")
    least = seen.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
    tied = seen.where("v > u") if large else seen
    out = tied.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    if not large:
        out = out.union(least.select("u", F.col("m").alias("v")))
    return out.where("u <> v").distinct()


def components(edges: DataFrame, u: str, v: str) -> DataFrame:
    """(node, component) for every node with an edge; component is its least node id. A star's centre may be hot: its
    least neighbour is found by partial aggregates, and its row is joined to its edges, which adaptive execution splits."""
    now = C.materialise(edges.select(F.least(u, v).alias("v"), F.greatest(u, v).alias("u")).where("u <> v").distinct(), "edges")
    before = None
    while True:
        after = C.materialise(_towards(_towards(now, True), False), "edges")
        state = after.agg(F.count("*"), F.sum(F.hash("u", "v").cast("long"))).first()
        if state == before:
            C.discard(now)
            break
        C.discard(now)
        before, now = state, after
    return after.select(F.col("u").alias("node"), F.col("v").alias("component")).union(after.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
