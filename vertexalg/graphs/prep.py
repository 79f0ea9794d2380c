"""Preparation: self-loops, parallel edges, symmetry, orientation without cycles, bipartite check."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vertexalg.graphs.graph import Graph


def drop_self_loops(g: Graph) -> Graph:
    if g.form:
        return g
    return g.with_edges(g.edges.where("src <> dst"))


def ones(g: Graph) -> Graph:
    """Every edge of weight 1, so that distances are levels."""
    if g.unit:
        return g
    out = g.with_edges(g.edges.withColumn("value", F.lit(1).cast("long")), form=g.form)
    out.unit = True
    return out


def dedupe(g: Graph, how: str = "min") -> Graph:
    """One edge per (src, dst): how its value comes from the parallel ones (min, max, sum, mean, first by value, keep all)."""
    if how == "keep":
        return g
    fold = {"min": F.min, "max": F.max, "sum": F.sum, "mean": F.avg, "first": F.min}[how]
    return g.with_edges(g.edges.groupBy("src", "dst").agg(fold("value").alias("value")))


def symmetrize(g: Graph) -> Graph:
    """Both arcs of every edge, unweighted parallel ones once (the smaller value stays)."""
    if g.form == "symmetric":
        return g
    return g.with_edges(g.arcs("both").groupBy("src", "dst").agg(F.min("value").alias("value")), False, "symmetric")


def upper_triangle(g: Graph) -> Graph:
    """Symmetrise and keep src < dst: a graph without cycles."""
    if g.form == "upper":
        return g
    edges = g.edges.where("src <> dst").select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), "value")
    return g.with_edges(edges.groupBy("src", "dst").agg(F.min("value").alias("value")), True, "upper")


def degree_order(g: Graph) -> Graph:
    """As upper_triangle, but from the end of smaller (degree, id): in-lists stay near the square root of E, hubs too."""
    arcs = upper_triangle(g).edges.select("src", "dst", "value")
    degree = arcs.select(F.explode(F.array("src", "dst")).alias("vid")).groupBy("vid").count()
    with_src = arcs.join(degree.select(F.col("vid").alias("src"), F.col("count").alias("a")), "src")
    both = with_src.join(degree.select(F.col("vid").alias("dst"), F.col("count").alias("b")), "dst")
    swap = (F.col("a") < F.col("b")) | ((F.col("a") == F.col("b")) & (F.col("src") < F.col("dst")))
    # many small lists: the hub end sends last
    return g.with_edges(both.select(F.when(swap, F.col("dst")).otherwise(F.col("src")).alias("src"), F.when(swap, F.col("src")).otherwise(F.col("dst")).alias("dst"), "value"))


def as_bipartite(df: DataFrame, left: str, right: str, value: str) -> DataFrame:
    """(user, item, rating) in one id space: vid = 2*id for the left side and 2*id+1 for the right side."""
    return df.select((F.col(left) * 2).cast("long").alias("src"), (F.col(right) * 2 + 1).cast("long").alias("dst"), F.col(value).alias("value"))


def check_bipartite(edges: DataFrame) -> None:
    """Raises unless every edge goes from an even to an odd id."""
    if not edges.where("pmod(src, 2) <> 0 or pmod(dst, 2) <> 1").isEmpty():
        raise ValueError("the graph is not bipartite: an edge joins two vertices of one side")


def check_weights(g: Graph) -> None:
    if not g.edges.where("value is null").isEmpty():
        raise ValueError("an edge has no weight")
