"""Degrees as products with a vector of ones."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vertexalg.engine import run_program
from vertexalg.graphs.graph import Graph
from vertexalg.program import VertexProgram


class DegreeProgram(VertexProgram):
    activation, apply_to, max_supersteps = "all", "all", 1
    state = ("degree",)

    def __init__(self, direction: str = "out", weighted: bool = False) -> None:
        self.direction, self.weighted = direction, weighted

    def init(self, v):
        return {"degree": F.lit(0.0) if self.weighted else F.lit(0).cast("long")}

    def send(self, s):
        return F.lit(1).cast("long")

    def process(self, m, e, dst):
        return e.cast("double") if self.weighted else m

    def apply(self, red, s):
        return {"degree": F.coalesce(red, F.lit(0.0 if self.weighted else 0))}


def in_degree(g: Graph, weighted: bool = False, strategy: str = "auto") -> DataFrame:
    return run_program(g, DegreeProgram("out", weighted), strategy=strategy).state.select("vid", "degree")


def out_degree(g: Graph, weighted: bool = False, strategy: str = "auto") -> DataFrame:
    return run_program(g, DegreeProgram("in", weighted), strategy=strategy).state.select("vid", "degree")


def degree_histogram(g: Graph, which=in_degree) -> DataFrame:
    return which(g).groupBy("degree").agg(F.count("*").alias("vertices"))


def degree_stats(g: Graph) -> DataFrame:
    """One row: vertices, edges, mean and largest in- and out-degree."""
    ends = in_degree(g).withColumnRenamed("degree", "i").join(out_degree(g).withColumnRenamed("degree", "o"), "vid")
    return ends.agg(F.count("*").alias("vertices"), F.sum("i").alias("edges"), F.round(F.avg("i"), 6).alias("mean_degree"), F.max("i").alias("max_in"), F.max("o").alias("max_out"))
