"""Connected components by the least label (edges count both ways)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vertexalg.engine import run_program
from vertexalg.graphs.graph import Graph
from vertexalg.program import Reduce, VertexProgram


class ComponentsProgram(VertexProgram):
    direction, state = "both", ("label",)

    def init(self, v):
        return {"label": v("vid")}

    def send(self, s):
        return s("label")

    def reduce(self):
        return Reduce.min()

    def apply(self, red, s):
        return {"label": F.least(s("label"), red)}


def components(g: Graph, strategy: str = "auto") -> DataFrame:
    return run_program(g, ComponentsProgram(), strategy=strategy).state.select("vid", F.col("label").alias("component"))
