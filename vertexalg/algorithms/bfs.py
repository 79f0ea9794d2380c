"""Breadth-first search: levels from one root or more, on the symmetric graph; null where unreached."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vertexalg.engine import ProgramResult, run_program
from vertexalg.graphs.graph import Graph
from vertexalg.graphs.prep import drop_self_loops, symmetrize
from vertexalg.program import Reduce, VertexProgram


class BfsProgram(VertexProgram):
    def __init__(self, roots: list[int], parents: bool = False, prune_visited: bool = False) -> None:
        self.roots, self.parents, self.needs_dst_state = roots, parents, prune_visited
        self.state = ("level", "parent") if parents else ("level",)

    def init(self, v):
        root = v("vid").isin(self.roots)
        level = {"level": F.when(root, F.lit(0)).cast("long")}
        return level | ({"parent": F.lit(None).cast("long")} if self.parents else {})

    def active0(self, v):
        return v("vid").isin(self.roots)

    def send(self, s):
        return F.struct(s("level").alias("level"), F.col("vid").alias("by")) if self.parents else s("level")

    def process(self, m, e, dst):
        out = F.struct((m["level"] + 1).alias("level"), m["by"].alias("by")) if self.parents else m + 1
        # set once: what has a level already takes no contribution
        return F.when(dst("level").isNull(), out) if self.needs_dst_state else out

    def reduce(self):
        return Reduce.min()

    def apply(self, red, s):
        first = s("level").isNull()
        if self.parents:
            return {"level": F.when(first, red["level"]).otherwise(s("level")), "parent": F.when(first, red["by"]).otherwise(s("parent"))}
        return {"level": F.coalesce(s("level"), red)}


def check_present(g: Graph, ids: list[int]) -> None:
    if g.vertices.where(F.col("vid").isin(ids)).select("vid").distinct().count() < len(set(ids)):
        raise ValueError("a source is no vertex of the graph")


def bfs_run(g: Graph, root: int | None = None, roots: list[int] | None = None, parents: bool = False, prune_visited: bool = False, strategy: str = "auto", symmetric: bool = False, **options) -> ProgramResult:
    roots = roots if roots is not None else [root]
    check_present(g, roots)
    both = g if symmetric else symmetrize(drop_self_loops(g))
    out = run_program(both, BfsProgram(roots, parents, prune_visited), strategy=strategy, **options)
    if both is not g:
        both.unpersist()
    return out


def bfs(g: Graph, root: int | None = None, **options) -> DataFrame:
    """(vid, level[, parent]); symmetric=True: the edges are symmetric already."""
    return bfs_run(g, root, **options).state.drop("active")


def bfs_levels(levels: DataFrame) -> DataFrame:
    return levels.groupBy("level").agg(F.count("*").alias("vertices"))
