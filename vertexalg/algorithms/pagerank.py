"""Page rank: rank = r + (1 - r) * sum of in-neighbours' rank / out-degree, from 1.0; sinks pass nothing on."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vertexalg.engine import ProgramResult, run_program
from vertexalg.graphs.graph import Graph
from vertexalg.matrix.columns import degrees
from vertexalg.program import Reduce, VertexProgram


class PageRankProgram(VertexProgram):
    """mode 'all': every vertex sends and is updated each round. 'recipients': only vertices that changed send and only
    those that a value reached are updated (the plain superstep rule)."""

    state = ("rank", "outdeg")

    def __init__(self, r: float = 0.15, mode: str = "all", tol: float | None = None) -> None:
        self.r, self.tol = r, tol
        self.activation, self.apply_to = ("all", "all") if mode == "all" else ("changed", "recipients")
        self.stop_when_unchanged = tol is not None or mode != "all"

    def init(self, v):
        return {"rank": F.lit(1.0), "outdeg": v("outdeg")}

    def send(self, s):
        return F.when(s("outdeg") > 0, s("rank") / s("outdeg"))

    def reduce(self):
        return Reduce.sum()

    def apply(self, red, s):
        return {"rank": F.lit(self.r) + F.lit(1 - self.r) * F.coalesce(red, F.lit(0.0))}

    def changed(self, old, new):
        return F.abs(old("rank") - new("rank")) > self.tol if self.tol is not None else ~old("rank").eqNullSafe(new("rank"))


def with_out_degree(g: Graph, lying: bool = False) -> Graph:
    """The same graph, its vertices with outdeg (counted where the edges lie, so it costs no more than V rows).
    lying: count in the columns that the supersteps use, so that no edge moves for it."""
    if lying:
        degree = degrees(g).withColumnRenamed("degree", "outdeg")
    else:
        degree = g.edges.groupBy(F.col("src").alias("vid")).agg(F.count("*").alias("outdeg"))
    out = Graph(g.edges, g.vertices.join(degree, "vid", "left").na.fill(0, ["outdeg"]), g.directed, g.conf)
    out._layouts = g._layouts
    return out


def pagerank_run(g: Graph, r: float = 0.15, iterations: int | None = 10, rank_mode: str = "all", tol: float | None = None, strategy: str = "auto", **options) -> ProgramResult:
    return run_program(with_out_degree(g, strategy in ("auto", "columns")), PageRankProgram(r, rank_mode, tol), iterations, strategy=strategy, **options)


def pagerank(g: Graph, r: float = 0.15, iterations: int | None = 10, rank_mode: str = "all", tol: float | None = None, strategy: str = "auto") -> DataFrame:
    """(vid, rank). With tol and iterations None: until no rank moves by more than tol."""
    return pagerank_run(g, r, iterations, rank_mode, tol, strategy).state.select("vid", "rank")


def pagerank_step(g: Graph, ranks: DataFrame, r: float = 0.15) -> DataFrame:
    """One round from given ranks (vid, rank): the unit of time per iteration."""
    sized = with_out_degree(g)
    start = sized.vertices.select("vid", "outdeg").join(ranks, "vid").select("vid", "rank", "outdeg", F.lit(True).alias("active"))
    return run_program(sized, PageRankProgram(r), 1, start=start).state.select("vid", "rank")
