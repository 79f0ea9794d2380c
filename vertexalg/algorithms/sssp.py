"""Single-source shortest paths by frontier Bellman-Ford: only vertices whose distance changed send."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vertexalg.engine import ProgramResult, run_program
from vertexalg.graphs.graph import Graph
from vertexalg.graphs.prep import check_weights
from vertexalg.program import Reduce, VertexProgram


class SsspProgram(VertexProgram):
    """Null is infinity. frontier False: every reached vertex sends in every round."""

    def __init__(self, source: int, frontier: bool = True, parents: bool = False, kind: str = "long") -> None:
        self.source, self.parents, self.kind = source, parents, kind
        self.activation = "changed" if frontier else "all"
        self.state = ("dist", "parent") if parents else ("dist",)

    def init(self, v):
        dist = {"dist": F.when(v("vid") == self.source, F.lit(0)).cast(self.kind)}
        return dist | ({"parent": F.lit(None).cast("long")} if self.parents else {})

    def active0(self, v):
        return v("vid") == self.source

    def send(self, s):
        if self.parents:
            return F.when(s("dist").isNotNull(), F.struct(s("dist").alias("dist"), F.col("vid").alias("by")))
        return s("dist")

    def process(self, m, e, dst):
        return F.struct((m["dist"] + e).alias("dist"), m["by"].alias("by")) if self.parents else m + e

    def reduce(self):
        return Reduce.min()

    def apply(self, red, s):
        if self.parents:
            # a tie takes the smaller parent, so the tree does not depend on the order of rounds
            better = s("dist").isNull() | (red["dist"] < s("dist")) | ((red["dist"] == s("dist")) & (s("parent") > red["by"]))
            return {"dist": F.least(s("dist"), red["dist"]), "parent": F.when(better, red["by"]).otherwise(s("parent"))}
        return {"dist": F.least(s("dist"), red)}

    def changed(self, old, new):
        return ~old("dist").eqNullSafe(new("dist"))


def sssp_run(g: Graph, source: int, frontier: bool = True, parents: bool = False, max_supersteps: int | None = None, on_negative_cycle: str = "error", strategy: str = "auto", **options) -> ProgramResult:
    """With a negative cycle distances fall for ever: more rounds than vertices raise an error (or stop, with 'stop')."""
    check_weights(g)
    kind = dict(g.edges.dtypes)["value"]
    row = g.vertices.agg(F.count("*").alias("n"), F.count_if(F.col("vid") == source).alias("here")).first()
    if not row["here"]:
        raise ValueError("a source is no vertex of the graph")
    bound = max_supersteps or row["n"] + 1
    out = run_program(g, SsspProgram(source, frontier, parents, "double" if kind in ("double", "float") else "long"), bound, strategy=strategy, **options)
    if max_supersteps is None and not out.converged and on_negative_cycle == "error":
        raise ValueError("a cycle of negative weight can be reached from the source")
    return out


def sssp(g: Graph, source: int, **options) -> DataFrame:
    """(vid, dist): null where the source does not reach."""
    return sssp_run(g, source, **options).state.select("vid", "dist")


def shortest_paths(g: Graph, source: int, **options) -> DataFrame:
    """(vid, dist, parent)."""
    return sssp_run(g, source, parents=True, **options).state.select("vid", "dist", "parent")


def path_to(tree: DataFrame, target: int) -> list[int]:
    """The vertices from the source to target along parents, one lookup per step of the path."""
    out, at = [], target
    while at is not None:
        out.append(at)
        row = tree.where(F.col("vid") == at).select("parent").first()
        at = row["parent"] if row else None
    return out[::-1]
