"""Baseline: both end states are joined to all edges in every round, and what isn't active is filtered after."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vertexalg.engine import ProgramResult, run_program
from vertexalg.graphs.graph import Graph
from vertexalg.graphs.prep import upper_triangle
from vertexalg.matrix.spmv import _reduced
from vertexalg.program import VertexProgram


def triplets(g: Graph, state: DataFrame, x: DataFrame, program: VertexProgram) -> DataFrame:
    """(vid, red, _n) from all edges with both states beside them; no layout is reused."""
    names = list(program.state)
    sends = F.col("active") if program.activation == "changed" else F.lit(True)
    sources = state.select(F.col("vid").alias("src"), F.when(sends, program.send(F.col)).alias("_m"))
    targets = state.select(F.col("vid").alias("dst"), F.struct(*names).alias("_dst"))
    forward = g.edges.select("src", "dst", "value")
    back = g.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "value")
    edges = {"out": forward, "in": back, "both": forward.unionByName(back)}[program.direction]
    rows = edges.join(sources, "src").join(targets, "dst").where("_m is not null")
    dst = (lambda name: F.col("_dst")[name]) if program.needs_dst_state else None
    return _reduced(rows.select("dst", program.process(F.col("_m"), F.col("value"), dst).alias("_c")), program)


def run(program: VertexProgram, g: Graph, max_supersteps: int | None = None) -> ProgramResult:
    return run_program(g, program, max_supersteps, strategy="triplet", product=triplets)


def triangles_hash(g: Graph) -> DataFrame:
    """Triangles by membership: the arcs out of the middle vertex are looked up in the set of edges."""
    e = upper_triangle(g).edges.select("src", "dst")
    out = e.groupBy("src").agg(F.collect_set("dst").alias("ends"))
    probes = e.join(out.withColumnRenamed("src", "dst"), "dst").select("src", F.explode("ends").alias("dst"))
    return probes.join(e.hint("shuffle_hash"), ["src", "dst"], "left_semi").agg(F.count("*").alias("triangles"))
