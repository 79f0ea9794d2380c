"""Graphs and programs from SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from vertexalg.algorithms.bfs import bfs
from vertexalg.algorithms.components import components
from vertexalg.algorithms.degrees import in_degree, out_degree
from vertexalg.algorithms.pagerank import pagerank
from vertexalg.algorithms.sssp import sssp
from vertexalg.algorithms.triangles import triangle_count
from vertexalg.graphs.graph import Graph

_PROGRAMS = {"pagerank": pagerank, "bfs": bfs, "sssp": sssp, "components": components, "triangles": triangle_count, "in_degree": in_degree, "out_degree": out_degree}
_GRAPHS: dict[str, Graph] = {}


def register_graph(spark: SparkSession, name: str, g: Graph) -> None:
    """Views name_edges and name_vertices, and the graph's name for run_sql_program."""
    g.edges.createOrReplaceTempView(f"{name}_edges")
    g.vertices.createOrReplaceTempView(f"{name}_vertices")
    _GRAPHS[name] = g


def run_sql_program(name: str, program: str, **options) -> DataFrame:
    """Runs a program on a registered graph; the result is also the view name_program."""
    out = _PROGRAMS[program](_GRAPHS[name], **options)
    out.createOrReplaceTempView(f"{name}_{program}")
    return out


def bfs_recursive_sql(spark: SparkSession, name: str, root: int, depth: int) -> DataFrame:
    """Levels up to depth by a recursive query (small graphs: it keeps every walk)."""
    return spark.sql(
        f"with recursive w(vid, level) as (select cast({root} as bigint), 0 union all select e.dst, w.level + 1 from w join {name}_edges e on e.src = w.vid where w.level < {depth}) "
        "select vid, min(level) as level from w group by vid"
    )
