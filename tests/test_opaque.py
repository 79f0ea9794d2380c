"""Programs whose process is a Python function of rows."""

from vertexalg.algorithms.sssp import SsspProgram, sssp
from vertexalg.engine import run_program
from vertexalg.graphs import derive
from vertexalg.graphs.graph import Graph
from vertexalg.measures.ablation import opaque


def test_rows_without_a_message(spark):
    """A column holds its own vertex too, so the function meets rows that carry no message and rows that carry no value."""
    g = Graph.from_edges(spark.createDataFrame([(1, 2, 3), (2, 3, 4), (4, 1, 1)], "src long, dst long, value long"), value="value")
    for kind in ("udf", "arrow"):
        assert {r.vid: r.dist for r in run_program(g, opaque(SsspProgram(1), kind)).state.collect()} == {1: 0, 2: 3, 3: 7, 4: None}


def test_given_tables(spark, sf):
    g = derive.graph(spark, sf, "trade")
    assert sorted(map(tuple, run_program(g, opaque(SsspProgram(0))).state.select("vid", "dist").collect())) == sorted(map(tuple, sssp(g, 0).collect()))
