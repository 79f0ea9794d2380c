"""Supersteps on columns: chained jobs, hubs cut into parts, absent columns, and what a plan exchanges."""

import pytest
from pyspark.sql import functions as F

from vertexalg.algorithms.bfs import BfsProgram
from vertexalg.algorithms.components import ComponentsProgram
from vertexalg.algorithms.pagerank import PageRankProgram, with_out_degree
from vertexalg.algorithms.sssp import SsspProgram
from vertexalg.conf import written
from vertexalg.engine import chainable, init_state, run_program
from vertexalg.graphs import derive
from vertexalg.graphs.graph import Graph
from vertexalg.matrix import columns
from vertexalg.plans.inspect import exchanges
from vertexalg.program import Reduce


def rows(df):
    return sorted(map(tuple, df.collect()), key=repr)


@pytest.mark.parametrize("strategy", ["columns", "rows_broadcast", "cols_shuffle"])
@pytest.mark.parametrize("chain", [1, 3, 8])
def test_chains_tell_the_same(spark, sf, strategy, chain):
    g = derive.graph(spark, sf, "basket_chain")
    for program in (SsspProgram(0), PageRankProgram(), ComponentsProgram(), SsspProgram(0, frontier=False), SsspProgram(0, parents=True)):
        bound = 5 if isinstance(program, PageRankProgram) else None
        h = with_out_degree(g) if bound else g
        if program.activation == "all" and not bound:
            bound = 20
        want, got = run_program(h, program, bound, "cols_shuffle", chain=1), run_program(h, program, bound, strategy, chain=chain)
        assert [s[:6] for s in got.steps] == [s[:6] for s in want.steps] and got.converged == want.converged
        shown = ("vid", *(F.round(c, 9) if c == "rank" else F.col(c) for c in program.state), "active")
        assert rows(got.state.select(*shown)) == rows(want.state.select(*shown))


def test_hubs_and_strangers(spark, monkeypatch):
    """A hub's column is cut into parts; edges from or to ids that are no vertices bring nothing; vertices without edges stay."""
    monkeypatch.setattr(columns, "CELLS", 7)
    edges = [(0, i, i) for i in range(1, 60)] + [(i, 0, 1) for i in range(1, 60, 2)] + [(5, 999, 1), (998, 6, 1)]
    vertices = spark.createDataFrame([(i,) for i in range(62)], "vid long")
    g = Graph.from_edges(spark.createDataFrame(edges, "src long, dst long, value long"), value="value", vertices=vertices)
    got = run_program(g, SsspProgram(0))
    assert rows(got.state.select("vid", "dist")) == sorted([(i, i) for i in range(60)] + [(60, None), (61, None)], key=repr)
    assert columns.columns(g, "out").agg(F.max(F.size("_cells"))).first()[0] <= 8 + 8
    assert columns.columns(g, "out").select("vid").distinct().count() == 62
    none = Graph.from_edges(spark.createDataFrame([], "src long, dst long"), vertices=vertices)
    assert run_program(none, ComponentsProgram()).state.where("label = vid").count() == 62


def test_one_exchange_a_superstep(spark, sf):
    g = derive.graph(spark, sf, "basket_chain")
    program = SsspProgram(0)
    columns.columns(g).count()
    state = written(init_state(g, program)).repartition(int(spark.conf.get("spark.sql.shuffle.partitions")), "vid")
    once = columns.superstep(g, state, program, program.state, F.col("active")).select("vid", F.col("red").alias("dist"), F.lit(True).alias("active"))
    twice = columns.superstep(g, once, program, program.state, F.col("active"))
    base = exchanges(state)
    assert exchanges(once) - base == 1 and exchanges(twice) - base == 2


def test_what_is_chained():
    assert chainable(SsspProgram(0)) and chainable(PageRankProgram()) and chainable(BfsProgram([0]))
    assert not chainable(PageRankProgram(tol=1e-3)) and not chainable(SsspProgram(0, frontier=False))


def test_columns_hold_no_destinations(spark, sf):
    g = derive.graph(spark, sf, "trade")
    with pytest.raises(ValueError, match="destinations"):
        run_program(g, BfsProgram([3], prune_visited=True), strategy="columns")


@pytest.mark.parametrize("strategy", ["auto", "rows_broadcast", "cols_shuffle"])
def test_reductions_that_gather(spark, sf, strategy):
    """A merge of one's own, folded in parts, and a Python function of all contributions give what the built-in one gives."""
    g = derive.graph(spark, sf, "basket_chain")
    want = rows(run_program(g, SsspProgram(0)).state.select("vid", "dist"))

    class Folded(SsspProgram):
        def reduce(self):
            return Reduce.custom(lambda a, b: F.least(a, b), F.lit(None).cast("long"), salts=3)

    class Grouped(SsspProgram):
        def reduce(self):
            return Reduce.grouped(lambda values: values.min(), "long")

    for program in (Folded(0), Grouped(0)):
        got = run_program(g, program, strategy=strategy)
        assert rows(got.state.select("vid", "dist")) == want and sum(s[3] for s in got.steps) == 12105
    with pytest.raises(ValueError, match="Python"):
        run_program(g, Grouped(0), strategy="columns")
