"""Ranks by residuals: blocks settle before anything is exchanged."""

import pytest

from vertexalg.algorithms.pagerank import with_out_degree
from vertexalg.baselines import worklist
from vertexalg.conf import EngineConf
from vertexalg.engine import run_program
from vertexalg.graphs import derive
from vertexalg.graphs.graph import Graph


def ranks(state):
    return {r.vid: r["rank"] + r.residual for r in state.collect()}


def test_blocks_settle(spark, sf):
    g = derive.graph(spark, sf, "trade").written()
    whole = run_program(with_out_degree(g), worklist.ResidualProgram(0.15, 1e-6), 200)
    want = ranks(whole.state)
    one, exchanges = worklist.residual_rounds(g, eps=1e-6)
    assert exchanges == 1 and ranks(one) == pytest.approx(want, abs=2e-6 / 0.15)
    three, exchanges = worklist.residual_rounds(g, eps=1e-6, blocks=3)
    assert 1 < exchanges <= len(whole.steps) and ranks(three) == pytest.approx(want, abs=2e-6 / 0.15)
    assert all(r.residual <= 1e-6 for r in three.collect())
    stopped, exchanges = worklist.residual_rounds(g, eps=1e-6, max_supersteps=2, blocks=3)
    assert exchanges == 2 and any(r.residual > 1e-6 for r in stopped.collect())
    g.unpersist()


def test_blocks_follow_size(spark, monkeypatch):
    edges = spark.createDataFrame([(i, i + 1) for i in range(10)], "src long, dst long")
    assert worklist.settled_blocks(Graph.from_edges(edges)) == 1
    monkeypatch.setattr(worklist, "EDGES", 4)
    assert worklist.settled_blocks(Graph.from_edges(edges)) == 3
    assert worklist.settled_blocks(Graph.from_edges(edges, conf=EngineConf(partitions=5))) == 5
    assert worklist.settled_blocks(Graph.from_edges(edges.limit(0))) == 1


@pytest.mark.parametrize("blocks", [1, 4])
def test_odd_edges(spark, blocks):
    """Loops, arcs twice, ends that are no vertices, a vertex alone, a sink."""
    arcs = [(1, 1), (1, 2), (1, 2), (2, 3), (3, 1), (2, 99), (98, 1), (3, 5)]
    vertices = spark.createDataFrame([(v,) for v in (1, 2, 3, 4, 5)], "vid long")
    g = Graph.from_edges(spark.createDataFrame(arcs, "src long, dst long"), vertices=vertices)
    want = dict.fromkeys((1, 2, 3, 4, 5), 0.15)
    for _ in range(300):
        want = {v: 0.15 + 0.85 * sum(want[a] / sum(x == a for x, _ in arcs) for a, b in arcs if b == v and a in want) for v in want}
    got = {r.vid: r["rank"] for r in worklist.pagerank_residual(g, eps=1e-9, blocks=blocks).collect()}
    assert got == pytest.approx(want, abs=1e-7)
    none = Graph.from_edges(spark.createDataFrame([], "src long, dst long"), vertices=vertices)
    assert {r.vid: r["rank"] for r in worklist.pagerank_residual(none, blocks=blocks).collect()} == dict.fromkeys((1, 2, 3, 4, 5), 0.15)
