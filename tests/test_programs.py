"""Worked micro-graph, invariants, baselines against the engine, edge cases."""

import random

import pytest
from pyspark.sql import functions as F

from vertexalg.algorithms import cf
from vertexalg.algorithms.bfs import bfs
from vertexalg.algorithms.components import components
from vertexalg.algorithms.degrees import in_degree, out_degree
from vertexalg.algorithms.pagerank import pagerank, pagerank_step
from vertexalg.algorithms.sssp import path_to, shortest_paths, sssp, sssp_run
from vertexalg.algorithms.triangles import triangle_count, triangle_list, triangles_per_vertex
from vertexalg.baselines import native, semiring, triplet, workfront, worklist
from vertexalg.algorithms.sssp import SsspProgram
from vertexalg.graphs import derive, prep
from vertexalg.graphs.graph import Graph

ARCS = [(1, 2, 4), (1, 3, 1), (3, 2, 2), (2, 4, 5), (3, 4, 8), (4, 5, 3), (5, 1, 1), (2, 5, 20)]


@pytest.fixture(scope="module")
def micro(spark):
    return Graph.from_edges(spark.createDataFrame(ARCS, "src long, dst long, w long"), value="w")


def values(df):
    return {r[0]: r[1] for r in df.collect()}


def test_trace_of_shortest_paths(micro):
    out = sssp_run(micro, 1)
    assert values(out.state.select("vid", "dist")) == {1: 0, 2: 3, 3: 1, 4: 8, 5: 11}
    assert [(s[1], s[3], s[4], s[5]) for s in out.steps] == [(1, 2, 2, 2), (2, 4, 3, 3), (3, 4, 3, 2), (2, 2, 2, 1), (1, 1, 1, 0)]


def test_degrees(micro):
    assert values(in_degree(micro)) == {1: 1, 2: 2, 3: 1, 4: 2, 5: 2}
    assert values(out_degree(micro)) == {1: 2, 2: 2, 3: 2, 4: 1, 5: 1}
    assert values(in_degree(micro, weighted=True))[5] == 23.0


def test_ranks(micro):
    assert values(pagerank(micro, iterations=1)) == pytest.approx({1: 1.0, 2: 1.0, 3: 0.575, 4: 1.0, 5: 1.425})
    two = {1: 1.36125, 2: 0.819375, 3: 0.575, 4: 0.819375, 5: 1.425}
    assert values(pagerank(micro, iterations=2)) == pytest.approx(two)
    assert values(pagerank_step(micro, pagerank(micro, iterations=1))) == pytest.approx(two)


def test_levels_paths_triangles_components(micro):
    assert values(bfs(micro, 1)) == {1: 0, 2: 1, 3: 1, 5: 1, 4: 2}
    assert path_to(shortest_paths(micro, 1), 5) == [1, 3, 2, 4, 5]
    assert triangle_count(micro).first()[0] == 4
    assert {tuple(r) for r in triangle_list(micro).collect()} == {(1, 2, 3), (1, 2, 5), (2, 3, 4), (2, 4, 5)}
    assert sum(values(triangles_per_vertex(micro)).values()) == 12
    assert triangle_count(micro, mode="symmetric").first()[0] == 4
    assert set(values(components(micro)).values()) == {1}


@pytest.mark.parametrize("strategy", ["rows_broadcast", "cols_shuffle", "grid"])
def test_strategies_agree(micro, strategy):
    assert values(sssp(micro, 1, strategy=strategy)) == {1: 0, 2: 3, 3: 1, 4: 8, 5: 11}
    assert triangle_count(micro, strategy=strategy).first()[0] == 4


def test_random_graph_against_baselines(spark):
    rng = random.Random(5)
    rows = [(rng.randrange(30), rng.randrange(30), rng.randrange(1, 9)) for _ in range(120)]
    g = prep.dedupe(prep.drop_self_loops(Graph.from_edges(spark.createDataFrame(rows, "src long, dst long, w long"), value="w")))
    source = min(r[0] for r in rows)
    want = values(sssp(g, source))
    assert values(sssp(g, source, frontier=False)) == want
    assert values(triplet.run(SsspProgram(source), g).state.select("vid", "dist")) == want
    assert values(semiring.sssp(g, source)) == want
    assert values(worklist.sssp(g, source, "bucket", 3)) == want
    assert values(worklist.sssp(g, source, "priority")) == want
    assert values(native.sssp(g, source)) == want
    assert values(workfront.sssp(g, source)) == want
    dist = {k: (v if v is not None else float("inf")) for k, v in want.items()}
    arcs = [tuple(r) for r in g.edges.collect()]
    assert all(dist[v] <= dist[u] + w for u, v, w in arcs)
    t = triangle_count(g).first()[0]
    for engine in ("spgemm", "hash", "join"):
        assert triangle_count(g, engine=engine).first()[0] == t
    assert triangle_count(g, order="degree").first()[0] == t


def test_goldens(spark, sf):
    g = derive.graph(spark, sf, "basket_chain")
    out = sssp_run(g, 0)
    total = out.state.agg(F.count("dist"), F.sum("dist"), F.max("dist")).first()
    assert (len(out.steps), sum(s[3] for s in out.steps), *total) == (9, 12105, 200, 2549, 23)
    assert [s[1] for s in out.steps] == [1, 31, 175, 141, 104, 62, 38, 13, 1]
    assert triangle_count(g).first()[0] == 11682
    ranks = pagerank(g).agg(F.round(F.sum("rank"), 4), F.round(F.max("rank"), 5)).first()
    assert tuple(ranks) == (200.0, 1.66228)


def test_gradient_descent(spark):
    rows = spark.createDataFrame([(u, i, 1 + (u * 3 + i * 5) % 5) for u in range(8) for i in range(6) if (u + i) % 3], "user long, item long, rating int")
    errors = [r["rmse"] for r in cf.cf_trace(rows, k=2, gamma=0.01, iterations=3).orderBy("round").collect()]
    assert errors == sorted(errors, reverse=True)
    a, b = cf.cf_gd(rows, k=2, iterations=2), semiring.cf_gd(rows, k=2, iterations=2)
    left, right = ({(r[0], r[1]): tuple(r)[2:] for r in m.factors.collect()} for m in (a, b))
    assert left.keys() == right.keys()
    assert all(left[k] == pytest.approx(right[k]) for k in left)


def test_sgd_equals_a_serial_replay(spark):
    import numpy as np

    data = [(u, i, float(1 + (u * 3 + i * 5) % 5)) for u in range(7) for i in range(5)]
    rows = spark.createDataFrame(data, "user long, item long, rating double")
    got = {(r[0], r[1]): r[2:] for r in cf.cf_sgd(rows, k=2, gamma=0.01, epochs=1, strata=2).factors.collect()}
    d = rows.select("user", "item", "rating", *(F.pmod(F.xxhash64(c, F.lit(42)), F.lit(2)).alias(b) for c, b in (("user", "ub"), ("item", "ib"))), F.xxhash64("user", "item", F.lit(42)).alias("h")).collect()
    start = lambda side, i: np.array([(1 + (i * 7 + k * 13 + side * 5) % 10) / 10 for k in range(2)])
    f = {(0, u): start(0, u) for u in range(7)} | {(1, i): start(1, i) for i in range(5)}
    for s in range(2):
        for r in sorted((r for r in d if (r["ub"] - r["ib"]) % 2 == s), key=lambda r: (r["h"], r["user"], r["item"])):
            p, q = f[0, r["user"]], f[1, r["item"]]
            e = r["rating"] - p @ q
            f[0, r["user"]], f[1, r["item"]] = p + 0.01 * (e * q - 0.05 * p), q + 0.01 * (e * p - 0.05 * q)
    assert all(got[k] == pytest.approx(tuple(v)) for k, v in f.items())


def test_edge_cases(spark):
    empty = Graph.from_edges(spark.createDataFrame([], "src long, dst long"), vertices=spark.range(3).withColumnRenamed("id", "vid"))
    assert values(in_degree(empty)) == {0: 0, 1: 0, 2: 0}
    assert values(pagerank(empty, iterations=1)) == pytest.approx({0: 0.15, 1: 0.15, 2: 0.15})
    assert triangle_count(empty).first()[0] == 0
    assert values(sssp(empty, 1)) == {0: None, 1: 0, 2: None}
    loop = Graph.from_edges(spark.createDataFrame([(1, 1)], "src long, dst long"))
    assert prep.drop_self_loops(loop).edges.count() == 0
    weights = lambda rows: Graph.from_edges(spark.createDataFrame(rows, "src long, dst long, w long"), value="w")
    assert values(sssp(weights([(1, 2, 5), (2, 3, -3), (1, 3, 4)]), 1)) == {1: 0, 2: 5, 3: 2}
    assert values(sssp(weights([(1, 2, 0), (2, 1, 0)]), 1)) == {1: 0, 2: 0}
    with pytest.raises(ValueError, match="negative"):
        sssp(weights([(1, 2, 1), (2, 1, -2)]), 1)
    with pytest.raises(ValueError, match="weight"):
        sssp(weights([(1, 2, None)]), 1)
    with pytest.raises(ValueError, match="source"):
        sssp(weights([(1, 2, 1)]), 9)
    with pytest.raises(ValueError, match="bipartite"):
        prep.check_bipartite(spark.createDataFrame([(0, 2)], "src long, dst long"))
