"""The graph of pages that share a path: by classes, it gives what the plain programs give on all pairs."""

import random

import pytest
from pyspark.sql import functions as F

from vertexalg.algorithms.bfs import bfs
from vertexalg.algorithms.components import components
from vertexalg.algorithms.degrees import in_degree, out_degree
from vertexalg.algorithms.pagerank import pagerank
from vertexalg.algorithms.triangles import clustering, triangle_count, triangles_per_vertex
from vertexalg.graphs import derive, twins
from vertexalg.registry import QUERIES, root_of


@pytest.fixture(scope="module")
def pages(spark, tmp_path_factory):
    """Twins, pages of one path only, pages without a path, an id that two rows have, an id that is null, no html."""
    rng = random.Random(3)
    sets = [rng.sample("abcdefgh", rng.randint(1, 3)) for _ in range(7)] + [["x"], ["y"], ["y", "z"], []]
    html = lambda names: "".join(f'<a href="/{n}">{n}</a>' for n in names) + '<a href="http://w/">w</a>'
    rows = [(i, html(sets[i % len(sets)])) for i in range(3, 40)] + [(5, html("q")), (50, html("q")), (60, None)]
    folder = str(tmp_path_factory.mktemp("pages"))
    spark.createDataFrame(rows, "page_id long, html string").write.parquet(f"{folder}/pages.parquet")
    return folder


@pytest.fixture(scope="module")
def whole(spark, pages):
    """The same graph with all pairs spelled out."""
    g = derive.graph(spark, pages, "colink").written("colink")
    g.vertices = g.vertices.distinct()
    return g


def rows_of(df):
    return sorted(tuple(round(v, 9) if isinstance(v, float) else (v is not None, v or 0) for v in r) for r in df.collect())


@pytest.mark.parametrize("name", ["degree", "rank", "levels", "components", "triangle_count", "triangles_per_vertex", "clustering", "edge_count"])
def test_as_on_pairs(spark, pages, whole, name):
    plain = {
        "degree": in_degree, "rank": pagerank, "levels": lambda g: bfs(g, root_of(g.edges)), "components": components, "triangle_count": triangle_count,
        "triangles_per_vertex": triangles_per_vertex, "clustering": clustering, "edge_count": lambda g: g.edges.agg(F.count("*").alias("edges")),
    }
    got, want = getattr(twins, name)(twins.twins(spark, pages)), plain[name](whole)
    assert got.dtypes == want.select(*got.columns).dtypes
    assert rows_of(got) == rows_of(want.select(*got.columns))
    if name == "degree":
        assert rows_of(got) == rows_of(out_degree(whole))


def test_pairs_hold_every_tie(spark, pages, whole):
    rows = [tuple(r) for r in twins.pairs(twins.twins(spark, pages)).collect()]
    assert len(rows) == len(set(rows))
    cls = {v: c for v, c, n in rows if n == 0}
    links = {(a, b) for a, b, n in rows if n == 1}
    tied = {(v, w) for v in cls for w in cls if v != w and (cls[v] == cls[w] or (cls[v], cls[w]) in links)}
    assert tied == {(r.src, r.dst) for r in whole.edges.collect()}


@pytest.mark.parametrize("name", ["tc_per_vertex", "clustering", "pr_colink", "tc_colink", "bfs_colink", "changed_vertices", "unreached", "components_colink", "graph_colink", "indegree_colink", "outdegree_colink"])
def test_no_pairs_are_made(spark, pages, monkeypatch, name):
    def spelled(s, d):
        raise AssertionError("pairs of pages are spelled out")

    monkeypatch.setitem(derive._EDGES, "colink", spelled)
    monkeypatch.setattr(derive, "colink", spelled)
    assert QUERIES[name](spark, pages).count() > 0


def test_no_ties(spark, tmp_path):
    spark.createDataFrame([(1, "no link"), (2, None)], "page_id long, html string").write.parquet(f"{tmp_path}/pages.parquet")
    t = twins.twins(spark, str(tmp_path))
    assert rows_of(twins.levels(t)) == [((True, 1), (False, 0)), ((True, 2), (False, 0))]
    assert [tuple(r) for r in twins.rank(t).orderBy("vid").collect()] == [(1, 0.15), (2, 0.15)]
    assert [tuple(r) for r in twins.components(t).orderBy("vid").collect()] == [(1, 1), (2, 2)]
    assert twins.triangle_count(t).first()[0] == 0 and twins.pairs(t).count() == 0 and twins.edge_count(t).first()[0] == 0
