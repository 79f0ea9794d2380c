"""Queries that leave nothing out: frequent lines, every vector."""

import numpy as np
import pytest

from vertexalg.algorithms.components import components
from vertexalg.graphs import derive
from vertexalg.measures import experiments
from vertexalg.operators import relational
from vertexalg.operators.knn import nearest_vectors


@pytest.fixture
def lines(spark, tmp_path):
    """60 documents of one line, of which 10 share a second one; the least of them is of bad quality."""
    docs = [(i, "a line that all of these share\n" + ("  a line of a few documents" if i % 6 == 1 else f"short {i}")) for i in range(60)] + [(100, "a line of one document only"), (101, None)]
    spark.createDataFrame(docs, "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(i, int(i > 0)) for i in (*range(60), 100)], "doc_id long, quality int").write.parquet(str(tmp_path / "labels.parquet"))
    return str(tmp_path)


def test_frequent_lines(spark, lines):
    few = [i for i in range(60) if i % 6 == 1]
    want = {(1, i) for i in few[1:]} | {(i, 1) for i in few[1:]} | {(0, i) for i in range(1, 60)} | {(i, 0) for i in range(1, 60)}
    got = [(r.src, r.dst) for r in derive.docshare(spark, lines).collect()]
    assert len(got) == len(want) and set(got) == want
    whole = {tuple(r) for r in components(derive.graph(spark, lines, "docshare")).collect()}
    assert whole == {(i, 0) for i in range(60)} | {(100, 100), (101, 101)}
    good = {tuple(r) for r in relational.docshare_quality(spark, lines).collect()}
    assert good == {(i, 1) for i in range(1, 60)} | {(100, 100)}


def test_every_vector(spark, sf):
    rows = spark.read.parquet(f"{sf}/embeddings.parquet").collect()
    ids, x = np.array([r.vec_id for r in rows]), np.array([r.embedding for r in rows], float)
    unit = x / np.sqrt((x * x).sum(axis=1))[:, None]
    c = np.round(unit @ unit.T, 9)
    c[ids[:, None] == ids[None]] = -9
    want = {(int(ids[i]), int(ids[j])): c[i, j] for i in range(len(ids)) for j in np.lexsort((ids, -c[i]))[:8]}
    got = {(r.src, r.dst): r.value for r in relational.knn(spark, sf).collect()}
    assert got.keys() == want.keys() and len(got) == 8 * len(ids)
    assert all(got[k] == pytest.approx(want[k], abs=2e-6) for k in got)


def test_vector_grid(spark):
    rng = np.random.default_rng(4)
    x = rng.integers(-2, 3, (70, 4)).astype(float)  # many ties and some zero vectors
    rows = [(i, [float(v) for v in x[i]]) for i in range(70)] + [(3, [float(v) for v in x[3]]), (80, None), (81, [1.0, None, 1.0, 1.0]), (82, [float("nan")] * 4), (None, [1.0] * 4), (83, [1.0]), (84, [2.0])]
    length = np.sqrt((x * x).sum(axis=1))
    want = {(83, 84), (84, 83)}
    for i in np.flatnonzero(length):
        c = np.round(x @ x[i] / np.where(length > 0, length, 1) / length[i], 9)
        c[(length == 0) | (np.arange(70) == i)] = -9
        want |= {(int(i), int(j)) for j in np.lexsort((np.arange(70), -c))[:8]}
    got = [(r.src, r.dst) for r in nearest_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), 8, block=16).collect()]
    assert len(got) == len(want) and set(got) == want


def test_systems_agree(spark, tmp_path, sf, monkeypatch):
    """Every system has a run of its own for every algorithm, and on a small graph all give the engine's result."""
    assert {(s, a) for s in experiments.SYSTEMS for a in experiments.DATASETS} == set(experiments.runs())
    monkeypatch.setattr(experiments, "DATASETS", {"pr": ("trade",), "bfs": ("trade",), "tc": ("trade",), "sssp": ("trade",), "cf": ("synth_rating",)})
    rows = experiments.compare(spark, sf).collect()
    assert len(rows) == 25 and all(r.agrees for r in rows)
    assert {r.system for r in experiments.against_frameworks(spark, sf).collect()} == {"triplet", "semiring", "worklist"}
    told = {r.algorithm: r.slowdown for r in experiments.against_native(spark, sf).collect()}
    assert set(told) == {"pr", "bfs", "tc", "cf", "overall"} and all(v > 0 for v in told.values())


def test_disagreement_is_told(spark):
    frame = lambda rows: spark.createDataFrame(rows, "vid long, rank double")
    assert experiments.agrees("triplet", "pr", frame([(1, 0.5), (2, 1.0)]), frame([(2, 1.0), (1, 0.5 + 1e-9)]))
    assert not experiments.agrees("triplet", "pr", frame([(1, 0.5)]), frame([(1, 0.51)]))
    assert not experiments.agrees("triplet", "pr", frame([(1, 0.5)]), frame([(1, 0.5), (2, 1.0)]))
    assert not experiments.agrees("triplet", "pr", frame([(1, 0.5), (2, None)]), frame([(1, 0.5), (2, 1.0)]))
    whole = lambda rows: spark.createDataFrame(rows, "vid long, dist long")
    assert experiments.agrees("triplet", "sssp", whole([(1, None)]), whole([(1, None)])) and not experiments.agrees("triplet", "sssp", whole([(1, 2)]), whole([(1, 3)]))


def test_native_descent_is_the_same(spark, sf):
    from vertexalg.algorithms import cf
    from vertexalg.baselines import native

    ratings = derive.ratings(spark, sf)
    a, b = (sorted(map(tuple, m.factors.collect())) for m in (cf.cf_sgd(ratings, k=4, epochs=2, strata=3), native.cf(ratings, k=4, epochs=2, strata=3)))
    assert len(a) == len(b) and all(x == pytest.approx(y, abs=1e-12) for x, y in zip(a, b, strict=True))


def test_followers_over_buckets(spark):
    rng = np.random.default_rng(5)
    rows = [(int(k), int(t), i) for i, (k, t) in enumerate(zip(rng.integers(0, 3, 80), rng.integers(0, 60, 80), strict=True))]
    got = {r["id"]: r["next"] and r["next"]["id"] for r in derive.followers(spark.createDataFrame(rows, "k long, at long, id long"), ("k",), "at", "id", 7).collect()}
    want = {}
    for k in range(3):
        mine = sorted((t, i) for g, t, i in rows if g == k)
        want |= {i: mine[n + 1][1] if n + 1 < len(mine) else None for n, (_, i) in enumerate(mine)}
    assert got == want
