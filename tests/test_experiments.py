"""The experiments make no run that their frame does not ask for, and none twice."""

import pytest

from vertexalg.measures import experiments


@pytest.fixture
def made(spark, monkeypatch):
    """(system, algorithm) of the runs made on small data sets, told as they are made."""
    monkeypatch.setattr(experiments, "DATASETS", {"pr": ("trade",), "tc": ("trade", "basket_chain"), "sssp": ("trade",)})
    monkeypatch.setattr(experiments, "_SECONDS", {})
    monkeypatch.setattr(experiments, "_FOUND", {})
    out, plain = [], experiments.runs()

    def noted(key, prepare, run):
        return prepare, lambda p, ready: (out.append((*key, p.name)), run(p, ready))[1]

    monkeypatch.setattr(experiments, "runs", lambda: {k: noted(k, *v) for k, v in plain.items()})
    return out


def test_runs_asked_for(spark, sf, made):
    before = spark.conf.get("spark.sql.codegen.useIdInClassName", None)
    told = {r.algorithm for r in experiments.against_native(spark, sf).collect()}
    assert told == {"pr", "tc", "overall"}
    want = [(s, a, n) for a, n, times in (("pr", "trade", 2), ("tc", "trade", 2), ("tc", "basket_chain", 1)) for s in ("engine", "native") for _ in range(times)]
    assert sorted(made) == sorted(want)  # the first data set of an algorithm twice, as its code is compiled then
    made.clear()
    rows = experiments.agreement(spark, sf).collect()
    assert len(rows) == 20 and all(r.agrees for r in rows)
    assert len(made) == len(set(made)) == 14 and not set(made) & set(want)
    made.clear()
    assert experiments.agreement(spark, sf).count() == 20 and not made
    assert spark.conf.get("spark.sql.codegen.useIdInClassName", None) == before


def test_edges_are_derived_once(spark, sf, monkeypatch):
    names = []
    monkeypatch.setattr(experiments, "written", lambda df, name="step", kept=experiments.written: (names.append(df.columns), kept(df, name))[1])
    p = experiments.load(spark, sf, "trade")
    assert names == [["src", "dst", "value"], ["vid"]] and p.base.vertices.count() == 25
    assert p.both is p.both and p.both.vertices is p.base.vertices and len(names) == 3
