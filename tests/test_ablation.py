"""The ablation tells all bars or none, and makes no run that its frame does not ask for."""

import threading

import pytest

from vertexalg.measures import ablation, experiments


@pytest.fixture
def bars(spark, monkeypatch):
    """Bars as they are run: (bar, algorithm, bars at work, whether classes are shared)."""
    monkeypatch.setattr(experiments, "OPTIMISED", (("rank", "trade"), ("sssp", "trade")))
    monkeypatch.setattr(experiments, "_TOLD", {})
    out, plain, lock, at_work = [], ablation.bar, threading.Lock(), []

    def bar(name, g, algorithm, *more):
        with lock:
            at_work.append(name)
            out.append((name, algorithm, len(at_work), spark.conf.get("spark.sql.codegen.useIdInClassName", "true") == "false"))
        try:
            return plain(name, g, algorithm, *more)
        finally:
            with lock:
                at_work.remove(name)

    monkeypatch.setattr(ablation, "bar", bar)
    return out


EVERY = {(b, a) for b in ablation.BARS for a in ("rank", "sssp")}


def test_agreement_takes_no_time(spark, sf, bars):
    rows = experiments.ablation_agreement(spark, sf).collect()
    assert {(r.bar, r.algorithm) for r in rows} == EVERY and all(r.agrees for r in rows)
    assert len(bars) == 10 and max(b[2] for b in bars) > 1 and all(b[3] for b in bars)
    assert experiments.ablation_agreement(spark, sf).count() == 10 and len(bars) == 10


def test_times_are_taken_alone_and_whole(spark, sf, bars, monkeypatch):
    plain, broken = ablation.bar, [True]

    def bar(name, *more):
        if name == "parallel" and broken:
            raise OSError(broken.pop())
        return plain(name, *more)

    monkeypatch.setattr(ablation, "bar", bar)
    with pytest.raises(OSError):
        experiments.ablation_rows(spark, sf)
    bars.clear()
    rows = experiments.ablation_rows(spark, sf).collect()
    assert {(r.bar, r.algorithm) for r in rows} == EVERY and all(r.agrees and r.gain > 0 for r in rows)
    assert len(bars) == 10 and all(b[2] == 1 for b in bars)
    assert experiments.ablation_agreement(spark, sf).count() == 10 and len(bars) == 10
