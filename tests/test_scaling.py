"""Scaling is measured in the caller's session."""

import subprocess

from vertexalg.measures import experiments


def test_tasks_and_settings(spark, sf):
    before = {k: spark.conf.get(k, None) for k in experiments._TASKS}
    with experiments.on_cores(spark, 3) as conf:
        assert conf.blocks(spark) == 3
        assert spark.read.parquet(f"{sf}/lineitem.parquet").repartition("l_orderkey").rdd.getNumPartitions() <= 3
    assert {k: spark.conf.get(k, None) for k in experiments._TASKS} == before


def test_no_other_process(spark, sf, monkeypatch):
    def started(*args, **options):
        raise AssertionError("a process is started")

    monkeypatch.setattr(subprocess, "run", started)
    monkeypatch.setattr(experiments, "SYSTEMS", ("engine", "triplet"))
    rows = experiments.scaling_rows(spark, sf, cores=(1, 2)).collect()
    assert {(r.system, r.algorithm, r.cores) for r in rows} == {(s, a, n) for s in ("engine", "triplet") for a in ("pr", "sssp") for n in (1, 2)}
    assert all(r.seconds > 0 and (r.cores == 2 or r.speedup == 1) for r in rows)
