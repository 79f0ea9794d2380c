"""Experiments in sessions that fit their data sets, and on no more numbers of cores than a frame names."""

import pytest

from vertexalg.measures import experiments


def test_partitions_follow_size(spark, sf, monkeypatch):
    names = ("spark.sql.shuffle.partitions", "spark.sql.adaptive.enabled", "spark.sql.codegen.useIdInClassName")
    before = {k: spark.conf.get(k, None) for k in names}
    spark.conf.set("spark.sql.shuffle.partitions", "200")
    try:
        p = experiments.fitted(spark, sf, "trade")
        assert p.base.spark.conf.get("spark.sql.shuffle.partitions") == "1" and p.base.persist("columns")._layouts["columns out"].rdd.getNumPartitions() == 1
        p.release()
        monkeypatch.setattr(experiments, "EDGES", 100)
        n = int(experiments.fitted(spark, sf, "trade").base.spark.conf.get("spark.sql.shuffle.partitions"))
        assert 1 < n == -(-p.base.edges.count() // 100)
        monkeypatch.setattr(experiments, "EDGES", 1)
        assert experiments.fitted(spark, sf, "trade").base.spark.conf.get("spark.sql.shuffle.partitions") == "200"
        assert spark.conf.get("spark.sql.shuffle.partitions") == "200"
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before["spark.sql.shuffle.partitions"])
    assert {k: spark.conf.get(k, None) for k in names} == before


@pytest.mark.parametrize("told", [False, True])
def test_one_core_alone(spark, monkeypatch, told):
    asked, kept = [], {}
    monkeypatch.setattr(experiments, "_TOLD", kept)

    def rows(s, d, cores):
        asked.append(cores)
        return s.createDataFrame([(x, "pr", "trade", n, t, 1.0) for x, t in (("engine", 1.0), ("triplet", 3.0)) for n in cores], "system string, algorithm string, dataset string, cores int, seconds double, speedup double")

    if told:
        kept[experiments._key(spark, "d", "scaling", experiments.CORES)] = []
    monkeypatch.setattr(experiments, "scaling_rows", rows)
    out = {(r.system, r.algorithm): r.speedup for r in experiments.single_thread(spark, "d").collect()}
    assert out == pytest.approx({("triplet", "pr"): 3.0, ("triplet", "overall"): 3.0}) and asked == [experiments.CORES if told else (1,)]
