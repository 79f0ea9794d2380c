"""Rows that hold collections stay small, however large the tables are."""

from pyspark.sql import functions as F

from vertexalg.matrix import dcsc
from vertexalg.operators import relational


def test_maps_of_degrees(spark):
    degree = spark.range(-500, 20_000).select(F.col("id").alias("part"), (F.col("id") % 7).alias("degree"))
    row = relational.degree_maps(degree).agg(F.max(F.size("m")).alias("most"), F.sum(F.size("m")).alias("all")).first()
    assert row["most"] <= 64 and row["all"] == 20_500


def test_blocks_by_edges(spark, monkeypatch):
    monkeypatch.setattr(dcsc, "ENTRIES", 1000)
    edges = spark.range(20_000).select((F.col("id") % 700).alias("src"), F.pmod(F.col("id") * 7919, F.lit(9973)).alias("dst"), F.col("id").alias("value"))
    d = dcsc.to_dcsc(edges).persist()
    assert d.count() == 20 and d.agg(F.max(F.size("vals"))).first()[0] < 3000
    assert sorted(map(tuple, dcsc.from_dcsc(d).collect())) == sorted(map(tuple, edges.collect()))
