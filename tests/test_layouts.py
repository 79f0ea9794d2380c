"""Matrix and vector layouts, plans, measures, sources, streams."""

import random

import pytest
from pyspark.sql import functions as F

from vertexalg.algorithms.sssp import SsspProgram, sssp
from vertexalg.conf import EngineConf
from vertexalg.engine import init_state
from vertexalg.graphs import derive
from vertexalg.graphs.graph import Graph
from vertexalg.graphs.rmat import RMAT_RANK, rmat, rmat_edges
from vertexalg.matrix.blocks import partition_rows, salted
from vertexalg.matrix.dcsc import block_product, dcsc_column, from_dcsc, to_dcsc
from vertexalg.matrix.semirings import MIN_PLUS
from vertexalg.matrix.spmv import generalized_spmv, spmv
from vertexalg.matrix.strategies import choose
from vertexalg.matrix.vectors import BitmapVector, PairVector, same
from vertexalg.measures.timing import gains, geometric_mean, speedup
from vertexalg.plans.inspect import exchanges, operators, python_operators
from vertexalg.program import Reduce, VertexProgram


@pytest.fixture(scope="module")
def edges(spark):
    rng = random.Random(3)
    rows = {(rng.randrange(40), rng.randrange(200)): rng.randrange(9) for _ in range(150)}
    rows[7, 2**33] = 4
    return spark.createDataFrame([(a, b, w) for (a, b), w in rows.items()], "src long, dst long, value long")


def rows_of(df):
    return sorted(tuple(r) for r in df.collect())


def test_dcsc(edges):
    d = to_dcsc(edges, 5)
    assert rows_of(from_dcsc(d)) == rows_of(edges)
    for r in d.collect():
        assert r["col_ids"] == sorted(set(r["col_ids"]))
        assert r["col_ptr"][0] == 0 and r["col_ptr"][-1] == len(r["row_ids"]) == len(r["vals"]) and len(r["col_ptr"]) == len(r["col_ids"]) + 1
    found = d.select(F.explode(dcsc_column(7)).alias("e")).select("e.row", "e.value")
    assert rows_of(found) == rows_of(edges.where("src = 7").select("dst", "value"))


def test_block_kernel(spark, edges):
    x = spark.createDataFrame([(7, 1), (11, 5), (999, 0)], "vid long, value long")
    want = spmv(Graph.from_edges(edges, value="value"), x, *MIN_PLUS)
    assert rows_of(block_product(to_dcsc(edges, 4), x).select("vid", F.col("value").cast("long"))) == rows_of(want)
    with pytest.raises(ValueError, match="larger"):
        block_product(to_dcsc(edges, 4), x, limit=8)


def test_vectors(spark, edges):
    pairs = PairVector(spark.createDataFrame([(i, i % 100) for i in (0, 1, 63, 64, 127, 2**33)], "vid long, val long"))
    bits = pairs.to_bitmap()
    assert same(bits.to_pairs(), pairs) and bits.count() == 6
    assert rows_of(bits.keep(edges, "dst").select("src", "dst")) == rows_of(pairs.keep(edges, "dst").select("src", "dst"))
    assert not same(pairs, PairVector(pairs.df.where("vid > 0")))


def test_partitions(edges):
    for balance in ("hash", "edges"):
        p = partition_rows(edges, 4, "dst", 2, balance)
        assert p.rdd.getNumPartitions() == 8
        assert p.count() == edges.count()
        where = p.select("dst", F.spark_partition_id().alias("p")).distinct().groupBy("dst").count()
        assert where.where("count > 1").isEmpty()
    assert rows_of(salted(edges, "dst", "value", F.sum)) == rows_of(edges.groupBy("dst").agg(F.sum("value")))


def test_plans(spark, edges):
    g = Graph.from_edges(edges, value="value", conf=EngineConf(partitions=4)).persist("dst").persist("src")
    x = spark.createDataFrame([(7, 1)], "vid long, _m long")
    program = SsspProgram(7)
    near = generalized_spmv(g, x, program, strategy="rows_broadcast")
    near.collect()
    assert exchanges(near) == 0 and operators(near)["BroadcastHashJoin"] == 1 and python_operators(near) == 0
    far = generalized_spmv(g, x, program, strategy="cols_shuffle")
    assert operators(far)["SortMergeJoin"] + operators(far)["ShuffledHashJoin"] + operators(far)["BroadcastHashJoin"] == 1  # no join on the destination
    g.unpersist()


def test_chooser():
    assert choose(100, 16, 1 << 20) == "rows_broadcast"
    assert choose(None, 16, 1 << 20) == "cols_shuffle"
    assert choose(10**9, 16, 1 << 20, blocks=256, needs_dst_state=True) == "grid"
    assert choose(10**9, 16, 1 << 20, blocks=256) == "cols_shuffle"


def test_reductions(spark, edges):
    class Both(VertexProgram):
        direction = "both"

        def __init__(self, how):
            self.how = how

        def process(self, m, e, dst):
            return e

        def reduce(self):
            return self.how

    g = Graph.from_edges(edges, value="value")
    x = g.vertices.select("vid", F.lit(1).alias("_m"))
    ends = edges.select(F.col("dst").alias("vid"), "value").unionByName(edges.select(F.col("src").alias("vid"), "value"))
    for how, fold in ((Reduce.min(), F.min), (Reduce.max(), F.max), (Reduce.sum(), F.sum), (Reduce.count(), F.count), (Reduce.custom(lambda a, b: F.greatest(a, b), F.lit(-1).cast("long")), F.max)):
        want = rows_of(ends.groupBy("vid").agg(fold("value")))
        for strategy in ("rows_broadcast", "grid"):
            assert rows_of(generalized_spmv(g, x, Both(how), strategy=strategy).select("vid", "red")) == want
    lists = generalized_spmv(g, x, Both(Reduce.collect()), strategy="grid")
    assert rows_of(lists.select("vid", F.size("red"))) == rows_of(ends.groupBy("vid").agg(F.count("*").cast("int")))


def test_initial_state_is_checked(spark, edges):
    from vertexalg.engine import run_program

    g = Graph(edges, spark.createDataFrame([(1,), (1,)], "vid long"))
    with pytest.raises(ValueError, match="unique"):
        run_program(g, SsspProgram(1), validate=True)
    assert init_state(g, SsspProgram(1)).columns == ["vid", "dist", "active"]


def test_published_means():
    assert round(geometric_mean([7.5, 7.9, 1.5, 7.1, 10.6]), 1) == 5.8
    assert round(geometric_mean([4.1, 2.2, 36.0, 4.8, 10.2]), 1) == 6.9
    assert round(geometric_mean([2.6, 1.0, 0.8, 1.5, 0.7]), 1) == 1.2
    assert round(geometric_mean([1.15, 1.18, 2.10, 0.73]), 2) == 1.20
    assert gains({"a": 8.0, "b": 4.0, "c": 1.0}) == {"a": 1.0, "b": 2.0, "c": 8.0}


def test_speedup_frame(spark):
    rows = spark.createDataFrame([("engine", "pr", "x", 1.0), ("engine", "pr", "y", 2.0), ("other", "pr", "x", 4.0), ("other", "pr", "y", 2.0)], "system string, algorithm string, dataset string, seconds double")
    assert {r["algorithm"]: round(r["speedup"], 6) for r in speedup(rows).collect()} == {"pr": 2.0, "overall": 2.0}


def test_rmat_forms_agree(spark):
    from vertexalg.sources.rmat_source import register

    register(spark)
    want = rows_of(rmat_edges(spark, 6, RMAT_RANK))
    assert rows_of(spark.read.format("rmat").option("scale", 6).load()) == want
    assert rows_of(spark.sql("select * from rmat_edges(6, 5700, 1900, 1900, 42)")) == want
    g = rmat(spark, 10)
    assert (g.vertices.count(), g.edges.count()) == (891, 12044)


def test_files(spark, edges, tmp_path):
    from vertexalg.sources.tables import read_edge_list, save_bucketed, write_edge_list

    write_edge_list(edges, str(tmp_path / "e"))
    assert rows_of(read_edge_list(spark, str(tmp_path / "e")).select("src", "dst", F.col("value").cast("long"))) == rows_of(edges)
    (tmp_path / "m.mtx").write_text("%%matrix coordinate\n3 3 2\n1 2 0.5\n3 1 2\n")
    assert rows_of(read_edge_list(spark, str(tmp_path / "m.mtx"), matrix_market=True)) == [(1, 2, 0.5), (3, 1, 2.0)]
    for kind in ("json", "orc"):
        edges.write.format(kind).save(str(tmp_path / kind))
        assert rows_of(spark.read.format(kind).schema(edges.schema).load(str(tmp_path / kind))) == rows_of(edges)
    table = save_bucketed(edges, "bucketed_edges", 4)
    assert rows_of(table) == rows_of(edges)
    assert exchanges(table.groupBy("dst").count()) == 0
    spark.sql("drop table bucketed_edges")


def test_sql_surface(spark, edges):
    from vertexalg.sqlapi import bfs_recursive_sql, register_graph, run_sql_program

    g = Graph.from_edges(edges, value="value")
    register_graph(spark, "g", g)
    run_sql_program("g", "sssp", source=7)
    assert spark.sql("select count(*) from g_sssp where dist = 0").first()[0] >= 1
    ones = g.with_edges(edges.withColumn("value", F.lit(1).cast("long")))
    want = rows_of(sssp(ones, 7).where("dist <= 2"))
    assert rows_of(bfs_recursive_sql(spark, "g", 7, 2).select("vid", F.col("level").cast("long"))) == want


def test_stream_equals_batch(spark, sf, tmp_path):
    from vertexalg.streaming import edges as S

    rows = spark.read.parquet(f"{sf}/events.parquet").orderBy("ts")
    rows.repartitionByRange(3, "ts").write.parquet(str(tmp_path / "in"))
    stream = S.window_degree(S.stream_edges(S.event_stream(spark, str(tmp_path / "in"))))
    query = stream.writeStream.format("memory").queryName("degrees").outputMode("complete").start()
    query.processAllAvailable()
    query.stop()
    batch = S.window_degree(rows.select(F.col("ts").cast("timestamp").alias("ts"), F.col("user_id").alias("src")))
    assert rows_of(spark.table("degrees")) == rows_of(batch)


def test_distances_follow_inserts(spark):
    from vertexalg.streaming.edges import follow_distances

    got = []
    batch = follow_distances(1, lambda df, n: got.append({r[0]: r[1] for r in df.collect()}))
    frame = lambda rows: spark.createDataFrame(rows, "src long, dst long, value long")
    batch(frame([(1, 2, 5), (2, 3, 5)]), 0)
    batch(frame([(1, 3, 2), (3, 4, 1)]), 1)
    assert got == [{1: 0, 2: 5, 3: 10}, {1: 0, 2: 5, 3: 2, 4: 3}]


def test_subgraph_and_ids(spark, sf):
    from vertexalg.graphs.ids import encode_ids

    names = spark.createDataFrame([("b",), ("a",), ("b",), (None,), ("c",)], "name string")
    assert rows_of(encode_ids(names, "name")) == [("a", 0), ("b", 1), ("c", 2)]
    g = derive.graph(spark, sf, "trade")
    kept = g.subgraph(F.col("vid") < 5).edges
    assert kept.where("src >= 5 or dst >= 5").isEmpty() and kept.count() == g.edges.where("src < 5 and dst < 5").count()


def test_counters(spark, edges):
    from vertexalg.measures.counters import counted, counters, normalised
    from vertexalg.measures.effort import effort

    with counted(spark, "one"):
        edges.groupBy("dst").count().collect()
    c = counters(spark, "one")
    assert c["records"] > 0
    assert normalised({"engine": {"a": 2.0}, "x": {"a": 4.0}})["x"]["a"] == 2.0
    assert all(0 < n < 60 for n in effort().values())


def test_late_rows_and_repeats(spark, tmp_path):
    from vertexalg.streaming import edges as S

    rows = lambda items: spark.createDataFrame([(i, t, 1, "a", 1.0, "{}") for i, t in items], "event_id long, ts string, user_id long, event_type string, value double, props string").withColumn("ts", F.col("ts").cast("timestamp_ntz"))
    folder = str(tmp_path / "late")
    rows([(1, "2024-01-01 00:00:00"), (2, "2024-01-01 12:00:00")]).coalesce(1).write.mode("append").parquet(folder)
    stream = S.without_repeats(S.stream_edges(S.event_stream(spark, folder)))
    query = stream.writeStream.format("memory").queryName("late").outputMode("append").option("checkpointLocation", str(tmp_path / "cp")).start()
    query.processAllAvailable()
    # one is a repeat, one comes days after the watermark has passed it
    rows([(2, "2024-01-01 12:00:00"), (3, "2024-01-01 01:00:00"), (4, "2024-01-01 12:30:00")]).coalesce(1).write.mode("append").parquet(folder)
    query.processAllAvailable()
    query.stop()
    assert sorted(r.event_id for r in spark.table("late").collect()) == [1, 2, 4]


def test_running_degree(spark, tmp_path):
    from vertexalg.streaming import edges as S

    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        folder = str(tmp_path / "edges")
        frame = lambda r: spark.createDataFrame(r, "src long, dst long")
        frame([(1, 2), (3, 2)]).coalesce(1).write.parquet(folder)
        stream = S.running_degree(spark.readStream.schema("src long, dst long").option("maxFilesPerTrigger", 1).parquet(folder))
        query = stream.writeStream.format("memory").queryName("running").outputMode("update").option("checkpointLocation", str(tmp_path / "cp")).start()
        query.processAllAvailable()
        frame([(4, 2), (4, 5)]).coalesce(1).write.mode("append").parquet(folder)
        query.processAllAvailable()
        query.stop()
        assert sorted(tuple(r) for r in spark.table("running").collect()) == [(2, 2), (2, 3), (5, 1)]
    finally:
        spark.conf.unset("spark.sql.streaming.stateStore.providerClass")


def test_stream_joins(spark, sf, tmp_path):
    from vertexalg.streaming import edges as S

    rows = spark.read.parquet(f"{sf}/events.parquet")
    rows.write.parquet(str(tmp_path / "in"))
    events = S.event_stream(spark, str(tmp_path / "in"))
    names = spark.createDataFrame([("click", 1), ("view", 2)], "event_type string, code int")
    query = events.join(names, "event_type").writeStream.format("memory").queryName("static").outputMode("append").start()
    query.processAllAvailable()
    query.stop()
    assert spark.table("static").count() == rows.join(names, "event_type").count()
    a = events.withWatermark("ts", "1 hour").select(F.col("ts").alias("ta"), "user_id", F.col("event_id").alias("a"))
    b = S.event_stream(spark, str(tmp_path / "in")).withWatermark("ts", "1 hour").select(F.col("ts").alias("tb"), F.col("user_id").alias("u"), F.col("event_id").alias("b"))
    near = (F.col("user_id") == F.col("u")) & F.expr("tb > ta and tb <= ta + interval 1 hour")
    query = a.join(b, near).writeStream.format("memory").queryName("near").outputMode("append").start()
    query.processAllAvailable()
    query.stop()
    ts = rows.select(F.col("ts").cast("timestamp").alias("ta"), "user_id", F.col("event_id").alias("a"))
    batch = ts.join(ts.toDF("tb", "u", "b"), near)
    assert spark.table("near").count() == batch.count()
