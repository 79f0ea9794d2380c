"""Generated graphs whose picks are the rows of a given table."""

import duckdb
import pytest

from vertexalg.registry import ORACLES, QUERIES


@pytest.fixture(scope="module")
def tables(spark, tmp_path_factory):
    folder = str(tmp_path_factory.mktemp("picks"))
    ids = [*range(1, 400), 5, 5, -3, -(2**40), 2**40 + 9, None]
    for name, key in (("orders", "o_orderkey"), ("customer", "c_custkey")):
        spark.createDataFrame([(i,) for i in ids], f"{key} long").write.parquet(f"{folder}/{name}.parquet")
    return folder


@pytest.mark.parametrize("name", ["graph_rmat", "graph_rmat_tri", "graph_rmat_path", "graph_synth_rating", "workfront_sssp_rmat_path"])
def test_rows_of_the_table(spark, tables, name):
    con = duckdb.connect()
    for table in ("orders", "customer"):
        con.execute(f"create view {table} as select * from read_parquet('{tables}/{table}.parquet/*.parquet')")
    found = con.execute(ORACLES[name])
    at = [c[0] for c in found.description]
    got = QUERIES[name](spark, tables)
    key = lambda r: tuple((v is not None, v or 0) for v in r)
    want = [tuple(row[at.index(c)] for c in got.columns) for row in found.fetchall()]
    rows = [tuple(r) for r in got.collect()]
    assert len(rows) > 50 and sorted(rows, key=key) == sorted(want, key=key)
