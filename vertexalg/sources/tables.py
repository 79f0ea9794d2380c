"""Readers and writers of tables, edge lists and saved graphs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_edge_list(spark: SparkSession, path: str, sep: str = " ", weighted: bool = True, matrix_market: bool = False) -> DataFrame:
    """Lines 'src dst [weight]'; lines that begin with % are comments. matrix_market: the first other line tells the sizes
    and is left out; it is the one that comes first in the file and has three whole numbers."""
    fields = [T.StructField("src", T.LongType()), T.StructField("dst", T.LongType())]
    if weighted:
        fields.append(T.StructField("value", T.DoubleType()))
    rows = spark.read.csv(path, schema=T.StructType(fields), sep=sep, comment="%")
    if not matrix_market:
        return rows
    marked = rows.withColumn("_p", F.monotonically_increasing_id())
    least = marked.agg(F.min("_p").alias("_least"))
    return marked.join(F.broadcast(least)).where("_p <> _least").drop("_p", "_least")


def write_edge_list(edges: DataFrame, path: str, sep: str = " ") -> None:
    edges.select("src", "dst", "value").write.mode("overwrite").csv(path, sep=sep)


def save_bucketed(edges: DataFrame, name: str, blocks: int, key: str = "dst") -> DataFrame:
    """Edges as a table bucketed by key and sorted by the other end: products read it without a shuffle."""
    other = "src" if key == "dst" else "dst"
    edges.write.mode("overwrite").bucketBy(blocks, key).sortBy(other).saveAsTable(name)
    return edges.sparkSession.table(name)
