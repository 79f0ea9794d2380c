"""Dense ids for arbitrary keys, without a global sort in one task."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vertexalg.conf import written


def encode_ids(df: DataFrame, column: str, partitions: int | None = None) -> DataFrame:
    """(key, vid): keys of column without nulls, numbered 0.. in key order.

    Keys are dealt by range; each block numbers its own, and the blocks' sizes (one number per block) give the offsets."""
    keys = df.select(F.col(column).alias("key")).where("key is not null").distinct()
    n = partitions or df.sparkSession.sparkContext.defaultParallelism
    ranged = written(keys.repartitionByRange(n, "key").select("key", F.spark_partition_id().alias("block")), "keys")
    sizes = ranged.groupBy("block").agg(F.count("*").alias("n"))
    before = W.orderBy("block").rowsBetween(W.unboundedPreceding, -1)
    offsets = sizes.select("block", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    place = F.row_number().over(W.partitionBy("block").orderBy("key")) - 1
    return ranged.withColumn("place", place).join(F.broadcast(offsets), "block").select("key", (F.col("base") + F.col("place")).cast("long").alias("vid"))
