"""Tunables and the shared folder."""

from __future__ import annotations

import tempfile
import uuid
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession


@dataclass(frozen=True)
class EngineConf:
    """partitions: blocks of the matrix; None means factor times the session's default parallelism.

    broadcast_bytes: a message vector up to this size is broadcast, a larger one never.
    """

    partitions: int | None = None
    factor: int = 1
    broadcast_bytes: int = 8 << 20

    def blocks(self, spark: SparkSession) -> int:
        return self.partitions or self.factor * spark.sparkContext.defaultParallelism


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share: the session's. Only a local session without one gets a temporary folder; elsewhere
    its executors would not see it, so that is an error."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if spark.sparkContext.master.split("[")[0] != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="vertexalg-"))
        found = spark.sparkContext.getCheckpointDir()
    return found


class Table:
    """A frame written once to the shared folder: lineage ends there, and a lost executor loses nothing."""

    def __init__(self, df: DataFrame, name: str = "step") -> None:
        self.spark = df.sparkSession
        self.path = f"{shared_dir(self.spark)}/{name}-{uuid.uuid4().hex}"
        df.write.parquet(self.path)
        self.df = self.spark.read.schema(df.schema).parquet(self.path)

    def delete(self) -> None:
        path = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(self.path)
        path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def written(df: DataFrame, name: str = "step") -> DataFrame:
    return Table(df, name).df


class Rolling:
    """The newest of a series of written frames. The one before it is deleted, as the newest is written and reads it no more."""

    def __init__(self, name: str = "step") -> None:
        self.name, self.table = name, None

    def put(self, df: DataFrame) -> DataFrame:
        before, self.table = self.table, Table(df, self.name)
        if before is not None:
            before.delete()
        return self.table.df
