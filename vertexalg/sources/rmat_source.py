"""spark.read.format('rmat'): a Python data source of synthetic edges, and a table function for SQL."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.functions import udtf

from vertexalg.graphs.rmat import MODULUS, RMAT_RANK


def _mix(x: np.ndarray) -> np.ndarray:
    return ((x ^ (x >> 15)) * 1103515245 + 12345) % MODULUS


def edge_range(first: int, last: int, scale: int, shares: tuple[int, int, int], seed: int) -> tuple[np.ndarray, np.ndarray]:
    """Sources and destinations of edges first..last-1, the same as the DataFrame form gives."""
    e = np.arange(first, last, dtype=np.int64)
    h = _mix(_mix(((e % MODULUS) * 2654435 + seed) % MODULUS))
    u, v = np.zeros_like(e), np.zeros_like(e)
    a, b, c = np.cumsum(shares)
    for level in range(1, scale + 1):
        h = _mix(h ^ (level * 40503))
        t = (h >> 7) % 10000
        u = u * 2 + (t >= b)
        v = v * 2 + (((t >= a) & (t < b)) | (t >= c))
    return u, v


class _Part(InputPartition):
    def __init__(self, first: int, last: int) -> None:
        self.first, self.last = first, last


class _Reader(DataSourceReader):
    def __init__(self, options: dict) -> None:
        self.scale = int(options.get("scale", 10))
        self.count = int(options.get("edgefactor", options.get("edge_factor", 16))) << self.scale
        self.seed = int(options.get("seed", 42))
        self.shares = tuple(int(options.get(k, d)) for k, d in (("a", RMAT_RANK.a), ("b", RMAT_RANK.b), ("c", RMAT_RANK.c)))
        self.parts = int(options.get("partitions", 8))

    def partitions(self) -> list[InputPartition]:
        step = -(-self.count // self.parts)
        return [_Part(i, min(i + step, self.count)) for i in range(0, self.count, step)]

    def read(self, partition: _Part) -> Iterator[pa.RecordBatch]:
        for at in range(partition.first, partition.last, 1 << 18):
            u, v = edge_range(at, min(at + (1 << 18), partition.last), self.scale, self.shares, self.seed)
            yield pa.RecordBatch.from_arrays([pa.array(u), pa.array(v)], names=["src", "dst"])


class RmatSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "rmat"

    def schema(self) -> str:
        return "src bigint, dst bigint"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


@udtf(returnType="src: bigint, dst: bigint")
class RmatEdges:
    def eval(self, scale: int, a: int, b: int, c: int, seed: int):
        for first in range(0, 16 << scale, 1 << 16):
            u, v = edge_range(first, min(first + (1 << 16), 16 << scale), scale, (a, b, c), seed)
            yield from zip(u.tolist(), v.tolist(), strict=True)


@udtf(returnType="neighbor: bigint")
class GraphNeighbors:
    """The entries of a neighbour list, one row each."""

    def eval(self, neighbors: list):
        for n in neighbors or ():
            yield (n,)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(RmatSource)
    spark.udtf.register("rmat_edges", RmatEdges)
    spark.udtf.register("graph_neighbors", GraphNeighbors)
