"""Baseline: a frontier sweep over compressed rows in one process. It is meant for graphs that fit one task, so its
size is checked and a larger graph is refused."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vertexalg.graphs.graph import Graph

LIMIT = 20_000_000


def sssp(g: Graph, source: int, limit: int = LIMIT) -> DataFrame:
    n = g.edges.count()
    if n > limit:
        raise ValueError(f"{n} edges are more than one process is meant to hold ({limit})")

    def sweep(edges: pa.Table) -> pa.Table:
        src, dst, w = (edges.column(c).to_numpy() for c in ("src", "dst", "value"))
        ids, flat = np.unique(np.concatenate([src, dst]), return_inverse=True)
        s, t = flat[: len(src)], flat[len(src) :]
        order = np.argsort(s, kind="stable")
        t, w = t[order], w[order].astype(np.int64)
        row = np.searchsorted(s[order], np.arange(len(ids) + 1))
        far = np.iinfo(np.int64).max
        dist = np.full(len(ids), far)
        front = np.flatnonzero(ids == source)
        dist[front] = 0
        while len(front):
            size = row[front + 1] - row[front]
            stop = np.cumsum(size)
            at = np.arange(int(stop[-1])) + np.repeat(row[front] - (stop - size), size)
            before = dist.copy()
            np.minimum.at(dist, t[at], np.repeat(dist[front], size) + w[at])
            front = np.flatnonzero(dist < before)
        return pa.table({"vid": ids.astype(np.int64), "dist": pa.array(dist, mask=dist == far)})

    found = g.edges.groupBy(F.lit(0).alias("all")).applyInArrow(lambda t: sweep(t.select(["src", "dst", "value"])), "vid long, dist long")
    return g.vertices.select("vid").join(found, "vid", "left")
