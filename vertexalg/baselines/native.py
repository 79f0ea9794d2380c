"""Baseline: each algorithm by hand as plain DataFrame code, with its own choice of partitioning and joins."""

from __future__ import annotations

from operator import mul

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.storagelevel import StorageLevel

from vertexalg.algorithms.cf import CFModel, fields, initial
from vertexalg.conf import Rolling, written
from vertexalg.graphs.graph import Graph
from vertexalg.graphs.prep import drop_self_loops, ones, symmetrize, upper_triangle


def shares(g: Graph, r: float = 0.15) -> DataFrame:
    """What each edge passes on of a rank, dealt by its source and kept."""
    degree = g.edges.groupBy("src").agg(F.count("*").alias("d"))
    return g.edges.join(degree, "src").select("src", "dst", (F.lit(1 - r) / F.col("d")).alias("w")).repartition(g.blocks(), "src").persist(StorageLevel.MEMORY_AND_DISK)


def pagerank(g: Graph, r: float = 0.15, iterations: int = 10, share: DataFrame | None = None) -> DataFrame:
    own = shares(g, r) if share is None else share
    kept = Rolling("ranks")
    ranks = kept.put(g.vertices.select("vid", F.lit(1.0).alias("rank")))
    for _ in range(iterations):
        sums = own.join(ranks.withColumnRenamed("vid", "src"), "src").groupBy(F.col("dst").alias("vid")).agg(F.sum(F.col("rank") * F.col("w")).alias("s"))
        ranks = kept.put(ranks.select("vid").join(sums, "vid", "left").select("vid", (r + F.coalesce("s", F.lit(0.0))).alias("rank")))
    if share is None:
        own.unpersist()
    return ranks


def laid_out(g: Graph) -> DataFrame:
    """Edges dealt by destination and kept."""
    return g.edges.repartition(g.blocks(), "dst").persist(StorageLevel.MEMORY_AND_DISK)


def _frontier(laid: DataFrame, vertices: DataFrame, root: int) -> DataFrame:
    """Rounds over the frontier alone; what was found is one growing table of (vid, dist)."""
    start = vertices.where(F.col("vid") == root).select("vid", F.lit(0).cast("long").alias("dist"))
    fronts, found = Rolling("front"), Rolling("known")
    front, known = fronts.put(start), found.put(start)
    while True:
        reached = laid.join(front.withColumnRenamed("vid", "src"), "src").groupBy(F.col("dst").alias("vid")).agg(F.min(F.col("dist") + F.col("value")).alias("dist"))
        better = reached.join(known.withColumnRenamed("dist", "old"), "vid", "left").where("old is null or dist < old").select("vid", "dist")
        front = fronts.put(better)
        if front.isEmpty():
            return vertices.select("vid").join(known, "vid", "left")
        known = found.put(known.unionByName(front).groupBy("vid").agg(F.min("dist").alias("dist")))


def sssp(g: Graph, source: int, laid: DataFrame | None = None) -> DataFrame:
    own = laid_out(g) if laid is None else laid
    found = _frontier(own, g.vertices, source)
    if laid is None:
        own.unpersist()
    return found


def bfs(g: Graph, root: int, laid: DataFrame | None = None) -> DataFrame:
    return sssp(ones(symmetrize(drop_self_loops(g))), root, laid).withColumnRenamed("dist", "level")


def triangles(g: Graph) -> DataFrame:
    e = upper_triangle(g).edges.select("src", "dst")
    uv, vw = e.select(F.col("src").alias("u"), F.col("dst").alias("v")), e.select(F.col("src").alias("v"), F.col("dst").alias("w"))
    return uv.join(vw, "v").join(e.select(F.col("src").alias("u"), F.col("dst").alias("w")), ["u", "w"]).agg(F.count("*").alias("triangles"))


def cf(ratings: DataFrame, k: int = 4, gamma: float = 0.002, lam: float = 0.05, epochs: int = 1, strata: int = 4, seed: int = 42) -> CFModel:
    """Stochastic descent by hand, the published choice of the hand-written code: whole blocks of ratings go through numpy
    rating by rating, both factor matrices of a block as plain arrays.

    Users and items are dealt to strata blocks each; the blocks of a diagonal share no vertex and run side by side. The visits are
    in the order of ``cf_sgd``, so both give the same factors."""
    d, names = strata, fields(k)
    block = lambda c: F.pmod(F.xxhash64(c, F.lit(seed)), F.lit(d)).cast("int")
    rows = written(ratings.select(F.col("user").cast("long").alias("user"), F.col("item").cast("long").alias("item"), F.col("rating").cast("double").alias("rating")).withColumn("ub", block("user")).withColumn("ib", block("item")), "ratings")

    def start(side: int, column: str, at: str) -> DataFrame:
        ids = rows.select(F.col(column).alias("id"), F.col(at).alias("block"), (F.col(column) * 2 + side).alias("vid")).distinct()
        return written(ids.select("id", "block", F.array(*(initial(F.col("vid"), i, seed=seed) for i in range(k))).alias("p")), "factors")

    users, items = start(0, "user", "ub"), start(1, "item", "ib")
    kept = Rolling("factors")
    schema = "side int, id long, block int, p array<double>"

    def descend(ratings: pa.Table, both: pa.Table) -> pa.Table:
        p = both.column("p").to_pylist()
        side, ids = both.column("side").to_numpy(), both.column("id").to_numpy()
        place = [np.flatnonzero(side == n) for n in (0, 1)]
        order = [x[np.argsort(ids[x], kind="stable")] for x in place]
        rows = ratings.sort_by([("h", "ascending"), ("user", "ascending"), ("item", "ascending")])
        at = [o[np.searchsorted(ids[o], rows.column(c).to_numpy())].tolist() for o, c in zip(order, ("user", "item"), strict=True)] if len(rows) else ([], [])
        for a, b, y in zip(*at, rows.column("rating").to_pylist(), strict=True):  # a few factors are faster as plain numbers than as arrays
            u, v = p[a], p[b]
            error = y - sum(map(mul, u, v))
            p[a] = [x + gamma * (error * z - lam * x) for x, z in zip(u, v, strict=True)]
            p[b] = [z + gamma * (error * x - lam * z) for x, z in zip(u, v, strict=True)]
        return both.select(["side", "id", "block"]).append_column("p", pa.array(p, pa.list_(pa.float64())))

    for epoch in range(epochs):
        hashed = rows.withColumn("h", F.xxhash64("user", "item", F.lit(seed + epoch)))
        for s in range(d):
            part = hashed.where(F.pmod(F.col("ub") - F.col("ib"), F.lit(d)) == s).withColumn("key", F.col("ub"))
            mine = users.select(F.lit(0).alias("side"), "id", "block", "p", F.col("block").alias("at"))
            other = items.select(F.lit(1).alias("side"), "id", "block", "p", F.pmod(F.col("block") + s, F.lit(d)).alias("at"))
            moved = kept.put(part.groupBy("key").cogroup(mine.unionByName(other).groupBy("at")).applyInArrow(descend, schema))
            users, items = (moved.where(F.col("side") == n).select("id", "block", "p") for n in (0, 1))
    shown = lambda df: df.select("id", *(F.get("p", F.lit(i)).alias(f) for i, f in enumerate(names)))
    return CFModel(shown(users), shown(items), [], k)
