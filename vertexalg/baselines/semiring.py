"""Baseline: matrix primitives on a q x q grid. A product sees a message and an edge, never the destination."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vertexalg.algorithms import cf
from vertexalg.algorithms.pagerank import with_out_degree
from vertexalg.conf import EngineConf, Rolling, written
from vertexalg.graphs.graph import Graph
from vertexalg.graphs.prep import drop_self_loops, ones, symmetrize, upper_triangle
from vertexalg.matrix.semirings import MIN_PLUS, PLUS_TIMES
from vertexalg.matrix.spmv import spmv


def on_grid(g: Graph, q: int) -> Graph:
    """The same graph cut into q x q blocks; it is made once, as its layout is kept."""
    if q not in g.grids:
        g.grids[q] = Graph(g.edges, g.vertices, g.directed, EngineConf(partitions=q * q, broadcast_bytes=g.conf.broadcast_bytes), g.form)
    return g.grids[q]


def pagerank(g: Graph, r: float = 0.15, iterations: int = 10, grid: int = 2) -> DataFrame:
    sized = with_out_degree(on_grid(g, grid))
    plus_first = (lambda m, e: m, PLUS_TIMES[1])
    kept = Rolling("ranks")
    ranks = kept.put(sized.vertices.select("vid", "outdeg", F.lit(1.0).alias("rank")))
    for _ in range(iterations):
        x = ranks.where("outdeg > 0").select("vid", (F.col("rank") / F.col("outdeg")).alias("value"))
        y = spmv(sized, x, *plus_first, strategy="grid")
        ranks = kept.put(ranks.select("vid", "outdeg").join(y, "vid", "left").select("vid", "outdeg", (r + (1 - r) * F.coalesce("value", F.lit(0.0))).alias("rank")))
    return ranks.select("vid", "rank")


def sssp(g: Graph, source: int, grid: int = 2) -> DataFrame:
    """Min-plus products of the whole reached vector until it stands still."""
    blocks = on_grid(g, grid)
    kept = Rolling("dist")
    dist = kept.put(g.vertices.select("vid", F.when(F.col("vid") == source, F.lit(0).cast("long")).alias("dist")))
    while True:
        y = spmv(blocks, dist.where("dist is not null").select("vid", F.col("dist").alias("value")), *MIN_PLUS, strategy="grid")
        nxt = kept.put(dist.join(y, "vid", "left").select("vid", F.least("dist", "value").alias("dist"), (~F.least("dist", "value").eqNullSafe(F.col("dist"))).alias("moved")))
        dist = nxt.select("vid", "dist")
        if nxt.where("moved").isEmpty():
            return dist


def bfs(g: Graph, root: int, grid: int = 2) -> DataFrame:
    return sssp(ones(symmetrize(drop_self_loops(g))), root, grid).select("vid", F.col("dist").alias("level"))


def triangles_spgemm(g: Graph, mask_late: bool = True) -> DataFrame:
    """A*A masked by A: with mask_late the whole product is made first (its size is the number of wedge ends)."""
    e = upper_triangle(g).edges.select("src", "dst")
    first, second = e.select("src", F.col("dst").alias("mid")), e.select(F.col("src").alias("mid"), "dst")
    if not mask_late:
        return first.join(second, "mid").join(e, ["src", "dst"], "left_semi").agg(F.count("*").alias("triangles"))
    square = written(first.join(second, "mid").groupBy("src", "dst").agg(F.count("*").alias("n")), "square")
    return square.join(e, ["src", "dst"]).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("triangles"))


def wedges(g: Graph) -> DataFrame:
    """(wedges): rows of the product before summing."""
    e = upper_triangle(g).edges
    into, out = e.groupBy(F.col("dst").alias("vid")).agg(F.count("*").alias("a")), e.groupBy(F.col("src").alias("vid")).agg(F.count("*").alias("b"))
    return into.join(out, "vid").agg(F.coalesce(F.sum(F.col("a") * F.col("b")), F.lit(0)).alias("wedges"))


def cf_gd(ratings: DataFrame, k: int = 4, gamma: float = 0.002, lam: float = 0.05, iterations: int = 5) -> cf.CFModel:
    """The error matrix is written out on the rating pattern, then multiplied with either factor matrix."""
    names = cf.fields(k)
    side = lambda n, c: ratings.select(F.lit(n).alias("side"), F.col(c).alias("id"), (F.col(c) * 2 + n).alias("vid")).distinct()
    rows = side(0, "user").union(side(1, "item"))
    kept, errors = Rolling("factors"), Rolling("error")
    factors = kept.put(rows.select("side", "id", *(cf.initial(F.col("vid"), i).alias(f) for i, f in enumerate(names))))
    for _ in range(iterations):
        model = cf.CFModel(factors.where("side = 0"), factors.where("side = 1"), [], k)
        error = errors.put(cf.rating_error(ratings, model))
        parts = []
        for n, own, other in ((0, "user", "item"), (1, "item", "user")):
            far = factors.where(F.col("side") == 1 - n).withColumnRenamed("id", other)
            parts.append(error.join(far, other).groupBy(F.lit(n).alias("side"), F.col(own).alias("id")).agg(*(F.sum(F.col("error") * F.col(f)).alias(f"g_{f}") for f in names)))
        grads = reduce(DataFrame.unionByName, parts)
        factors = kept.put(factors.join(grads, ["side", "id"]).select("side", "id", *((F.col(f) + gamma * (F.col(f"g_{f}") - lam * F.col(f))).alias(f) for f in names)))
    return cf.CFModel(factors.where("side = 0").drop("side"), factors.where("side = 1").drop("side"), [], k)
