"""Operator 9: nearest neighbours by a block matrix join with int8 product tiles.

Vectors are scaled to unit length and quantised to int8 with a scale each. For a = s qa + ea and b = t qb + eb,
<a,b> differs from s t <qa,qb> by at most |s qa| |eb| + |ea| |b|, so a tile of int8 products gives every cosine with a
bound. A query keeps the k best lower bounds in a heap; only pairs whose upper bound reaches
its k-th are recomputed from the original vectors in double precision. The result is exact.

Queries and candidates are cut into groups; a grid cell (query group, candidate group) is one cogroup, whose two sides
have a bounded size. A query's best of all cells are merged by rank, with a limit before the shuffle.
Scale: candidates move once per query group, queries once per candidate group.
"""

from __future__ import annotations

import heapq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vertexalg.llm import common as C

K, QUERY_GROUP, GROUP, TILE = 5, 2048, 20_000, 2048


def _matrix(rows: pa.Table, name: str) -> np.ndarray:
    lists = rows.column(name).combine_chunks()
    return lists.flatten().to_numpy().reshape(len(lists), -1).astype(np.float64)


def quantise(x: np.ndarray):
    """Unit vectors to (int8 codes, scale, length of the code vector, length of the rest)."""
    unit = x / np.sqrt((x * x).sum(axis=1))[:, None]
    scale = np.maximum(np.abs(unit).max(axis=1), 1e-300) / 127
    code = np.rint(unit / scale[:, None]).astype(np.int8)
    near = code * scale[:, None]
    rest = unit - near
    return code, scale, np.sqrt((near * near).sum(axis=1)), np.sqrt((rest * rest).sum(axis=1))


def tile(a, b) -> tuple[np.ndarray, np.ndarray]:
    """Cosines of all pairs of two quantised blocks, and how far off they can be."""
    # floats hold sums of 1,024 products of int8 exactly (under 2**24), doubles those of any usual length
    wide = np.float32 if a[0].shape[1] <= 1024 else np.float64
    dot = a[0].astype(wide) @ b[0].astype(wide).T
    about = dot * a[1][:, None] * b[1][None]
    return about, a[2][:, None] * b[3][None] + a[3][:, None] + 1e-9


def cosine(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Of matching rows, in double precision; equal rows give equal results wherever they stand."""
    return (x * y).sum(axis=1) / (np.sqrt((x * x).sum(axis=1)) * np.sqrt((y * y).sum(axis=1)))


def search_block(query_id: np.ndarray, query: np.ndarray, vec_id: np.ndarray, vector: np.ndarray, k: int) -> list[tuple[int, int, float]]:
    """(number of the query, vector, score): the k nearest of each query, none of its own id; ties to the smaller id."""
    best: list[list[tuple[float, int]]] = [[] for _ in query_id]  # heaps of (score, -id)
    order = np.argsort(vec_id, kind="stable")
    vec_id, vector = vec_id[order], vector[order]
    coded = quantise(query)
    floor = np.full(len(query_id), -np.inf)
    for at in range(0, len(vec_id), TILE):
        ids, part = vec_id[at : at + TILE], vector[at : at + TILE]
        about, off = tile(coded, quantise(part))
        about[query_id[:, None] == ids[None]] = -np.inf
        if len(ids) > k:
            low = np.partition(about - off, len(ids) - k, axis=1)[:, len(ids) - k]
            floor = np.maximum(floor, low)
        q, v = np.nonzero((about + off >= floor[:, None]) & np.isfinite(about))
        for start in range(0, len(q), 1 << 14):
            qs, vs = q[start : start + (1 << 14)], v[start : start + (1 << 14)]
            for i, score, name in zip(qs.tolist(), cosine(query[qs], part[vs]).tolist(), ids[vs].tolist(), strict=True):
                heap = best[i]
                if len(heap) < k:
                    heapq.heappush(heap, (score, -name))
                elif (score, -name) > heap[0]:
                    heapq.heapreplace(heap, (score, -name))
        floor = np.maximum(floor, [h[0][0] - 1e-9 if len(h) == k else -np.inf for h in best])
    return [(i, -name, score) for i, heap in enumerate(best) for score, name in heap]


def nearest(vectors: DataFrame, queries: DataFrame, k: int = K, query_group: int = QUERY_GROUP, group: int = GROUP) -> DataFrame:
    """(query_id, rank, vec_id, score): for each of queries (vec_id, embedding) the k nearest of vectors by cosine, itself left out.

    Vectors that are null or zero, or hold a null or a value that isn't finite, take no part; so do those of another
    length than their partner. Rows that repeat an id with other values stand for themselves, as queries (each is ranked by
    itself) and as candidates (of other ids); equal rows count once. A null id takes no part. A query without candidates
    gives no row, and so does an empty table."""
    good = lambda x: F.col("vec_id").isNotNull() & F.col("x").isNotNull() & (F.size("x") > 0) & F.forall("x", lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf"))) & F.exists("x", lambda v: v != 0)  # noqa: E731, ARG005
    usable = lambda df: df.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("x")).where(good(None)).select("vec_id", "x", F.size("x").alias("d"), F.xxhash64("x").alias("variant")).distinct()
    wanted, rows = usable(queries), usable(vectors)
    q_groups, groups = -(-wanted.count() // query_group), -(-rows.count() // group)
    cells = lambda n: F.explode(F.sequence(F.lit(0), F.lit(max(n, 1) - 1)))
    part = lambda n: F.pmod(F.xxhash64("vec_id"), F.lit(max(n, 1))).cast("int")
    left = wanted.select("vec_id", "variant", "x", "d", part(q_groups).alias("qg"), cells(groups).alias("g")).groupBy("d", "qg", "g")
    # other names than the queries': a plan that is used twice is renamed, and must not take one side's for the other's
    right = rows.select(F.col("vec_id").alias("to"), F.col("x").alias("y"), F.col("d").alias("e"), part(groups).alias("h"), cells(q_groups).alias("qh")).groupBy("e", "qh", "h")

    def cell(a: pa.Table, b: pa.Table) -> pa.Table:
        found = search_block(a.column("vec_id").to_numpy(), _matrix(a, "x"), b.column("to").to_numpy(), _matrix(b, "y"), k) if len(a) and len(b) else []
        at, vec_id, score = zip(*found, strict=True) if found else ((), (), ())
        at = pa.array(at, pa.int64())
        return pa.table({"query_id": a.column("vec_id").take(at), "variant": a.column("variant").take(at), "vec_id": pa.array(vec_id, pa.int64()), "score": pa.array(score, pa.float64())})

    found = left.cogroup(right).applyInArrow(cell, "query_id long, variant long, vec_id long, score double")
    order = W.partitionBy("query_id", "variant").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op9_nearest_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = C.table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    return nearest(vectors, vectors.where("vec_id % 50 = 0"))
