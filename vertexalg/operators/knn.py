"""The nearest vectors of every vector, exact, by a grid of blocks.

Vectors are dealt into blocks; a grid cell (source block, target block) is one cogroup whose sides have a bounded size.
A cell multiplies tiles of unit vectors and keeps the k best targets of each source; the best of all cells are merged by rank.
Scale: each vector moves once per block and side, and k rows per source leave each cell.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vertexalg.functions.vectors import wide

BLOCK, TILE = 20_000, 2048


def _unit(rows: pa.Table, name: str) -> np.ndarray:
    lists = rows.column(name).combine_chunks()
    x = lists.flatten().to_numpy().reshape(len(lists), -1)
    x = x / np.abs(x).max(axis=1)[:, None]  # squares of tiny or huge values stay in range
    return x / np.sqrt((x * x).sum(axis=1))[:, None]


def best_of_cell(src: np.ndarray, x: np.ndarray, dst: np.ndarray, y: np.ndarray, k: int, tile: int = TILE) -> list[np.ndarray]:
    """(src, dst, cosine, its 9 digits): the k nearest y of each x, none of its own id; ties of 9 digits to the smaller id."""
    kept = []
    for a in range(0, len(src), tile):
        best = [np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0), np.zeros(0)]  # row, dst, cosine, digits
        for b in range(0, len(dst), tile):
            ids = dst[b : b + tile]
            cosine = x[a : a + tile] @ y[b : b + tile].T
            digits = np.round(cosine, 9)
            digits[src[a : a + tile, None] == ids[None]] = -np.inf
            near = np.isfinite(digits)
            if len(ids) > k:
                near &= digits >= np.partition(digits, len(ids) - k, axis=1)[:, len(ids) - k, None]
            row, column = np.nonzero(near)
            best = [np.append(p, q) for p, q in zip(best, (row, ids[column], cosine[near], digits[near]), strict=True)]
            order = np.lexsort((best[1], -best[3], best[0]))
            best = [p[order] for p in best]
            place = np.arange(len(order)) - np.searchsorted(best[0], best[0])
            best = [p[place < k] for p in best]
        kept.append([src[a + best[0]], *best[1:]])
    return [np.concatenate(c) for c in zip(*kept, strict=True)]


def nearest_vectors(vectors: DataFrame, k: int, block: int = BLOCK) -> DataFrame:
    """(src, dst, value): the k nearest by cosine of every row of vectors (vec_id, embedding), value in 6 digits.

    Vectors that are null, empty or zero, or hold a null or a value that isn't finite, take no part, nor does a null id;
    vectors of different lengths do not meet. Equal rows count once; rows of one id are one source and never meet."""
    fine = F.forall("x", lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf"))) & F.exists("x", lambda v: v != 0)
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), wide("embedding").alias("x")).where(F.col("vec_id").isNotNull() & fine)
    rows = rows.select("vec_id", "x", F.size("x").alias("d")).distinct()
    blocks = max(1, -(-rows.count() // block))
    part, every = F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    left = rows.select("vec_id", "x", "d", part.alias("i"), every.alias("j")).groupBy("d", "i", "j")
    # other names than the left side's: a plan that is used twice is renamed, and must not take one side's for the other's
    right = rows.select(F.col("vec_id").alias("to"), F.col("x").alias("y"), F.col("d").alias("e"), part.alias("j"), every.alias("i")).groupBy("e", "i", "j")

    def cell(a: pa.Table, b: pa.Table) -> pa.Table:
        found = [[], [], [], []]
        if len(a) and len(b):
            found = best_of_cell(a.column("vec_id").to_numpy(), _unit(a, "x"), b.column("to").to_numpy(), _unit(b, "y"), k)
        kinds = zip(("src", "dst", "c", "digits"), found, (pa.int64(), pa.int64(), pa.float64(), pa.float64()), strict=True)
        return pa.table({name: pa.array(values, kind) for name, values, kind in kinds})

    found = left.cogroup(right).applyInArrow(cell, "src long, dst long, c double, digits double")
    order = W.partitionBy("src").orderBy(F.desc("digits"), "dst")
    return found.withColumn("r", F.row_number().over(order)).where(F.col("r") <= k).select("src", "dst", F.round("c", 6).alias("value"))
