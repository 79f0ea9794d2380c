"""Doubly compressed columns: per row block the non-empty columns, where each begins, row ids and values."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


#: Entries of a block where the caller names no number of blocks.
ENTRIES = 1 << 16


def to_dcsc(edges: DataFrame, blocks: int | None = None) -> DataFrame:
    """(block, col_ids, col_ptr, row_ids, vals); a block is one row and one task's work, so blocks bounds its size: by default there is one
    for every ``ENTRIES`` edges, 8 at least (edges are counted for it). Columns are ascending, and so are the rows of a column."""
    n = blocks or max(8, -(-edges.count() // ENTRIES))
    block = F.pmod(F.xxhash64("dst"), F.lit(n)).cast("int").alias("block")
    value = edges.schema["value"].dataType.simpleString()

    def compress(t: pa.Table) -> pa.Table:
        t = t.sort_by([("src", "ascending"), ("dst", "ascending"), ("value", "ascending")]).combine_chunks()
        src = t.column("src").to_numpy()
        begin = np.flatnonzero(np.append(True, src[1:] != src[:-1]))
        whole = lambda x: pa.ListArray.from_arrays(pa.array([0, len(x)], pa.int32()), x)
        row, val = (t.column(c).combine_chunks() for c in ("dst", "value"))
        ptr = pa.array(np.append(begin, len(src)), pa.int32())
        return pa.table({"block": t.column("block")[:1].cast(pa.int32()), "col_ids": whole(pa.array(src[begin])), "col_ptr": whole(ptr), "row_ids": whole(row), "vals": whole(val)})

    given = edges.select(block, F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"), "value")
    return given.groupBy("block").applyInArrow(compress, f"block int, col_ids array<bigint>, col_ptr array<int>, row_ids array<bigint>, vals array<{value}>")


def from_dcsc(dcsc: DataFrame) -> DataFrame:
    """(src, dst, value): every column is repeated for its entries, a block at a time."""

    def unfold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(len(batch)):
                col, ptr, row, val = (batch.column(c)[i].values for c in ("col_ids", "col_ptr", "row_ids", "vals"))
                src = np.repeat(col.to_numpy(), np.diff(ptr.to_numpy()))
                yield pa.RecordBatch.from_arrays([pa.array(src), row, val], names=["src", "dst", "value"])

    value = dcsc.schema["vals"].dataType.elementType.simpleString()
    return dcsc.select("col_ids", "col_ptr", "row_ids", "vals").mapInArrow(unfold, f"src bigint, dst bigint, value {value}")


def dcsc_column(src: int) -> Column:
    """Entries (row, value) of column src of a block; empty where the block has none."""
    at = F.array_position("col_ids", src).cast("int")
    begin = F.get("col_ptr", at - 1)
    part = lambda c: F.slice(c, begin + 1, F.get("col_ptr", at) - begin)
    return F.when(at > 0, F.arrays_zip(part("row_ids").alias("row"), part("vals").alias("value"))).otherwise(F.array().cast("array<struct<row: bigint, value: bigint>>"))


def block_product(dcsc: DataFrame, x: DataFrame, kind: str = "min_plus", limit: int = 8 << 20) -> DataFrame:
    """(vid, value) of x (vid, value) by a numpy kernel over whole blocks. x goes to every task, so its size is checked."""
    n = x.count()
    if n * 16 > limit:
        raise ValueError(f"a vector of {n} entries is larger than {limit} bytes; use generalized_spmv with a shuffle")
    rows = sorted((r["vid"], r["value"]) for r in x.collect())
    ids, values = np.array([r[0] for r in rows], np.int64), np.array([r[1] for r in rows], np.float64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for block in batch.to_pylist():
                col, ptr = np.array(block["col_ids"], np.int64), np.array(block["col_ptr"], np.int64)
                at = np.searchsorted(ids, col)
                has = at < len(ids)
                has[has] = ids[at[has]] == col[has]
                pick = np.flatnonzero(has)
                size = ptr[pick + 1] - ptr[pick]
                stop = np.cumsum(size)
                flat = np.arange(int(stop[-1]) if len(stop) else 0) + np.repeat(ptr[pick] - (stop - size), size)
                row, w = np.array(block["row_ids"], np.int64)[flat], np.array(block["vals"], np.float64)[flat]
                m = np.repeat(values[at[pick]], size)
                names, slot = np.unique(row, return_inverse=True)
                if kind == "min_plus":
                    y = np.full(len(names), np.inf)
                    np.minimum.at(y, slot, m + w)
                else:
                    y = np.bincount(slot, m * w, len(names)) if len(names) else np.zeros(0)
                yield pa.RecordBatch.from_arrays([pa.array(names, pa.int64()), pa.array(y, pa.float64())], names=["vid", "value"])

    return dcsc.mapInArrow(run, "vid long, value double")
