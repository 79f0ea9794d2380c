"""Generalized sparse matrix-vector product: process is the multiply, reduce the add.

rows_broadcast: edges lie in blocks by destination, messages are broadcast, the reduction stays in the block: no exchange
                but of the states that process reads.
cols_shuffle:   edges lie in blocks by source, messages join there, partial results are exchanged by destination.
grid:           edges lie in cells of a q x q grid; messages go to the q cells of their column, partial results to one row.
Layouts are kept with the graph, for both directions too, so no edge is exchanged in a product unless
process reads destinations and messages are too many to be broadcast.
triplet:        both end states are joined to every edge and filtered after (the baseline's plan).
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vertexalg.graphs.graph import Graph
from vertexalg.matrix.strategies import choose
from vertexalg.program import VertexProgram


def _struct_reader(struct: str):
    return lambda name: F.col(struct)[name]


def _contributions(joined: DataFrame, program: VertexProgram) -> DataFrame:
    dst = _struct_reader("_dst") if program.needs_dst_state else None
    return joined.select("dst", program.process(F.col("_m"), F.col("value"), dst).alias("_c"))


def _reduced(contributions: DataFrame, program: VertexProgram) -> DataFrame:
    """(vid, red, _n): _n counts the contributions (dst, _c). Spark reduces in each block before it exchanges; a reduction that
    gathers does so in salted parts of a destination, and one in Python counts in Python too."""
    how = program.reduce()
    first = [c.alias(n) for c, n in zip(how.columns(F.col("_c")), how.names, strict=True)]
    if how.python:
        out = contributions.groupBy("dst").agg(*first, _length()(F.col("_c")).alias("_n"))
    elif how.salts > 1:
        parts = contributions.withColumn("_salt", F.pmod(F.monotonically_increasing_id(), F.lit(how.salts))).groupBy("dst", "_salt").agg(*first, F.count("*").alias("_n"))
        out = parts.groupBy("dst").agg(*(how.merge(F.col(n))[0].alias(n) for n in how.names), F.sum("_n").alias("_n"))
    else:
        out = contributions.groupBy("dst").agg(*first, F.count("*").alias("_n"))
    return out.select(F.col("dst").alias("vid"), how.finish(F.col).alias("red"), "_n")


def _length():
    def number(values: pd.Series) -> int:
        return len(values)

    return F.pandas_udf(number, "long")


def generalized_spmv(g: Graph, x: DataFrame, program: VertexProgram, dst_state: DataFrame | None = None, strategy: str = "auto", messages: int | None = None) -> DataFrame:
    """y (vid, red, _n) of x (vid, _m): one row per destination that got a message.

    dst_state (vid, _dst struct) is needed where the program reads destinations. messages: rows of x, if known."""
    blocks = g.blocks()
    if strategy == "auto":
        strategy = choose(messages, program.message_bytes, g.conf.broadcast_bytes, None, blocks, program.needs_dst_state)
    send = x.select(F.col("vid").alias("src"), "_m")

    def with_dst(df: DataFrame) -> DataFrame:
        if not program.needs_dst_state:
            return df
        return df.join(dst_state.select(F.col("vid").alias("dst"), "_dst"), "dst")

    if strategy == "rows_broadcast":
        joined = g.layout("dst", program.direction).join(F.broadcast(send), "src")
        return _reduced(_contributions(with_dst(joined), program), program)
    if strategy == "cols_shuffle":
        joined = g.layout("src", program.direction).join(send, "src")
        return _reduced(_contributions(with_dst(joined), program), program)
    if strategy == "grid":
        q = max(1, int(blocks**0.5))
        wide = send.withColumn("_col", F.pmod(F.xxhash64("src"), F.lit(q)).cast("int")).withColumn("_row", F.explode(F.sequence(F.lit(0), F.lit(q - 1))))
        joined = g.grid(q, program.direction).join(wide, ["_row", "_col", "src"])
        return _reduced(_contributions(with_dst(joined), program), program)
    raise ValueError(f"unknown strategy {strategy!r}")


def spmv(g: Graph, x: DataFrame, multiply, add, direction: str = "out", strategy: str = "auto") -> DataFrame:
    """(vid, value) of x (vid, value) over a semiring: multiply(message, edge value), add is a Reduce."""

    class Product(VertexProgram):
        def process(self, m: Column, e: Column, dst) -> Column:
            return multiply(m, e)

        def reduce(self):
            return add

    product = Product()
    product.direction = direction
    y = generalized_spmv(g, x.select("vid", F.col("value").alias("_m")), product, strategy=strategy)
    return y.select("vid", F.col("red").alias("value"))
