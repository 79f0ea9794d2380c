"""The superstep on columns: the state of a vertex lies with the column of its out-edges, and both go on together.

A column is kept as rows (vid, _part, _cells): cells (to, value, own) of at most ``CELLS`` edges, the first of part 0
being the vertex itself. A sender's cells are its edges' contributions; a vertex that does not send gives its own cell
alone, so absent columns cost no edge. Contributions and old states are reduced in one aggregation by destination, which leaves the new state
dealt as the columns are: a superstep has one exchange, of partly reduced contributions, and the state is read once, so supersteps can be
chained in one job whose plan grows by the same amount with each.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vertexalg.graphs.graph import Graph
from vertexalg.program import VertexProgram

CELLS = 4096


def columns(g: Graph, direction: str = "out") -> DataFrame:
    """(vid, _part, _cells) of all vertices, dealt and sorted by vid, and kept. As many blocks as an aggregation of the session makes."""
    return g.kept(f"columns {direction}", lambda: _build(g, direction))


def _build(g: Graph, direction: str) -> DataFrame:
    blocks = int(g.spark.conf.get("spark.sql.shuffle.partitions"))
    edges = g.arcs(direction)
    value = edges.schema["value"].dataType
    rows = edges.withColumnRenamed("src", "vid").repartition(blocks, "vid").withColumn("n", F.count("*").over(W.partitionBy("vid")))
    cell = F.struct(F.col("dst").alias("to"), "value", F.lit(False).alias("own"))
    # a hub's column is cut into parts, so no row holds all of it
    lists = rows.groupBy("vid", F.pmod(F.xxhash64("dst"), F.ceil(F.col("n") / CELLS)).alias("_part")).agg(F.array_sort(F.collect_list(cell)).alias("_cells"))
    ids = g.vertices.select("vid").distinct().repartition(blocks, "vid")
    own = F.array(F.struct(F.col("vid").alias("to"), F.lit(None).cast(value).alias("value"), F.lit(True).alias("own")))
    # parts are numbered from 0 in each vertex, and the first holds the vertex itself, also where there is no edge
    beside = ids.hint("merge").join(lists, "vid", "left").withColumn("_part", F.row_number().over(W.partitionBy("vid").orderBy("_part")).cast("long") - 1)
    cells = F.coalesce("_cells", F.array().cast(lists.schema["_cells"].dataType))
    return beside.select("vid", "_part", F.when(F.col("_part") == 0, F.concat(own, cells)).otherwise(cells).alias("_cells")).sortWithinPartitions("vid")


def degrees(g: Graph, direction: str = "out") -> DataFrame:
    """(vid, degree) of all vertices, from the columns: what lies together is counted where it lies."""
    return columns(g, direction).groupBy("vid").agg(F.count_if(F.col("_part") == 0).alias("_own"), F.sum(F.size("_cells")).alias("_all")).select("vid", (F.col("_all") - F.col("_own")).alias("degree"))


def superstep(g: Graph, state: DataFrame, program: VertexProgram, names: Sequence[str], sends: Column) -> DataFrame:
    """(vid, names..., red, _n) of state (vid, names..., active): the old state of every vertex, what its
    contributions reduce to (null if there are none), and their number."""
    how = program.reduce()
    message = F.when(sends, program.send(F.col))
    told = state.select("vid", *names, message.alias("_m"))
    lying = told.hint("merge").join(columns(g, program.direction), "vid")
    cells = F.when(F.col("_m").isNotNull(), F.col("_cells")).when(F.col("_part") == 0, F.slice("_cells", 1, 1))
    salt = [F.pmod(F.xxhash64("vid"), F.lit(how.salts)).alias("_salt")] if how.salts > 1 else []
    rows = lying.select(*names, "_m", *salt, F.explode(cells).alias("_e"))
    own = F.col("_e.own")
    given = rows.select(F.col("_e.to").alias("vid"), own.alias("_own"), *(F.when(own, F.col(k)).alias(k) for k in names), F.when(~own, program.process(F.col("_m"), F.col("_e.value"), None)).alias("_c"), *(["_salt"] if salt else []))
    old = [F.first(k, ignorenulls=True).alias(k) for k in names]
    values = [c.alias(n) for c, n in zip(how.columns(F.col("_c")), how.names, strict=True)]
    if salt:  # a reduction that gathers does so in parts of a destination
        parts = given.groupBy("vid", "_salt").agg(*old, *values, F.count_if(~F.col("_own")).alias("_got"), F.bool_or("_own").alias("_is"))
        merged = [how.merge(F.when(F.col("_got") > 0, F.col(n)))[0].alias(n) for n in how.names]
        reduced = parts.groupBy("vid").agg(*old, *merged, F.sum("_got").alias("_got"), F.bool_or("_is").alias("_is"))
    else:
        reduced = given.groupBy("vid").agg(*old, *values, F.count_if(~F.col("_own")).alias("_got"), F.bool_or("_own").alias("_is"))
    # what goes to no vertex of the graph is dropped; a vertex that got nothing has no reduced value
    some = F.col("_got") > 0
    return reduced.where("_is").select("vid", *names, F.when(some, how.finish(F.col)).alias("red"), F.when(some, F.col("_got")).alias("_n"))
