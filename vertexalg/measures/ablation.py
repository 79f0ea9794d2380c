"""The cumulative ablation and core scaling. Every bar must give the same result; only its plan differs.

naive: opaque Python functions, vectors as pairs, one block (and so one task). +bitmap: the frontier filters edges as a bitmap first.
+inlined: functions as Column expressions. +parallel: one block per core. +balanced: more blocks than cores. All but the first use the bitmap.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from vertexalg.algorithms.pagerank import PageRankProgram, with_out_degree
from vertexalg.algorithms.sssp import SsspProgram
from vertexalg.conf import EngineConf
from vertexalg.engine import ProgramResult, run_program
from vertexalg.graphs.graph import Graph
from vertexalg.matrix.spmv import _reduced
from vertexalg.matrix.vectors import BitmapVector
from vertexalg.measures.timing import gains, timed_run
from vertexalg.program import VertexProgram

BARS = ("naive", "bitmap", "inlined", "parallel", "balanced")


def opaque(program: VertexProgram, kind: str = "udf") -> VertexProgram:
    """The same program with process as a function that Spark cannot see into: 'udf' row by row, 'arrow' in batches."""
    plain = isinstance(program, SsspProgram)
    out = T.LongType() if plain else T.DoubleType()
    if kind == "udf":  # Spark calls it for rows without a message too, and drops what it gives for them
        function = F.udf((lambda m, e: None if m is None or e is None else m + e) if plain else (lambda m, e: m), out)
    else:
        function = F.pandas_udf((lambda m, e: m + e) if plain else (lambda m, e: m), out)

    class Opaque(type(program)):
        def process(self, m, e, dst):
            return function(m, e)

    copy = Opaque.__new__(Opaque)
    copy.__dict__.update(program.__dict__)
    return copy


def _bitmap_product(g: Graph, state: DataFrame, x: DataFrame, program: VertexProgram) -> DataFrame:
    """Edges are first tested against the bits of the frontier, then meet the values."""
    bits = BitmapVector.of(x.select("vid", F.lit(1).alias("val")))
    joined = bits.keep(g.layout("dst"), "src").join(x.withColumnRenamed("vid", "src"), "src")
    return _reduced(joined.select("dst", program.process(F.col("_m"), F.col("value"), None).alias("_c")), program)


def _pairs_product(g: Graph, state: DataFrame, x: DataFrame, program: VertexProgram) -> DataFrame:
    joined = g.layout("dst").join(x.withColumnRenamed("vid", "src"), "src")
    return _reduced(joined.select("dst", program.process(F.col("_m"), F.col("value"), None).alias("_c")), program)


def bar(name: str, g: Graph, algorithm: str, root: int | None = None, iterations: int = 3, cores: int | None = None) -> tuple[float, ProgramResult]:
    """(seconds, result) of one bar on rank or shortest paths."""
    step = BARS.index(name)
    cores = cores or g.spark.sparkContext.defaultParallelism
    conf = EngineConf(partitions=1 if step < 3 else cores if step == 3 else 4 * cores)
    own = Graph(g.edges, g.vertices, g.directed, conf)
    program: VertexProgram = SsspProgram(root) if algorithm == "sssp" else PageRankProgram()
    if algorithm == "rank":
        own = with_out_degree(own)
    if step < 2:
        program = opaque(program)
    product = _bitmap_product if step else _pairs_product
    seconds, out = timed_run(lambda h: run_program(h, program, iterations if algorithm == "rank" else None, product=product), own, layouts=("dst",))
    own.unpersist()
    return seconds, out


def ablation(g: Graph, algorithm: str, root: int | None = None, iterations: int = 3) -> dict[str, float]:
    return gains({name: bar(name, g, algorithm, root, iterations)[0] for name in BARS})
