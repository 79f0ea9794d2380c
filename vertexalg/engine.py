"""The superstep driver: send, product, apply, until nothing is active or the rounds are used up.

One job writes the next state to the shared folder and counts, as observed metrics of the same job, what was active,
sent, processed and changed in each superstep. On columns a superstep reads the state once, so a job takes up to
``CHAIN`` of them; supersteps after the last that sends change nothing and are not told. Elsewhere a job is one superstep. The
state is read back from the folder, so plans stay small (a kept frame would double with every reference), a lost executor
costs one job at most, and states older than the last two are deleted.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, AtomicType, BinaryType, DataType, StringType, StructType

from vertexalg.conf import Table
from vertexalg.graphs.graph import Graph
from vertexalg.matrix import columns
from vertexalg.matrix.spmv import generalized_spmv
from vertexalg.matrix.strategies import choose
from vertexalg.program import VertexProgram

CHAIN = 3
_STEP = "superstep int, active long, messages long, edges long, receivers long, changed long, seconds double, strategy string"


@dataclass
class ProgramResult:
    state: DataFrame
    steps: list[tuple] = field(default_factory=list)
    converged: bool = False

    @property
    def supersteps(self) -> DataFrame:
        return self.state.sparkSession.createDataFrame(self.steps, _STEP)

    def save(self, path: str) -> None:
        self.state.write.mode("overwrite").parquet(path)


def init_state(g: Graph, program: VertexProgram) -> DataFrame:
    """(vid, state..., active)."""
    rows = program.init(F.col)
    return g.vertices.select("vid", *(c.alias(k) for k, c in rows.items()), F.coalesce(program.active0(F.col), F.lit(False)).alias("active"))


def check_vertices(g: Graph) -> None:
    row = g.vertices.agg(F.count("*").alias("n"), F.count("vid").alias("v"), F.count_distinct("vid").alias("d")).first()
    if not row["n"] == row["v"] == row["d"]:
        raise ValueError("vertex ids must be unique and not null")


def resume(spark: SparkSession, path: str) -> DataFrame:
    """A saved state, to be passed as start to run_program."""
    return spark.read.parquet(path)


def message_size(message: Column, kind: DataType) -> Column | None:
    """About the bytes of a message and its vertex; None where they can't be told from the type and the message's length."""
    if isinstance(kind, StructType):
        parts = [message_size(message[f.name], f.dataType) for f in kind.fields]
        return None if any(p is None for p in parts) else reduce(lambda a, b: a + b, parts, F.lit(16))
    if isinstance(kind, (StringType, BinaryType)):
        return F.coalesce(F.octet_length(message), F.lit(0)) + 24
    if isinstance(kind, ArrayType):
        return F.coalesce(F.size(message), F.lit(0)) * 8 + 24 if isinstance(kind.elementType, AtomicType) and not isinstance(kind.elementType, (StringType, BinaryType)) else None
    return F.lit(24) if isinstance(kind, AtomicType) else None


def chainable(program: VertexProgram) -> bool:
    """Whether a superstep past the end leaves the state as it is, or there is no end but the bound."""
    return not program.stop_when_unchanged or program.settles or (program.activation == "changed" and program.apply_to != "all")


def run_program(g: Graph, program: VertexProgram, max_supersteps: int | None = None, strategy: str = "auto", start: DataFrame | None = None, validate: bool = False, product: Callable[..., DataFrame] | None = None, chain: int = CHAIN) -> ProgramResult:
    """Runs program on g. max_supersteps None: the program's own bound, or until no vertex is active.

    strategy 'auto': columns, or one that a counted size allows where process reads destinations.
    product: another way to get (vid, red, _n) from (graph, state, messages, program).
    start: a state to go on from (vid, state..., active) instead of the program's initial one.
    chain: supersteps of one job, where the program's plan allows them.
    The result has the columns vid, state..., active; its steps count every round that sent something."""
    if validate:
        check_vertices(g)
    bound = max_supersteps if max_supersteps is not None else program.max_supersteps
    names = list(program.state)
    sends = F.col("active") if program.activation == "changed" else F.lit(True)
    given = start if start is not None else init_state(g, program)
    message = F.when(sends, program.send(F.col))
    told = (F.count_if("active").alias("active"), F.count_if(message.isNotNull()).alias("messages"))
    apart = program.needs_dst_state or program.reduce().python
    resident = product is None and (strategy == "columns" or (strategy == "auto" and not apart))
    if strategy == "columns" and apart:
        raise ValueError("columns don't hold destinations, nor reduce in Python: take another strategy for such a program")

    size = None if resident else message_size(message, given.select(message.alias("m")).schema["m"].dataType)
    if size is not None:
        told += (F.sum(F.when(message.isNotNull(), size)).alias("bytes"),)

    def after(state: DataFrame, plan: str, messages: int) -> DataFrame:
        """(vid, state..., active, _n) after one superstep."""
        if resident:
            joined = columns.superstep(g, state, program, names, sends)
        else:
            senders = state.where("active") if program.activation == "changed" else state
            x = senders.select("vid", program.send(F.col).alias("_m")).where("_m is not null")
            dst = state.select("vid", F.struct(*names).alias("_dst")) if program.needs_dst_state else None
            y = product(g, state, x, program) if product else generalized_spmv(g, x, program, dst, plan, messages)
            joined = state.drop("active").join(y, "vid", "left")
        applied = program.apply(F.col("red"), F.col)
        if program.apply_to != "all":
            applied = {k: F.when(F.col("_n").isNotNull(), c).otherwise(F.col(k)) for k, c in applied.items()}
        # the old state stays beside the new one until the change has been told
        fresh = F.struct(*(applied.get(k, F.col(k)).alias(k) for k in names))
        paired = joined.select("vid", F.struct(*names).alias("_old"), fresh.alias("_new"), "_n")
        change = program.changed(lambda k: F.col("_old")[k], lambda k: F.col("_new")[k])
        return paired.select("vid", *(F.col("_new")[k].alias(k) for k in names), F.coalesce(change, F.lit(False)).alias("active"), "_n")

    def observed(df: DataFrame, *more) -> tuple[DataFrame, Observation]:
        seen = Observation()
        return df.observe(seen, *told, *more).select("vid", *names, "active"), seen

    state, seen = observed(given)
    table, now, steps, old = None, None, [], []
    if not resident or bound == 0:
        table = Table(state, "state")
        now = seen.get

    def going() -> bool:
        # where apply runs everywhere, a round without messages still moves states
        moving = now["messages"] or (program.apply_to == "all" and now["active"])
        return bool(moving) and (bound is None or len(steps) < bound) and not (steps and not now["active"] and program.stop_when_unchanged)

    while now is None or going():
        began = time.time()
        plan = "columns" if resident else strategy
        if plan == "auto":
            plan = choose(now.get("bytes"), 1, g.conf.broadcast_bytes, None, g.blocks(), program.needs_dst_state)
        length = chain if resident and chainable(program) else 1
        length = length if bound is None else min(length, bound - len(steps))
        first, watched = (state, [seen]) if table is None else (table.df, [])
        after_it = first
        for _ in range(length):
            after_it, seen = observed(after(after_it, plan, now and now["messages"]), F.coalesce(F.sum("_n"), F.lit(0)).alias("edges"), F.count("_n").alias("receivers"))
            watched.append(seen)
        if table is not None:
            old.append(table)
        table = Table(after_it, "state")
        if now is None:  # the initial state was counted on the way
            now = watched.pop(0).get
            if not going():
                table.delete()
                table = Table(first.select("vid", *names, "active"), "state")
        seconds = (time.time() - began) / length
        for seen in watched:
            if going():
                before, now = now, seen.get
                steps.append((len(steps) + 1, before["active"], before["messages"], now["edges"], now["receivers"], now["active"], seconds, plan))
        if len(old) > 1:
            old.pop(0).delete()
    return ProgramResult(table.df, steps, not now["active"])
