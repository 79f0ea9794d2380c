"""Baseline: work lists. Blocks relax to a local fixed point before anything is exchanged (so they read fresh
state), and a schedule decides which vertices of the list go first."""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from vertexalg.algorithms import cf as factorisation
from vertexalg.conf import Rolling, Table, written
from vertexalg.engine import run_program
from vertexalg.graphs.graph import Graph
from vertexalg.graphs.prep import degree_order, drop_self_loops, ones, symmetrize
from vertexalg.program import VertexProgram

#: Edges of a block whose ranks settle in arrays, some 70 bytes each.
EDGES = 1 << 23


def _relax(edges: pd.DataFrame, state: pd.DataFrame) -> pd.DataFrame:
    """One block: shortest distances from its open vertices over edges inside, and offers to vertices outside."""
    dist = dict(zip(state["vid"].tolist(), (None if pd.isna(d) else int(d) for d in state["dist"]), strict=True))
    queue = [(dist[v], v) for v, now in zip(state["vid"].tolist(), state["go"].tolist(), strict=True) if now and dist[v] is not None]
    if not queue:
        return pd.DataFrame({"vid": [], "dist": []}, dtype="int64")
    heapq.heapify(queue)
    out: dict[int, list[tuple[int, int]]] = {}
    for u, v, w in zip(edges["src"].tolist(), edges["dst"].tolist(), edges["value"].tolist(), strict=True):
        out.setdefault(u, []).append((v, w))
    offers: dict[int, int] = {}
    while queue:
        d, u = heapq.heappop(queue)
        if d > dist[u]:
            continue
        for v, w in out.get(u, ()):
            if v in dist:
                if dist[v] is None or d + w < dist[v]:
                    dist[v] = offers[v] = d + w
                    heapq.heappush(queue, (d + w, v))
            elif d + w < offers.get(v, d + w + 1):
                offers[v] = d + w
    return pd.DataFrame({"vid": list(offers), "dist": list(offers.values())}, dtype="int64")


def in_blocks(g: Graph, n: int) -> DataFrame:
    """Edges with the block of their source, written."""
    return written(g.edges.select("src", "dst", "value", F.pmod(F.xxhash64("src"), F.lit(n)).cast("int").alias("b")), "edges")


def sssp_rounds(g: Graph, source: int, schedule: str = "bucket", bucket: int | None = None, blocks: int | None = None, edges: DataFrame | None = None) -> tuple[DataFrame, int]:
    """Distances and the number of exchanges. schedule: 'fifo' takes all open vertices, 'bucket' those of the
    lowest bucket of distances, 'priority' the nearest half of the open ones.

    A task holds the edges and states of one block: choose blocks so that it fits."""
    n = blocks or g.blocks()
    block = lambda c: F.pmod(F.xxhash64(c), F.lit(n)).cast("int")
    edges = in_blocks(g, n) if edges is None else edges
    step = bucket or max(1, int(g.edges.agg(F.avg("value")).first()[0] or 1) * 2)
    source_is = F.col("vid") == source
    state = Table(g.vertices.select("vid", F.when(source_is, F.lit(0)).cast("long").alias("dist"), source_is.alias("open")), "list")
    rounds = 0
    while True:
        row = state.df.where("open").agg(F.min("dist").alias("lo"), F.percentile_approx("dist", 0.5).alias("mid")).first()
        if row["lo"] is None:
            state_out = state.df.select("vid", "dist")
            return state_out, rounds
        rounds += 1
        limit = {"fifo": None, "bucket": (row["lo"] // step + 1) * step - 1, "priority": row["mid"]}[schedule]
        go: Column = F.col("open") if limit is None else F.col("open") & (F.col("dist") <= limit)
        now = state.df.select("vid", "dist", "open", go.alias("go"), block("vid").alias("b"))
        offers = edges.groupBy("b").cogroup(now.groupBy("b")).applyInPandas(_relax, "vid long, dist long")
        best = offers.groupBy("vid").agg(F.min("dist").alias("offer"))
        joined = now.join(best, "vid", "left")
        better = F.col("offer").isNotNull() & (F.col("dist").isNull() | (F.col("offer") < F.col("dist")))
        # what a block found inside is closed there already, unless it came from outside
        nxt = joined.select("vid", F.least("dist", "offer").alias("dist"), (better | (F.col("open") & ~F.col("go"))).alias("open"))
        old, state = state, Table(nxt, "list")
        old.delete()


def sssp(g: Graph, source: int, schedule: str = "bucket", bucket: int | None = None, blocks: int | None = None, edges: DataFrame | None = None) -> DataFrame:
    return sssp_rounds(g, source, schedule, bucket, blocks, edges)[0]


def bfs(g: Graph, root: int, schedule: str = "fifo", blocks: int | None = None, edges: DataFrame | None = None) -> DataFrame:
    return sssp(ones(symmetrize(drop_self_loops(g))), root, schedule, 1, blocks, edges).select("vid", F.col("dist").alias("level"))


class ResidualProgram(VertexProgram):
    """Ranks by residuals: a vertex whose residual exceeds eps adds it to its rank and pushes it on; all vertices at once, in supersteps of the engine."""

    state, apply_to = ("rank", "residual", "outdeg"), "all"
    settles = True  # where no residual exceeds eps, none is pushed and none arrives

    def __init__(self, r: float, eps: float) -> None:
        self.r, self.eps = r, eps

    def init(self, v):
        return {"rank": F.lit(0.0), "residual": F.lit(self.r), "outdeg": v("outdeg")}

    def send(self, s):
        return F.when((s("residual") > self.eps) & (s("outdeg") > 0), s("residual") / s("outdeg"))

    def apply(self, red, s):
        pushed = s("residual") > self.eps
        rank = F.when(pushed, s("rank") + s("residual")).otherwise(s("rank"))
        return {"rank": rank, "residual": F.when(pushed, F.lit(0.0)).otherwise(s("residual")) + (1 - self.r) * F.coalesce(red, F.lit(0.0))}

    def changed(self, old, new):
        return new("residual") > self.eps


def _settle(edges: pa.Table, state: pa.Table, r: float, eps: float) -> pa.Table:
    """One block: its vertices push residuals over eps until none is left inside. Gives their ranks and residuals, and what goes to vertices outside."""
    order = np.argsort(state.column("vid").to_numpy())
    vid, rank, residual = (state.column(c).to_numpy()[order] for c in ("vid", "rank", "residual"))
    src, dst = (edges.column(c).to_numpy() for c in ("src", "dst"))

    def place(ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        at = np.searchsorted(vid, ids)
        inside = at < len(vid)
        inside[inside] = vid[at[inside]] == ids[inside]
        return at, inside

    at, sends = place(src)
    at, dst = at[sends], dst[sends]
    to, inside = place(dst)
    outer, code = np.unique(dst[~inside], return_inverse=True)
    to[~inside] = len(vid) + code
    share = (1 - r) / np.maximum(np.bincount(at, minlength=len(vid)), 1)
    got = np.concatenate([residual, np.zeros(len(outer))])
    while (go := got[: len(vid)] > eps).any():
        pushed = np.where(go, got[: len(vid)], 0.0)
        rank = rank + pushed
        got[: len(vid)] -= pushed
        if len(at):
            got += np.bincount(to, (pushed * share)[at], len(got))
    return pa.table({"vid": np.append(vid, outer), "rank": np.append(rank, np.zeros(len(outer))), "residual": got, "own": np.arange(len(got)) < len(vid)})


def settled_blocks(g: Graph) -> int:
    """Blocks that ranks by residuals are cut into: as few as hold ``EDGES`` each."""
    return g.conf.partitions or max(1, -(-g.edges.count() // EDGES))


def source_blocks(g: Graph, n: int) -> DataFrame:
    """(src, dst, b): edges dealt by the block of their source and kept, so that no exchange of the method moves them."""
    block = F.pmod(F.xxhash64("src"), F.lit(n)).cast("int").alias("b")
    return g.kept(f"residual blocks {n}", lambda: g.edges.select("src", "dst", block).repartition(n, "b").sortWithinPartitions("b"))


def residual_rounds(g: Graph, r: float = 0.15, eps: float = 1e-4, max_supersteps: int = 200, blocks: int | None = None) -> tuple[DataFrame, int]:
    """(vid, rank, residual) and the number of exchanges. Blocks push until all residuals inside are settled, then what goes to other
    blocks is exchanged: never more exchanges than ``ResidualProgram`` has supersteps, and one block settles in one.

    A task holds the edges and states of one block."""
    n = blocks or settled_blocks(g)
    edges = source_blocks(g, n)
    kept = Rolling("residuals")
    state, rounds, left = kept.put(g.vertices.select("vid", F.lit(0.0).alias("rank"), F.lit(r).alias("residual"))), 0, r > eps
    while left and rounds < max_supersteps:
        now = state.withColumn("b", F.pmod(F.xxhash64("vid"), F.lit(n)).cast("int"))
        moved = edges.groupBy("b").cogroup(now.groupBy("b")).applyInArrow(lambda e, s: _settle(e, s, r, eps), "vid long, rank double, residual double, own boolean")
        whole = moved.groupBy("vid").agg(F.sum("rank").alias("rank"), F.sum("residual").alias("residual"), F.bool_or("own").alias("own")).where("own")
        seen = Observation()
        state = kept.put(whole.select("vid", "rank", "residual").observe(seen, F.count_if(F.col("residual") > eps).alias("left")))
        rounds, left = rounds + 1, seen.get["left"]
    return state, rounds


def pagerank_residual(g: Graph, r: float = 0.15, eps: float = 1e-4, max_supersteps: int = 200, blocks: int | None = None) -> DataFrame:
    """(vid, rank): within eps / r of the fixed point of the rank equation."""
    return residual_rounds(g, r, eps, max_supersteps, blocks)[0].select("vid", (F.col("rank") + F.col("residual")).alias("rank"))


def _common(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Work items (two ascending lists) to the number of their common members, a batch at a time."""
    for batch in batches:
        flat = []
        for side in ("a", "b"):
            lists = batch.column(side)
            size = lists.value_lengths().to_numpy()
            flat.append((np.repeat(np.arange(len(batch)), size), lists.flatten().to_numpy()))
        (row_a, x), (row_b, y) = flat
        _, code = np.unique(np.append(x, y), return_inverse=True)
        span = int(code.max(initial=0)) + 1
        both = np.intersect1d(row_a * span + code[: len(x)], row_b * span + code[len(x) :], assume_unique=True)
        yield pa.RecordBatch.from_arrays([pa.array([len(both)], pa.int64())], names=["n"])


def triangles(g: Graph) -> DataFrame:
    """Every arc of the orientation by degree is a work item that carries the lists of both its ends, merged in place;
    no superstep and no reduction by vertex."""
    e = degree_order(drop_self_loops(g)).edges.select("src", "dst")
    lists = e.groupBy("src").agg(F.array_sort(F.collect_list("dst")).alias("l"))
    items = e.join(lists.withColumnRenamed("l", "a"), "src").join(lists.select(F.col("src").alias("dst"), F.col("l").alias("b")), "dst").select("a", "b")
    return items.mapInArrow(_common, "n long").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("triangles"))


class _Side(factorisation.GradientProgram):
    """One side's step: items send against the edges to users ('in'), or users along them to items ('out')."""

    def __init__(self, direction: str, k: int, gamma: float, lam: float) -> None:
        super().__init__(k, gamma, lam)
        self.direction = direction


def cf(ratings: DataFrame, k: int = 4, gamma: float = 0.002, lam: float = 0.05, iterations: int = 1) -> factorisation.CFModel:
    """Gradient descent that reads fresh state: users move first, and items move from where users have come to in the same round."""
    g = factorisation.rating_graph(ratings)
    state, trace = None, []
    for _ in range(iterations):
        for direction in ("in", "out"):
            done = run_program(g, _Side(direction, k, gamma, lam), 1, start=state)
            state, trace = done.state, trace + done.steps
    return factorisation._model(state, k, trace)
