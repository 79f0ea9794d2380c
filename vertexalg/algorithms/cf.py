"""Collaborative filtering: factors of users and items by gradient descent (as a vertex program) and by SGD."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vertexalg.conf import EngineConf, Rolling, written
from vertexalg.engine import run_program
from vertexalg.graphs.graph import Graph
from vertexalg.graphs.prep import as_bipartite
from vertexalg.program import Reduce, VertexProgram


#: Users or items of one task of recommend, items of one block, items that bounds are taken from (of each cell of users).
GROUP, BLOCK, STRONG = 100_000, 64, 128


def fields(k: int) -> list[str]:
    return [f"f{i}" for i in range(k)]


def initial(vid: Column, i: int, init: str = "formula", seed: int = 42) -> Column:
    """Factor i of vertex vid: a fixed formula of id, factor and side, or hashed values in (0, 1)."""
    if init == "formula":
        return (F.lit(1) + F.pmod(F.expr("vid div 2") * 7 + i * 13 + F.pmod(vid, F.lit(2)) * 5, F.lit(10))) / F.lit(10.0)
    return F.pmod(F.xxhash64(vid, F.lit(i), F.lit(seed)), F.lit(1_000_003)) / F.lit(1_000_003.0)


def dot(a: Callable[[str], Column], b: Callable[[str], Column], k: int) -> Column:
    return reduce(lambda x, y: x + y, (a(f) * b(f) for f in fields(k)))


class GradientProgram(VertexProgram):
    """Every vertex sends its factors both ways; the contribution of an edge is (rating - <m, dst>) * m."""

    direction, activation, needs_dst_state, stop_when_unchanged = "both", "all", True, False

    def __init__(self, k: int, gamma: float, lam: float, init: str = "formula", seed: int = 42) -> None:
        self.k, self.gamma, self.lam, self.how, self.seed = k, gamma, lam, init, seed
        self.state, self.message_bytes = tuple(fields(k)), 16 + 8 * k

    def init(self, v):
        return {f: initial(v("vid"), i, self.how, self.seed) for i, f in enumerate(fields(self.k))}

    def send(self, s):
        return F.struct(*(s(f).alias(f) for f in fields(self.k)))

    def process(self, m, e, dst):
        error = e - dot(lambda f: m[f], dst, self.k)
        return F.struct(*((error * m[f]).alias(f) for f in fields(self.k)))

    def reduce(self):
        return Reduce.vector_sum(fields(self.k))

    def apply(self, red, s):
        return {f: s(f) + F.lit(self.gamma) * (red[f] - F.lit(self.lam) * s(f)) for f in fields(self.k)}


@dataclass
class CFModel:
    user_factors: DataFrame
    item_factors: DataFrame
    trace: list[tuple]
    k: int
    state: DataFrame | None = None

    @property
    def factors(self) -> DataFrame:
        side = lambda df, n: df.select(F.lit(n).alias("side"), "id", *fields(self.k))
        return side(self.user_factors, 0).unionByName(side(self.item_factors, 1))


def _model(state: DataFrame, k: int, trace: list[tuple]) -> CFModel:
    side = lambda n: state.where(F.pmod("vid", F.lit(2)) == n).select(F.expr("vid div 2").alias("id"), *fields(k))
    return CFModel(side(0), side(1), trace, k, state)


def rating_graph(ratings: DataFrame, user: str = "user", item: str = "item", rating: str = "rating", conf: EngineConf = EngineConf()) -> Graph:
    return Graph.from_edges(as_bipartite(ratings, user, item, rating), value=F.col("value").cast("double"), conf=conf)


def descend(g: Graph, k: int = 16, gamma: float = 0.002, lam: float = 0.05, iterations: int = 5, init: str = "formula", seed: int = 42, strategy: str = "auto", start: DataFrame | None = None) -> CFModel:
    """Gradient descent on a rating graph, from start (a state of its vertices) if given."""
    out = run_program(g, GradientProgram(k, gamma, lam, init, seed), iterations, strategy=strategy, start=start)
    return _model(out.state, k, out.steps)


def cf_gd(ratings: DataFrame, user: str = "user", item: str = "item", rating: str = "rating", k: int = 16, gamma: float = 0.002, lam: float = 0.05, iterations: int = 5, init: str = "formula", seed: int = 42, strategy: str = "auto", conf: EngineConf = EngineConf()) -> CFModel:
    g = rating_graph(ratings, user, item, rating, conf)
    out = descend(g, k, gamma, lam, iterations, init, seed, strategy)
    g.unpersist()
    return out


def _beside(pairs: DataFrame, model: CFModel) -> DataFrame:
    users = model.user_factors.select(F.col("id").alias("user"), F.struct(*fields(model.k)).alias("_u"))
    items = model.item_factors.select(F.col("id").alias("item"), F.struct(*fields(model.k)).alias("_i"))
    return pairs.join(users, "user").join(items, "item")


def predict(pairs: DataFrame, model: CFModel) -> DataFrame:
    """pairs (user, item, ...) with prediction."""
    guess = dot(lambda f: F.col("_u")[f], lambda f: F.col("_i")[f], model.k)
    return _beside(pairs, model).withColumn("prediction", guess).drop("_u", "_i")


def rating_error(ratings: DataFrame, model: CFModel) -> DataFrame:
    """(user, item, rating, error)."""
    return predict(ratings, model).select("user", "item", "rating", (F.col("rating") - F.col("prediction")).alias("error"))


def rmse(ratings: DataFrame, model: CFModel) -> DataFrame:
    return rating_error(ratings, model).agg(F.sqrt(F.avg(F.col("error") * F.col("error"))).alias("rmse"))


def objective(ratings: DataFrame, model: CFModel, lam: float = 0.05, form: str = "per_rating") -> DataFrame:
    """Squared errors plus lam times squared factor lengths, added for every rating or once per vertex."""
    length = lambda c: reduce(lambda x, y: x + y, (F.col(c)[f] * F.col(c)[f] for f in fields(model.k)))
    rows = _beside(ratings, model)
    error = F.col("rating") - dot(lambda f: F.col("_u")[f], lambda f: F.col("_i")[f], model.k)
    if form == "per_rating":
        return rows.agg(F.sum(error * error + lam * length("_u") + lam * length("_i")).alias("objective"))
    own = model.factors.withColumn("_u", F.struct(*fields(model.k))).agg(F.sum(length("_u")).alias("w"))
    return rows.agg(F.sum(error * error).alias("e")).join(own).select((F.col("e") + lam * F.col("w")).alias("objective"))


def _blocks(x: np.ndarray, size: int) -> list[np.ndarray]:
    """Places of the rows of x in blocks of up to size, near ones together: the widest column is halved until a block is small enough."""
    out, left = [], [np.arange(len(x))]
    while left:
        at = left.pop()
        if len(at) <= size:
            out += [at] if len(at) else []
            continue
        side = x[at, np.ptp(x[at], axis=0).argmax()]
        order = np.argpartition(side, len(at) // 2)
        left += [at[order[: len(at) // 2]], at[order[len(at) // 2 :]]]
    return out


def _strong(own: DataFrame, items: DataFrame, k: int) -> DataFrame:
    """(item, factors) of the best items of the mean users of up to 64 cells (above or below the mean in each of the first 6 factors)."""
    mean = own.agg(*(F.avg(f).alias(f) for f in fields(k))).first()
    cell = reduce(lambda a, b: a + b, (F.when(F.col(f) > F.lit(mean[f]), 1 << j).otherwise(0) for j, f in enumerate(fields(min(k, 6)))))
    means = own.groupBy(cell.alias("cell")).agg(*(F.avg(f).alias(f"m_{f}") for f in fields(k)))
    score = F.round(dot(lambda f: F.col(f"m_{f}"), F.col, k), 9)
    place = F.row_number().over(W.partitionBy("cell").orderBy(score.desc(), "item"))
    return items.crossJoin(F.broadcast(means)).withColumn("place", place).where(F.col("place") <= STRONG).select("item", *fields(k)).distinct()


def contenders(model: CFModel, ratings: DataFrame, n: int = 5, users: int = 64) -> DataFrame:
    """(user, item, prediction, key): of every user all items, rated or not, that are no worse than the n-th best that the user has not rated
    among a few strong items; so the n best that are not rated are there. key: the prediction in 9 digits.

    The strong items give bounds only. Users and items are dealt into groups of about ``GROUP`` by their counts, so a task holds one group of
    each however many there are. In a task both lie in blocks of near ones, and a block of items whose largest possible score for a block of
    users is under the bounds of all of them is passed over; what is left is scored, ``users`` at a time. An item or user whose factors are not finite has no score."""
    k, names, spark = model.k, fields(model.k), model.user_factors.sparkSession
    whole = reduce(lambda a, b: a & b, (F.coalesce(F.abs(f) < float("inf"), F.lit(False)) for f in names))
    own, items = (df.where(whole).select(F.col("id").alias(as_), *names) for df, as_ in ((model.user_factors, "user"), (model.item_factors, "item")))
    rows = sorted(_strong(own, items, k).collect())
    ids, strong = np.array([r[0] for r in rows], np.int64), np.array([r[1:] for r in rows], float).reshape(len(rows), k)
    place = spark.createDataFrame([(int(v), i) for i, v in enumerate(ids)], "item long, at int")
    seen = ratings.select("user", "item").join(F.broadcast(place), "item").groupBy("user").agg(F.collect_list("at").alias("seen"))

    def scores(p: np.ndarray, q: np.ndarray) -> np.ndarray:
        return sum(p[:, j : j + 1] * q[None, :, j] for j in range(k))

    def told(batch: pa.RecordBatch | pa.Table) -> np.ndarray:
        return np.column_stack([batch.column(f).to_numpy() for f in names]) if len(batch) else np.empty((0, k))

    def bounded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, len(whole), 512):
                batch = whole.slice(at, 512)
                worst, last = np.full(len(batch), -np.inf), np.full(len(batch), np.iinfo(np.int64).max)
                if len(ids) >= n:
                    s, old = np.round(scores(told(batch), strong), 9), batch.column("seen")
                    s[~np.isfinite(s)] = -np.inf
                    s[np.repeat(np.arange(len(batch)), old.value_lengths().fill_null(0).to_numpy()), old.flatten().to_numpy()] = -np.inf
                    worst = np.partition(s, len(ids) - n, axis=1)[:, len(ids) - n]
                    # of equal ones the smaller items come first
                    nth = n - (s > worst[:, None]).sum(axis=1)
                    last = np.where(np.isfinite(worst), ids[(np.cumsum(s == worst[:, None], axis=1) >= nth[:, None]).argmax(axis=1)], last)
                yield pa.RecordBatch.from_arrays([batch.column("user"), *(batch.column(f) for f in names), pa.array(worst), pa.array(last)], names=["user", *names, "worst", "last"])

    def best(u: pa.Table, i: pa.Table) -> pa.Table:
        out = [[np.empty(0, np.int64)], [np.empty(0, np.int64)], [np.empty(0)], [np.empty(0)]]
        p, q, user, item, worst, last = told(u), told(i), *(t.column(c).to_numpy() for t, c in ((u, "user"), (i, "item"), (u, "worst"), (u, "last")))
        cut = _blocks(q, BLOCK)
        low, high = (np.array([f(q[b], axis=0) for b in cut]).reshape(-1, k) for f in (np.min, np.max))
        for mine in _blocks(p, users) if cut else ():
            a, b, least = p[mine].min(axis=0), p[mine].max(axis=0), worst[mine].min()
            most = np.maximum(np.maximum(a * low, a * high), np.maximum(b * low, b * high)).sum(axis=1)
            near = np.flatnonzero(most >= least - 2e-9 - 1e-12 * np.abs(most))
            if not len(near):
                continue
            at = np.concatenate([cut[x] for x in near])
            s = scores(p[mine], q[at])
            key, w = np.round(s, 9), worst[mine][:, None]
            r, c = np.nonzero(np.isfinite(s) & ((key > w) | ((key == w) & (item[at][None] <= last[mine][:, None]))))
            for column, values in zip(out, (user[mine][r], item[at][c], s[r, c], key[r, c]), strict=True):
                column.append(values)
        return pa.table(dict(zip(("user", "item", "prediction", "key"), map(np.concatenate, out), strict=True)))

    cores = spark.sparkContext.defaultParallelism
    many = [-(-df.count() // GROUP) or 1 for df in (own, items)]
    many[0] = max(many[0], -(-cores // many[1]))  # small inputs use all cores too
    group = lambda c, m: F.pmod(F.xxhash64(c), F.lit(m)).cast("int")
    every = lambda m: F.explode(F.sequence(F.lit(0), F.lit(m - 1)))
    schema = ", ".join(["user long", *(f"{f} double" for f in names), "worst double", "last long"])
    left = own.join(seen, "user", "left").select("user", *names, "seen").mapInArrow(bounded, schema)
    left = left.withColumn("g", group("user", many[0])).withColumn("b", every(many[1]))
    right = items.withColumn("ib", group("item", many[1])).withColumn("ig", every(many[0]))
    return left.groupBy("g", "b").cogroup(right.groupBy("ig", "ib")).applyInArrow(best, "user long, item long, prediction double, key double")


def recommend(model: CFModel, ratings: DataFrame, n: int = 5, users: int = 64) -> DataFrame:
    """(user, rank, item, prediction): the n best items that each user has not rated, ties to the smaller item."""
    found = contenders(model, ratings, n, users).join(ratings.select("user", "item"), ["user", "item"], "left_anti")
    rank = F.row_number().over(W.partitionBy("user").orderBy(F.desc("key"), "item"))
    return found.withColumn("rank", rank).where(F.col("rank") <= n).select("user", "rank", "item", "prediction")


def cf_sgd(ratings: DataFrame, user: str = "user", item: str = "item", rating: str = "rating", k: int = 16, gamma: float = 0.002, lam: float = 0.05, epochs: int = 5, strata: int = 4, seed: int = 42, init: str = "formula") -> CFModel:
    """Factors updated rating by rating, in hashed order. Users and items are dealt to strata blocks each; one stratum is a
    diagonal of blocks that share no vertex, so its blocks run side by side and equal one serial order.

    A task holds one block of users, one of items and their ratings: choose strata so that it fits."""
    import pandas as pd

    d = strata
    block = lambda c: F.pmod(F.xxhash64(c, F.lit(seed)), F.lit(d)).cast("int")
    rows = written(ratings.select(F.col(user).cast("long").alias("user"), F.col(item).cast("long").alias("item"), F.col(rating).cast("double").alias("rating")).withColumn("ub", block("user")).withColumn("ib", block("item")), "ratings")
    ids = rows.select(F.lit(0).alias("side"), F.col("user").alias("id"), F.col("ub").alias("block")).union(rows.select(F.lit(1), "item", "ib")).distinct()
    vid = ids.withColumn("vid", F.col("id") * 2 + F.col("side"))
    kept = Rolling("factors")
    factors = kept.put(vid.select("side", "id", "block", *(initial(F.col("vid"), i, init, seed).alias(f) for i, f in enumerate(fields(k)))))
    schema = factors.schema

    def step(ratings: pd.DataFrame, own: pd.DataFrame) -> pd.DataFrame:
        p = own[fields(k)].to_numpy(copy=True)
        at = {key: r for r, key in enumerate(zip(own["side"], own["id"], strict=True))}
        for u, i, y in ratings.sort_values(["h", "user", "item"])[["user", "item", "rating"]].itertuples(index=False):
            a, b = at[0, u], at[1, i]
            pu, pi = p[a].copy(), p[b].copy()
            error = y - float(pu @ pi)
            p[a] = pu + gamma * (error * pi - lam * pu)
            p[b] = pi + gamma * (error * pu - lam * pi)
        return own.assign(**{f: p[:, j] for j, f in enumerate(fields(k))})[schema.names]

    for epoch in range(epochs):
        hashed = rows.withColumn("h", F.xxhash64("user", "item", F.lit(seed + epoch)))
        for s in range(d):
            part = hashed.where(F.pmod(F.col("ub") - F.col("ib"), F.lit(d)) == s).withColumn("key", F.col("ub"))
            key = F.when(F.col("side") == 0, F.col("block")).otherwise(F.pmod(F.col("block") + s, F.lit(d)))
            factors = kept.put(part.groupBy("key").cogroup(factors.withColumn("key", key).groupBy("key")).applyInPandas(lambda r, f: step(r, f), schema))
    side = lambda n: factors.where(F.col("side") == n).select("id", *fields(k))
    return CFModel(side(0), side(1), [], k)


def cf_trace(ratings: DataFrame, k: int = 4, gamma: float = 0.002, lam: float = 0.05, iterations: int = 5) -> DataFrame:
    """(round, rmse, objective) after rounds 0..iterations, each going on from the one before."""
    g, out, model = rating_graph(ratings), None, None
    for n in range(iterations + 1):
        model = descend(g, k, gamma, lam, 1 if n else 0, start=model and model.state)
        row = rmse(ratings, model).join(objective(ratings, model, lam)).select(F.lit(n).alias("round"), "rmse", "objective")
        row = written(row, "trace")
        out = row if out is None else out.unionByName(row)
    g.unpersist()
    return out
