"""Synthetic graphs from integer arithmetic alone, so that any engine reproduces them."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from vertexalg.conf import EngineConf
from vertexalg.graphs.graph import Graph

MODULUS = 2**31


@dataclass(frozen=True)
class Quadrants:
    """Shares in 1/10000 of the first three quadrants; the fourth has the rest."""

    a: int
    b: int
    c: int


#: The three parameter sets of the experiments.
RMAT_RANK, RMAT_TRI, RMAT_PATH = Quadrants(5700, 1900, 1900), Quadrants(4500, 1500, 1500), Quadrants(5000, 1000, 1000)


def mix(x: Column) -> Column:
    return F.pmod(x.bitwiseXOR(F.shiftright(x, 15)) * F.lit(1103515245) + F.lit(12345), F.lit(MODULUS))


def mix_sql(x: str) -> str:
    return f"((xor({x}, ({x}) >> 15) * 1103515245 + 12345) % {MODULUS})"


def _positive(x: str) -> str:
    return f"((({x}) % {MODULUS} + {MODULUS}) % {MODULUS})"


def rmat_edges(spark: SparkSession, scale: int, shares: Quadrants, edge_factor: int = 16, seed: int = 42, picks: DataFrame | None = None) -> DataFrame:
    """(src, dst): edge_factor * 2**scale picks, self-loops and repeats included. One fold per edge, no shuffle.
    picks (id): a table whose rows are the picks, in place of as many numbers; null ids pick nothing."""
    e = F.col("id")
    first = mix(mix(F.pmod(F.pmod(e, F.lit(MODULUS)) * 2654435 + seed, F.lit(MODULUS))))
    t1, t2, t3 = shares.a, shares.a + shares.b, shares.a + shares.b + shares.c
    hashed = lambda h, level: mix(h.bitwiseXOR(level * 40503))
    zero = F.struct(F.lit(0).cast("long").alias("u"), F.lit(0).cast("long").alias("v"), hashed(first, F.lit(1)).alias("h"))

    def step(acc: Column, level: Column) -> Column:
        t = F.pmod(F.shiftright(acc["h"], 7), F.lit(10000))
        u = F.when(t >= t2, 1).otherwise(0)
        v = F.when(((t >= t1) & (t < t2)) | (t >= t3), 1).otherwise(0)
        return F.struct((acc["u"] * 2 + u).alias("u"), (acc["v"] * 2 + v).alias("v"), hashed(acc["h"], level + 1).alias("h"))

    fold = F.aggregate(F.sequence(F.lit(1).cast("long"), F.lit(scale).cast("long")), zero, step)
    ids = spark.range(edge_factor << scale) if picks is None else picks.where("id is not null")
    return ids.select(fold.alias("f")).select(F.col("f.u").alias("src"), F.col("f.v").alias("dst"))


def rmat(spark: SparkSession, scale: int, shares: Quadrants = RMAT_RANK, edge_factor: int = 16, seed: int = 42, conf: EngineConf = EngineConf(), picks: DataFrame | None = None) -> Graph:
    """Prepared graph: no self-loops, no repeats; weight 1 + (31 src + 17 dst) mod 100."""
    edges = rmat_edges(spark, scale, shares, edge_factor, seed, picks).where("src <> dst").distinct()
    return Graph.from_edges(edges, value=(F.lit(1) + F.pmod(F.col("src") * 31 + F.col("dst") * 17, F.lit(100))).cast("long"), conf=conf)


def rmat_sql(scale: int, shares: Quadrants, edge_factor: int = 16, seed: int = 42, picks: str | None = None) -> str:
    """The same graph as SQL: (src, dst, value). picks: SQL of the ids (id) that are the picks."""
    ids = f"range({edge_factor << scale})" if picks is None else f"(select {_positive('id')} as range from ({picks}) where id is not null)"
    t1, t2, t3 = shares.a, shares.a + shares.b, shares.a + shares.b + shares.c
    first = mix_sql(mix_sql(f"((range % {MODULUS}) * 2654435 + {seed}) % {MODULUS}"))
    t = "((h >> 7) % 10000)"
    return (
        f"(with recursive k(l, u, v, h) as (select 0, 0::bigint, 0::bigint, {first}::bigint from {ids} union all "
        f"select l + 1, u * 2 + (({t}) >= {t2})::int, v * 2 + ((({t}) >= {t1} and ({t}) < {t2}) or ({t}) >= {t3})::int, h from (select l, u, v, {mix_sql('xor(h, (l + 1) * 40503)')} as h from k where l < {scale}))"
        f" select distinct u as src, v as dst, 1 + (u * 31 + v * 17) % 100 as value from k where l = {scale} and u <> v)"
    )


def synthetic_ratings(spark: SparkSession, users: int | DataFrame, items: int, per_user: int, seed: int = 42) -> DataFrame:
    """(user, item, rating): item popularity falls as a power law; the least rating of a repeated pair stays.
    users: how many, or a table of them (id); null ids rate nothing."""
    inside = lambda x: F.pmod(x, F.lit(MODULUS))
    u = inside(F.col("id") + seed)
    ids = spark.range(users) if isinstance(users, int) else users.where("id is not null")
    count = F.lit(1) + F.pmod(mix(u), F.lit(2 * per_user - 1))
    rows = ids.select(F.col("id").alias("user"), F.explode(F.sequence(F.lit(0).cast("long"), count - 1)).alias("j"))
    x = mix(mix(inside(F.col("user") * 7919 + F.col("j") * 104729 + seed)))
    high = F.shiftright(F.col("x"), 11)
    picked = rows.select("user", x.alias("x")).select("user", F.shiftright(high * high * items, 40).alias("item"), (F.lit(1) + F.pmod(mix(F.col("x")), F.lit(5))).alias("rating"))
    return picked.groupBy("user", "item").agg(F.min("rating").alias("rating"))


def synthetic_ratings_sql(users: int | str, items: int, per_user: int, seed: int = 42) -> str:
    """The same ratings as SQL; users: how many, or SQL of their ids (id)."""
    many = isinstance(users, int)
    inside = (lambda v: v) if many else _positive
    ids = f"range({users})" if many else f"(select id as range from ({users}) where id is not null)"
    x = mix_sql(mix_sql(inside(f"(u * 7919 + j * 104729 + {seed})")))
    return (
        f"(select u as \"user\", ((x >> 11) * (x >> 11) * {items}) >> 40 as item, min(1 + {mix_sql('x')} % 5) as rating from (select u, {x} as x from "
        f"(select range as u, unnest(range(1 + {mix_sql(inside(f'(range + {seed})'))} % {2 * per_user - 1})) as j from {ids})) group by all)"
    )
