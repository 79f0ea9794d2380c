"""Graphs on the given tables, each as DataFrame code and as the SQL that must give the same edges.

Every group that makes edges is bounded by its key (order), is cut into buckets of time (day, user, type), or makes a star: documents that share a line are
tied to the least of them, so a group of any size has as many edges as members and stays connected. `colink` has all pairs
of pages that share a path, as its definition asks.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vertexalg.conf import EngineConf
from vertexalg.graphs.graph import Graph
from vertexalg.graphs.rmat import RMAT_PATH, RMAT_RANK, RMAT_TRI, rmat, rmat_sql, synthetic_ratings, synthetic_ratings_sql
from vertexalg.sources.tables import table

LINK = r'href="([^"]*)"'
SHARED_LINE, NEIGHBOURS = 20, 8


def _least(rows: DataFrame) -> DataFrame:
    return rows.where("src <> dst").groupBy("src", "dst").agg(F.min("value").alias("value"))


def basket_chain(spark: SparkSession, d: str) -> DataFrame:
    order = W.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice")
    lines = table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice")
    rows = lines.select(F.col("l_partkey").alias("src"), F.lead("l_partkey").over(order).alias("dst"), F.col("l_quantity").cast("long").alias("value"))
    return _least(rows.where("dst is not null"))


def copurchase(spark: SparkSession, d: str) -> DataFrame:
    parts = table(spark, d, "lineitem").select("l_orderkey", "l_partkey").distinct()
    a, b = parts.withColumnRenamed("l_partkey", "src"), parts.withColumnRenamed("l_partkey", "dst")
    return a.join(b, "l_orderkey").where("src <> dst").select("src", "dst").distinct().withColumn("value", F.lit(1).cast("long"))


def micros(column: str):
    return F.unix_micros(F.col(column).cast("timestamp"))


def followers(rows: DataFrame, keys: tuple[str, ...], at: str, tie: str, bucket: int) -> DataFrame:
    """rows (keys not null) with next: the struct (at, tie, all other columns of rows) of the row that follows in its group of keys, ordered by
    at and tie; the last of a group has none.

    A group is cut into buckets of at, so none is sorted in one task: a row's follower is in its bucket, or the first of the
    next bucket that the group has."""
    given = [at, tie, *(c for c in rows.columns if c not in (at, tie))]
    cut = rows.withColumn("_b", F.floor(F.col(at) / bucket)).withColumn("_me", F.struct(*given))
    inside = cut.withColumn("_next", F.lead("_me").over(W.partitionBy(*keys, "_b").orderBy(at, tie)))
    heads = cut.groupBy(*keys, "_b").agg(F.min("_me").alias("_first"))
    after = heads.select(*keys, "_b", F.lead("_first").over(W.partitionBy(*keys).orderBy("_b")).alias("_after"))
    return inside.join(after, [*keys, "_b"]).select(*rows.columns, F.coalesce("_next", "_after").alias("next"))


_SECOND, _MINUTE = 1_000_000, 60_000_000


def handoff(spark: SparkSession, d: str) -> DataFrame:
    events = table(spark, d, "events").select("event_id", "user_id", F.to_date("ts").alias("day"), micros("ts").alias("at"))
    found = followers(events, ("day",), "at", "event_id", _MINUTE).where("next is not null")
    seconds = lambda c: F.expr(f"{c} div {_SECOND}")
    return _least(found.select(F.col("user_id").alias("src"), F.col("next.user_id").alias("dst"), (seconds("next.at") - seconds("at")).alias("value")))


def timeline(spark: SparkSession, d: str) -> DataFrame:
    events = table(spark, d, "events").select("event_id", "user_id", "event_type", F.to_date("ts").alias("day"), micros("ts").alias("at"))

    def follow(keys: tuple[str, ...], bucket: int) -> DataFrame:
        found = followers(events, keys, "at", "event_id", bucket).where("next is not null")
        return found.select(F.col("event_id").alias("src"), F.col("next.event_id").alias("dst"), (F.col("next.at") - F.col("at")).alias("value"))

    return _least(follow(("user_id",), 1440 * _MINUTE).unionByName(follow(("event_type", "day"), _MINUTE)))


def trade(spark: SparkSession, d: str) -> DataFrame:
    lines = table(spark, d, "lineitem").select("l_orderkey", "l_suppkey")
    sellers = table(spark, d, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), F.col("s_nationkey").cast("long").alias("src"))
    buyers = table(spark, d, "customer").select(F.col("c_custkey").alias("o_custkey"), F.col("c_nationkey").cast("long").alias("dst"))
    orders = table(spark, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
    return lines.join(orders, "l_orderkey").join(buyers, "o_custkey").join(sellers, "l_suppkey").where("src <> dst").groupBy("src", "dst").agg(F.count("*").alias("value"))


def ratings(spark: SparkSession, d: str) -> DataFrame:
    """(user, item, rating)."""
    lines = table(spark, d, "lineitem").select("l_orderkey", "l_partkey", "l_quantity")
    orders = table(spark, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("user"))
    return lines.join(orders, "l_orderkey").groupBy("user", F.col("l_partkey").alias("item")).agg(F.ceil(F.avg("l_quantity") / 10).cast("int").alias("rating"))


def page_links(spark: SparkSession, d: str) -> DataFrame:
    """(page_id, path): distinct relative link targets."""
    found = F.explode(F.regexp_extract_all("html", F.lit(LINK), F.lit(1)))
    return table(spark, d, "pages").select("page_id", found.alias("path")).where("path like '/%'").distinct()


def links(spark: SparkSession, d: str) -> DataFrame:
    """page 2*page_id -> path 2*number+1; paths are numbered in their order."""
    from vertexalg.graphs.ids import encode_ids

    pairs = page_links(spark, d)
    return pairs.join(encode_ids(pairs, "path").withColumnRenamed("key", "path"), "path").select((F.col("page_id") * 2).alias("src"), (F.col("vid") * 2 + 1).alias("dst"), F.lit(1).cast("long").alias("value"))


def colink(spark: SparkSession, d: str) -> DataFrame:
    pairs = page_links(spark, d)
    a, b = pairs.withColumnRenamed("page_id", "src"), pairs.withColumnRenamed("page_id", "dst")
    return a.join(b, "path").where("src <> dst").select("src", "dst").distinct().withColumn("value", F.lit(1).cast("long"))


def turns(spark: SparkSession, d: str) -> DataFrame:
    order = W.partitionBy("conv_id").orderBy("turn")
    rows = table(spark, d, "conversations").select((F.col("conv_id") * 100 + F.col("turn")).alias("src"), (F.col("conv_id") * 100 + F.lead("turn").over(order)).alias("dst"), F.length("text").cast("long").alias("value"))
    return rows.where("dst is not null")


def shared_lines(docs: DataFrame) -> DataFrame:
    """Edges between documents (doc_id, text) that share a trimmed line of 20 characters or more: each with the least
    one that has the line, both ways. A line's documents are a star: as many edges as documents, that connects what all its pairs would."""
    lines = docs.where("text is not null").select("doc_id", F.explode(F.split("text", "\n")).alias("line"))
    rows = lines.select("doc_id", F.trim("line").alias("line")).where(F.length("line") >= SHARED_LINE).select("doc_id", F.sha2("line", 256).alias("line")).distinct()
    stars = rows.join(rows.groupBy("line").agg(F.min("doc_id").alias("least")), "line").where("doc_id <> least")
    ends = F.array(F.struct(F.col("doc_id").alias("src"), F.col("least").alias("dst")), F.struct(F.col("least").alias("src"), F.col("doc_id").alias("dst")))
    return stars.select("doc_id", "least").distinct().select(F.inline(ends)).distinct().withColumn("value", F.lit(1).cast("long"))


def docshare(spark: SparkSession, d: str) -> DataFrame:
    return shared_lines(table(spark, d, "documents"))


def knn(spark: SparkSession, d: str) -> DataFrame:
    """The mesh of the 8 nearest vectors of every vector; weight: 1 - cosine in millionths."""
    from vertexalg.operators.knn import nearest_vectors

    near = nearest_vectors(table(spark, d, "embeddings").select("vec_id", "embedding"), NEIGHBOURS)
    return near.select("src", "dst", F.round((1 - F.col("value")) * 1_000_000).cast("long").alias("value"))


def page_vertices(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "pages").select(F.col("page_id").alias("vid"))


def turn_vertices(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "conversations").select((F.col("conv_id") * 100 + F.col("turn")).alias("vid"))


def document_vertices(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "documents").select(F.col("doc_id").alias("vid"))


_NEXT = "lead({x}) over (partition by {k} order by {o})"
_LEAST = "select src, dst, min(value) as value from ({q}) where dst is not null and src <> dst group by src, dst"
_PAGE_LINKS = f"select distinct page_id, path from (select page_id, unnest(regexp_extract_all(html, '{LINK}', 1)) as path from pages) where path like '/%'"

#: The 8 nearest of every vector by cosine (ties of 9 digits to the smaller id), in 6 digits.
KNN_SQL = f"with v as materialized (select vec_id, embedding::double[] as x from embeddings), p as (select a.vec_id as src, b.vec_id as dst, list_cosine_similarity(a.x, b.x) as c from v a join v b on a.vec_id <> b.vec_id), r as (select *, row_number() over (partition by src order by round(c, 9) desc, dst) as r from p) select src, dst, round(c, 6) as value from r where r <= {NEIGHBOURS}"


def docshare_sql(documents: str) -> str:
    """Stars of shared lines among the rows of documents (a table, or a query in brackets)."""
    return (
        f"with l as materialized (select distinct doc_id, line from (select doc_id, trim(unnest(string_split(text, chr(10))), ' ') as line from {documents}) where length(line) >= {SHARED_LINE}), "
        "s as (select distinct doc_id, least from l join (select line, min(doc_id) as least from l group by line) using (line) where doc_id <> least) "
        "select distinct src, dst, 1::bigint as value from (select doc_id as src, least as dst from s union all select least, doc_id from s)"
    )


#: Edge SQL (src, dst, value) by graph.
SQL: dict[str, str] = {
    "basket_chain": _LEAST.format(q="select l_partkey as src, " + _NEXT.format(x="l_partkey", k="l_orderkey", o="l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice") + " as dst, cast(l_quantity as bigint) as value from lineitem"),
    "copurchase": "select distinct a.l_partkey as src, b.l_partkey as dst, 1::bigint as value from lineitem a join lineitem b using (l_orderkey) where a.l_partkey <> b.l_partkey",
    "handoff": _LEAST.format(q="select user_id as src, " + _NEXT.format(x="user_id", k="ts::date", o="ts, event_id") + " as dst, " + _NEXT.format(x="epoch_us(ts) // 1000000", k="ts::date", o="ts, event_id") + " - epoch_us(ts) // 1000000 as value from events"),
    "timeline": _LEAST.format(q=" union all ".join("select event_id as src, " + _NEXT.format(x="event_id", k=k, o="ts, event_id") + " as dst, " + _NEXT.format(x="epoch_us(ts)", k=k, o="ts, event_id") + " - epoch_us(ts) as value from events" for k in ("user_id", "event_type, ts::date"))),
    "trade": "select s_nationkey::bigint as src, c_nationkey::bigint as dst, count(*) as value from lineitem join orders on l_orderkey = o_orderkey join customer on c_custkey = o_custkey join supplier on s_suppkey = l_suppkey where s_nationkey <> c_nationkey group by all",
    "links": f"select page_id * 2 as src, (dense_rank() over (order by path) - 1) * 2 + 1 as dst, 1::bigint as value from ({_PAGE_LINKS})",
    "colink": f"with l as ({_PAGE_LINKS}) select distinct a.page_id as src, b.page_id as dst, 1::bigint as value from l a join l b using (path) where a.page_id <> b.page_id",
    "turns": "select * from (select conv_id * 100 + turn as src, conv_id * 100 + " + _NEXT.format(x="turn", k="conv_id", o="turn") + " as dst, length(text)::bigint as value from conversations) where dst is not null",
    "docshare": docshare_sql("documents"),
    "knn": f"select src, dst, cast(round((1 - value) * 1000000) as bigint) as value from ({KNN_SQL})",
    "rmat": rmat_sql(10, RMAT_RANK)[1:-1],
    "rmat_tri": rmat_sql(10, RMAT_TRI)[1:-1],
    "rmat_path": rmat_sql(10, RMAT_PATH)[1:-1],
}
RATINGS_SQL = "select o_custkey as \"user\", l_partkey as item, cast(ceil(avg(l_quantity) / 10) as int) as rating from lineitem join orders on l_orderkey = o_orderkey group by all"
#: Vertices beyond the ends of edges.
VERTEX_SQL: dict[str, str] = {"colink": "select page_id as vid from pages", "turns": "select conv_id * 100 + turn as vid from conversations", "docshare": "select doc_id as vid from documents"}
SYMMETRIC = ("copurchase", "colink", "docshare")

_EDGES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (basket_chain, copurchase, handoff, timeline, trade, links, colink, turns, docshare, knn)}
_VERTICES = {"colink": page_vertices, "turns": turn_vertices, "docshare": document_vertices}
_RMAT = {"rmat": RMAT_RANK, "rmat_tri": RMAT_TRI, "rmat_path": RMAT_PATH}
NAMES = (*_EDGES, *_RMAT)


def order_picks(spark: SparkSession, d: str, name: str, conf: EngineConf = EngineConf()) -> Graph:
    """The generated graph of that name with a pick for every order instead of every number."""
    return rmat(spark, 10, _RMAT[name], conf=conf, picks=table(spark, d, "orders").select(F.col("o_orderkey").alias("id")))


ORDER_PICKS_SQL = {name: rmat_sql(10, shares, picks="select o_orderkey as id from orders")[1:-1] for name, shares in _RMAT.items()}


def customer_ratings(spark: SparkSession, d: str) -> DataFrame:
    """(user, item, rating) of every customer, made as the synthetic ratings are: 200 items, 10 picks a customer on average."""
    return synthetic_ratings(spark, table(spark, d, "customer").select(F.col("c_custkey").alias("id")), 200, 10)


CUSTOMER_RATINGS_SQL = synthetic_ratings_sql("select c_custkey as id from customer", 200, 10)[1:-1]


def edges(spark: SparkSession, d: str, name: str) -> DataFrame:
    return rmat(spark, 10, _RMAT[name]).edges if name in _RMAT else _EDGES[name](spark, d).select("src", "dst", "value")


def graph(spark: SparkSession, d: str, name: str, conf: EngineConf = EngineConf()) -> Graph:
    vertices = _VERTICES[name](spark, d) if name in _VERTICES else None
    return Graph.from_edges(edges(spark, d, name), value="value", directed=name not in SYMMETRIC, vertices=vertices, conf=conf)


def vertex_sql(name: str) -> str:
    return VERTEX_SQL.get(name) or f"select src as vid from ({SQL[name]}) union select dst from ({SQL[name]})"
