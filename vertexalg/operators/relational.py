"""The relational surface around the programs: building graphs from tables, feeding programs, reporting results.

Each operator is a function of (spark, folder) with the SQL that must give the same rows.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vertexalg.algorithms.bfs import bfs
from vertexalg.algorithms.components import components
from vertexalg.algorithms.pagerank import pagerank
from vertexalg.functions.vectors import wide
from vertexalg.graphs import derive, twins
from vertexalg.graphs.graph import Graph
from vertexalg.oracles import methods as S
from vertexalg.sources.tables import table

OPERATORS: list[tuple[str, Callable[[SparkSession, str], DataFrame], str | None]] = []
_CHAIN = derive.SQL["basket_chain"]
_RANKS = S.rank(_CHAIN, derive.vertex_sql("basket_chain"))
_DEGREES = f"select coalesce(a.vid, b.vid) as vid, coalesce(o, 0) as o, coalesce(i, 0) as i from (select src as vid, count(*) as o from ({_CHAIN}) group by src) a full join (select dst as vid, count(*) as i from ({_CHAIN}) group by dst) b on a.vid = b.vid"


def operator(name: str, sql: str | None):
    def add(fn):
        OPERATORS.append((name, fn, sql))
        return fn

    return add


def _ranks(s: SparkSession, d: str) -> DataFrame:
    return pagerank(derive.graph(s, d, "basket_chain")).select("vid", F.round("rank", 6).alias("rank"))


def _degrees(s: SparkSession, d: str) -> DataFrame:
    e = derive.basket_chain(s, d)
    out = e.groupBy(F.col("src").alias("vid")).agg(F.count("*").alias("o"))
    into = e.groupBy(F.col("dst").alias("vid")).agg(F.count("*").alias("i"))
    return out.join(into, "vid", "full").na.fill(0, ["o", "i"])


def _levels(s: SparkSession, d: str, name: str) -> DataFrame:
    if name == "colink":
        return twins.levels(twins.twins(s, d))
    g = derive.graph(s, d, name)
    return bfs(g, g.edges.agg(F.min("src")).first()[0]).select("vid", "level")


def _levels_sql(name: str) -> str:
    return S.paths(S.symmetric(derive.SQL[name]), derive.vertex_sql(name), f"select min(src) from ({derive.SQL[name]})", "1", "level")


# ---------------------------------------------------------------- scans, filters, projections


@operator("scan_edges", "select l_orderkey, l_partkey, l_linenumber, l_quantity from lineitem")
def scan_edges(s, d):
    return table(s, d, "lineitem").select("l_orderkey", "l_partkey", "l_linenumber", "l_quantity")


@operator("edges_filtered", f"select src, dst, value from ({_CHAIN}) where value between 10 and 20 and src <> dst")
def edges_filtered(s, d):
    return derive.basket_chain(s, d).where("src <> dst and value is not null").where(F.col("value").between(10, 20)).select("src", "dst", "value")


@operator("subgraph_brand", f"with p as (select p_partkey from part where p_brand = (select min(p_brand) from part)) select src, dst, value from ({_CHAIN}) where src in (select * from p) and dst in (select * from p)")
def subgraph_brand(s, d):
    parts = table(s, d, "part").select(F.col("p_partkey").alias("vid"), "p_brand")
    brand = parts.agg(F.min("p_brand")).first()[0]
    return Graph(derive.basket_chain(s, d), parts).subgraph(F.col("p_brand") == brand).edges


@operator("subgraph_language", f"with p as (select page_id from pages where url like '%/fr/%') select src, dst, value from ({derive.SQL['colink']}) where src in (select * from p) and dst in (select * from p)")
def subgraph_language(s, d):
    pages = table(s, d, "pages").select(F.col("page_id").alias("vid"), "url")
    return Graph(derive.colink(s, d), pages).subgraph(F.col("url").like("%/fr/%")).edges


@operator("rank_buckets", f"select case when rank < 0.8 then 'low' when rank < 1.2 then 'middle' else 'high' end as bucket, count(*) as vertices from ({_RANKS}) group by all")
def rank_buckets(s, d):
    bucket = F.when(F.col("rank") < 0.8, "low").when(F.col("rank") < 1.2, "middle").otherwise("high")
    return _ranks(s, d).groupBy(bucket.alias("bucket")).agg(F.count("*").alias("vertices"))


@operator("links_like", f"select page_id, path from ({derive._PAGE_LINKS}) where path like '/%' and regexp_matches(path, '^/[A-Z]') and path not in ('/The', '/And')")
def links_like(s, d):
    return derive.page_links(s, d).where(F.col("path").like("/%") & F.col("path").rlike("^/[A-Z]") & ~F.col("path").isin("/The", "/And"))


# ---------------------------------------------------------------- joins


def _rating_join(hint: str):
    def run(s, d):
        orders = table(s, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
        lines = table(s, d, "lineitem").select("l_orderkey", "l_partkey")
        # the broadcast form is for tables whose size is known to be small, as customer's nations are
        small = table(s, d, "nation").select(F.col("n_nationkey").alias("c_nationkey"), "n_name")
        people = table(s, d, "customer").select(F.col("c_custkey").alias("o_custkey"), "c_nationkey")
        named = people.join(F.broadcast(small) if hint == "broadcast" else small.hint(hint), "c_nationkey")
        joined = lines.join(orders if hint == "broadcast" else orders.hint(hint), "l_orderkey").join(named, "o_custkey")
        return joined.groupBy("n_name").agg(F.count("*").alias("lines"), F.count_distinct("l_partkey").alias("parts"))

    return run


_RATING_JOIN = "select n_name, count(*) as lines, count(distinct l_partkey) as parts from lineitem join orders on l_orderkey = o_orderkey join customer on c_custkey = o_custkey join nation on n_nationkey = c_nationkey group by n_name"
for _name, _hint in (("shj", "shuffle_hash"), ("smj", "merge"), ("bhj", "broadcast")):
    operator(f"join_rating_{_name}", _RATING_JOIN)(_rating_join(_hint))


@operator("rank_with_names", f"select p_partkey, p_name, coalesce(rank, 0.15) as rank from part left join ({_RANKS}) on vid = p_partkey")
def rank_with_names(s, d):
    parts = table(s, d, "part").select("p_partkey", "p_name")
    return parts.join(_ranks(s, d), F.col("vid") == F.col("p_partkey"), "left").select("p_partkey", "p_name", F.coalesce("rank", F.lit(0.15)).alias("rank"))


@operator("degree_in_out", _DEGREES)
def degree_in_out(s, d):
    return _degrees(s, d)


@operator("degree_right_outer", f"select p_partkey as vid, coalesce(i, 0) as i from (select dst, count(*) as i from ({_CHAIN}) where value > 45 group by dst) right join part on dst = p_partkey")
def degree_right_outer(s, d):
    into = derive.basket_chain(s, d).where("value > 45").groupBy("dst").agg(F.count("*").alias("i"))
    return into.join(table(s, d, "part").select("p_partkey"), F.col("dst") == F.col("p_partkey"), "right").select(F.col("p_partkey").alias("vid"), F.coalesce("i", F.lit(0)).alias("i"))


@operator("active_edges", f"select src, dst, value from ({_CHAIN}) where src in (select vid from ({_levels_sql('basket_chain')}) where level = 1)")
def active_edges(s, d):
    front = _levels(s, d, "basket_chain").where("level = 1").select(F.col("vid").alias("src"))
    return derive.basket_chain(s, d).join(front, "src", "left_semi").select("src", "dst", "value")


@operator("unreached", f"select vid from ({_levels_sql('colink')}) where level is null")
def unreached(s, d):
    found = _levels(s, d, "colink").where("level is not null")
    return derive.page_vertices(s, d).join(found, "vid", "left_anti")


@operator("copurchase_pairs", f"select src as u, dst as v from ({derive.SQL['copurchase']}) where src < dst")
def copurchase_pairs(s, d):
    parts = table(s, d, "lineitem").select("l_orderkey", "l_partkey").distinct()
    a, b = parts.withColumnRenamed("l_partkey", "u"), parts.withColumnRenamed("l_partkey", "v")
    return a.join(b, "l_orderkey").where("u < v").select("u", "v").distinct()


@operator("nation_pairs", "select a.n_name as seller, b.n_name as buyer from nation a, nation b where a.n_regionkey < b.n_regionkey")
def nation_pairs(s, d):
    """A fixed table of 25 rows on both sides: the one place for a nested loop."""
    n = table(s, d, "nation").select("n_name", "n_regionkey")
    a, b = n.toDF("seller", "ra"), n.toDF("buyer", "rb")
    return a.join(F.broadcast(b), F.col("ra") < F.col("rb")).select("seller", "buyer")


@operator("events_within_window", "select a.event_id as a, b.event_id as b from events a join events b on a.user_id = b.user_id and b.ts > a.ts and epoch_us(b.ts) - epoch_us(a.ts) <= 3600 * 1000000::bigint")
def events_within_window(s, d):
    """Pairs of one user's events up to an hour apart; both sides are cut into bins of an hour, so an equi-join finds them."""
    width = 3600 * 1_000_000
    e = table(s, d, "events").select("event_id", "user_id", derive.micros("ts").alias("at"))
    own = e.select("user_id", F.col("event_id").alias("a"), F.col("at").alias("ta"), F.explode(F.array(F.expr(f"at div {width}"), F.expr(f"at div {width}") + 1)).alias("bin"))
    other = e.select("user_id", F.col("event_id").alias("b"), F.col("at").alias("tb"), F.expr(f"at div {width}").alias("bin"))
    return own.join(other, ["user_id", "bin"]).where((F.col("tb") > F.col("ta")) & (F.col("tb") - F.col("ta") <= width)).select("a", "b")


@operator("asof_prev_event", "with c as (select e.event_id, e.user_id, e.ts from events e where event_type = (select max(event_type) from events)), p as (select * from events where event_type <> (select max(event_type) from events)) select c.event_id, p.event_id as before from c asof left join p on c.user_id = p.user_id and c.ts > p.ts")
def asof_prev_event(s, d):
    """For each event of the last kind the latest earlier one of another kind of the same user: one sort per user, no join."""
    e = table(s, d, "events").select("event_id", "user_id", "ts", "event_type")
    kind = e.agg(F.max("event_type")).first()[0]
    ask = F.col("event_type") == kind
    order = W.partitionBy("user_id").orderBy("ts").rowsBetween(W.unboundedPreceding, -1)
    return e.withColumn("before", F.last(F.when(~ask, F.col("event_id")), ignorenulls=True).over(order)).where(ask).select("event_id", "before")


@operator("tri_join", S.triangle_rows(derive.SQL["trade"]))
def tri_join(s, d):
    from vertexalg.algorithms.triangles import triangle_list

    return triangle_list(derive.graph(s, d, "trade"))


@operator("changed_vertices", f"with v as ({derive.vertex_sql('colink')}), a as (select vid, null::bigint as x from v), b as ({_levels_sql('colink')}) select a.vid from a join b using (vid) where a.x is distinct from b.level")
def changed_vertices(s, d):
    old = derive.page_vertices(s, d).select("vid", F.lit(None).cast("long").alias("x"))
    return old.join(_levels(s, d, "colink"), "vid").where(~F.col("x").eqNullSafe(F.col("level"))).select("vid")


@operator("top_edges_lateral", f"with e as materialized ({_CHAIN}), n as (select l.* from part p, lateral (select src, dst, value from e where e.src = p.p_partkey order by value desc, dst limit 2) l) select * from n")
def top_edges_lateral(s, d):
    e = derive.basket_chain(s, d).select("src", "dst", "value")
    e.createOrReplaceTempView("_lateral_edges")
    table(s, d, "part").select("p_partkey").createOrReplaceTempView("_lateral_parts")
    return s.sql("select l.src, l.dst, l.value from _lateral_parts p, lateral (select src, dst, value from _lateral_edges e where e.src = p.p_partkey order by value desc, dst limit 2) l")


# ---------------------------------------------------------------- aggregation


@operator("edge_weight_summary", f"select src, count(*) as n, sum(value)::bigint as total, min(value) as lo, max(value) as hi, round(avg(value), 6) as mean from ({_CHAIN}) group by src")
def edge_weight_summary(s, d):
    return derive.basket_chain(s, d).groupBy("src").agg(F.count("*").alias("n"), F.sum("value").alias("total"), F.min("value").alias("lo"), F.max("value").alias("hi"), F.round(F.avg("value"), 6).alias("mean"))


@operator("nbr_list", f"select dst as vid, array_to_string(list_sort(list(distinct src)), ',') as neighbors from ({_CHAIN}) group by dst")
def nbr_list(s, d):
    lists = derive.basket_chain(s, d).groupBy(F.col("dst").alias("vid")).agg(F.array_sort(F.collect_set("src")).alias("l"))
    return lists.select("vid", F.array_join(F.transform("l", lambda x: x.cast("string")), ",").alias("neighbors"))


@operator("distinct_nbrs", "select l_orderkey, count(distinct l_partkey) as parts from lineitem group by l_orderkey")
def distinct_nbrs(s, d):
    return table(s, d, "lineitem").groupBy("l_orderkey").agg(F.count_distinct("l_partkey").alias("parts"))


@operator("approx_nbrs", None)
def approx_nbrs(s, d):
    return table(s, d, "lineitem").groupBy("l_suppkey").agg(F.approx_count_distinct("l_partkey").alias("parts"))


_TRADE_NAMED = f"select r.r_name as region, n.n_name as nation, value from ({derive.SQL['trade']}) join nation n on n.n_nationkey = src join region r on r.r_regionkey = n.n_regionkey"


def _trade_named(s, d):
    nation = table(s, d, "nation").select(F.col("n_nationkey").cast("long").alias("src"), F.col("n_name").alias("nation"), "n_regionkey")
    region = table(s, d, "region").select(F.col("r_regionkey").alias("n_regionkey"), F.col("r_name").alias("region"))
    return derive.trade(s, d).join(nation, "src").join(region, "n_regionkey")


@operator("trade_rollup", f"select region, nation, sum(value)::bigint as lines from ({_TRADE_NAMED}) group by rollup (region, nation)")
def trade_rollup(s, d):
    return _trade_named(s, d).rollup("region", "nation").agg(F.sum("value").alias("lines"))


@operator("trade_cube", f"select region, nation, sum(value)::bigint as lines from ({_TRADE_NAMED}) group by cube (region, nation)")
def trade_cube(s, d):
    return _trade_named(s, d).cube("region", "nation").agg(F.sum("value").alias("lines"))


@operator("trade_gsets", f"select region, nation, sum(value)::bigint as lines, grouping_id(region, nation)::bigint as g from ({_TRADE_NAMED}) group by grouping sets ((region), (nation), ())")
def trade_gsets(s, d):
    _trade_named(s, d).createOrReplaceTempView("_trade_named")
    return s.sql("select region, nation, sum(value) as lines, grouping_id(region, nation) as g from _trade_named group by grouping sets ((region), (nation), ())")


@operator("frontier_bitmap", f"select word_no, (case when b >= 9223372036854775808 then b - 18446744073709551616 else b end)::bigint as bits, ids from (select vid // 64 as word_no, bit_or(1::hugeint << (vid % 64)::int) as b, count(*) as ids from ({_levels_sql('basket_chain')}) where level = 2 group by all)")
def frontier_bitmap(s, d):
    from vertexalg.matrix.vectors import BitmapVector

    front = _levels(s, d, "basket_chain").where("level = 2").select("vid", F.lit(1).alias("val"))
    return BitmapVector.of(front).df.select("word_no", "bits", F.bit_count("bits").cast("long").alias("ids"))


@operator("degree_pct", f"select round(quantile_cont(o, 0.5), 6) as p50, round(quantile_cont(o, 0.9), 6) as p90, round(quantile_cont(i, 0.99), 6) as p99_in, round(stddev_samp(o), 6) as sd from ({_DEGREES})")
def degree_pct(s, d):
    return _degrees(s, d).agg(F.round(F.percentile("o", F.lit(0.5)), 6).alias("p50"), F.round(F.percentile("o", F.lit(0.9)), 6).alias("p90"), F.round(F.percentile("i", F.lit(0.99)), 6).alias("p99_in"), F.round(F.stddev_samp("o"), 6).alias("sd"))


@operator("degree_pct_approx", None)
def degree_pct_approx(s, d):
    return _degrees(s, d).agg(F.percentile_approx("o", 0.5).alias("p50"), F.skewness("o").alias("skew"))


@operator("level_by_brand", f"select p_brand, count(*) filter (level = 1) as l1, count(*) filter (level = 2) as l2, count(*) filter (level = 3) as l3 from ({_levels_sql('basket_chain')}) join part on vid = p_partkey where level in (1, 2, 3) group by p_brand")
def level_by_brand(s, d):
    brand = table(s, d, "part").select(F.col("p_partkey").alias("vid"), "p_brand")
    wide_ = _levels(s, d, "basket_chain").join(brand, "vid").groupBy("p_brand").pivot("level", [1, 2, 3]).agg(F.count("vid"))
    return wide_.where("`1` is not null or `2` is not null or `3` is not null").select("p_brand", *(F.coalesce(F.col(f"`{i}`"), F.lit(0)).alias(f"l{i}") for i in (1, 2, 3)))


@operator("geomean_degree", f"select round(exp(avg(ln(o))), 6) as geomean from ({_DEGREES}) where o > 0")
def geomean_degree(s, d):
    from vertexalg.measures.timing import geomean

    return _degrees(s, d).where("o > 0").agg(F.round(geomean("o"), 6).alias("geomean"))


@operator("hubs", f"select dst as vid, count(*) as i from ({_CHAIN}) group by dst having count(*) > 30")
def hubs(s, d):
    return derive.basket_chain(s, d).groupBy(F.col("dst").alias("vid")).agg(F.count("*").alias("i")).where("i > 30")


# ---------------------------------------------------------------- windows


def _ranked(name: str, make: Callable, sql: str) -> None:
    @operator(name, f"select vid, p_brand, {sql.format('over (partition by p_brand order by rank desc, vid)')} as r from ({_RANKS}) join part on vid = p_partkey")
    def run(s, d):
        order = W.partitionBy("p_brand").orderBy(F.desc("rank"), "vid")
        brand = table(s, d, "part").select(F.col("p_partkey").alias("vid"), "p_brand")
        return _ranks(s, d).join(brand, "vid").select("vid", "p_brand", make().over(order).alias("r"))


_ranked("window_row_number", F.row_number, "cast(row_number() {} as int)")
_ranked("window_rank", F.rank, "cast(rank() {} as int)")
_ranked("window_dense_rank", F.dense_rank, "cast(dense_rank() {} as int)")
_ranked("window_ntile", lambda: F.ntile(4), "cast(ntile(4) {} as int)")
_ranked("window_percent_rank", F.percent_rank, "percent_rank() {}")
_ranked("window_cume_dist", F.cume_dist, "cume_dist() {}")


@operator("cum_degree", f"select p_brand, vid, sum(o) over (partition by p_brand order by vid rows between unbounded preceding and current row)::bigint as upto, sum(o) over (partition by p_brand order by vid range between 100 preceding and current row)::bigint as near from ({_DEGREES}) join part on vid = p_partkey")
def cum_degree(s, d):
    brand = table(s, d, "part").select(F.col("p_partkey").alias("vid"), "p_brand")
    order = W.partitionBy("p_brand").orderBy("vid")
    rows = _degrees(s, d).join(brand, "vid")
    return rows.select("p_brand", "vid", F.sum("o").over(order.rowsBetween(W.unboundedPreceding, 0)).alias("upto"), F.sum("o").over(order.rangeBetween(-100, 0)).alias("near"))


@operator("user_first_last", "select distinct user_id, first_value(event_id) over w as first, last_value(event_id) over w as last, nth_value(event_id, 2) over w as second from events window w as (partition by user_id order by ts rows between unbounded preceding and unbounded following)")
def user_first_last(s, d):
    order = W.partitionBy("user_id").orderBy("ts").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    return table(s, d, "events").select("user_id", F.first("event_id").over(order).alias("first"), F.last("event_id").over(order).alias("last"), F.nth_value("event_id", 2).over(order).alias("second")).distinct()


_SESSIONS = "with g as (select user_id, ts, case when epoch_us(ts) - epoch_us(lag(ts) over w) < 6 * 3600 * 1000000::bigint then 0 else 1 end as new from events window w as (partition by user_id order by ts)), s as (select user_id, ts, sum(new) over (partition by user_id order by ts rows unbounded preceding) as k from g) select user_id, epoch_us(min(ts)) as start, count(*) as events from s group by user_id, k"


@operator("user_sessions", _SESSIONS)
def user_sessions_(s, d):
    e = table(s, d, "events").select("user_id", derive.micros("ts").alias("at"))
    order = W.partitionBy("user_id").orderBy("at")
    new = F.when(F.col("at") - F.lag("at").over(order) < 6 * 3600 * 1_000_000, 0).otherwise(1)
    named = e.withColumn("new", new).withColumn("k", F.sum("new").over(order.rowsBetween(W.unboundedPreceding, 0)))
    return named.groupBy("user_id", "k").agg(F.min("at").alias("start"), F.count("*").alias("events")).select("user_id", "start", "events")


@operator("user_sessions_stream", _SESSIONS)
def user_sessions_stream(s, d):
    """The streaming form on the same rows as a batch."""
    from vertexalg.streaming.edges import user_sessions

    rows = table(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return user_sessions(rows).withColumn("start", F.unix_micros("start"))


def _window_degree(size: str, slide: str | None):
    from vertexalg.streaming.edges import window_degree

    def run(s, d):
        rows = table(s, d, "events").select(F.col("ts").cast("timestamp").alias("ts"), F.col("user_id").alias("src"))
        return window_degree(rows, size, slide).withColumn("start", F.unix_micros("start"))

    return run


operator("deg_tumbling", "select epoch_us(date_trunc('day', ts)) as start, user_id as vid, count(*) as degree from events group by all")(_window_degree("1 day", None))
operator("deg_sliding", "with w as (select user_id, (epoch_us(ts) // 21600000000 - unnest(range(4))) * 21600000000 as start from events) select start, user_id as vid, count(*) as degree from w group by all")(_window_degree("1 day", "6 hours"))


@operator("stream_edges", "select event_id, user_id as src from events")
def stream_edges_(s, d):
    from vertexalg.streaming.edges import stream_edges

    return stream_edges(table(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))).select("event_id", "src")


# ---------------------------------------------------------------- order, limits, sets


@operator("pr_top20", f"select vid, rank from ({_RANKS}) order by rank desc, vid limit 20")
def pr_top20(s, d):
    return _ranks(s, d).orderBy(F.desc("rank"), "vid").limit(20)


@operator("page_of_ranks", f"select vid, rank from ({_RANKS}) order by rank desc, vid limit 20 offset 40")
def page_of_ranks(s, d):
    return _ranks(s, d).orderBy(F.desc("rank"), "vid").offset(40).limit(20)


@operator("top_edges_per_vertex", f"select src, dst, value from (select *, row_number() over (partition by src order by value desc, dst) as r from ({_CHAIN})) where r <= 3")
def top_edges_per_vertex(s, d):
    order = W.partitionBy("src").orderBy(F.desc("value"), "dst")
    return derive.basket_chain(s, d).withColumn("r", F.row_number().over(order)).where("r <= 3").select("src", "dst", "value")


@operator("sym_edges", f"select src, dst from ({_CHAIN}) union select dst, src from ({_CHAIN})")
def sym_edges(s, d):
    e = derive.basket_chain(s, d)
    return e.select("src", "dst").unionByName(e.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()


@operator("common_edges", f"select src, dst from ({_CHAIN}) intersect select src, dst from ({derive.SQL['copurchase']})")
def common_edges(s, d):
    return derive.basket_chain(s, d).select("src", "dst").intersect(derive.copurchase(s, d).select("src", "dst"))


@operator("one_way_edges", f"select src, dst from ({_CHAIN}) except select dst, src from ({_CHAIN})")
def one_way_edges(s, d):
    e = derive.basket_chain(s, d)
    return e.select("src", "dst").exceptAll(e.select(F.col("dst").alias("src"), F.col("src").alias("dst")))


# ---------------------------------------------------------------- functions


@operator("page_hosts", "select regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) as host, count(*) as pages, max(length(url)) as longest from pages group by all")
def page_hosts(s, d):
    return table(s, d, "pages").select(F.parse_url("url", F.lit("HOST")).alias("host"), F.length("url").cast("long").alias("n")).groupBy("host").agg(F.count("*").alias("pages"), F.max("n").alias("longest"))


@operator("event_props", "select event_type, sum(cast(json_extract_string(props, '$.k') as bigint))::bigint as k, count(*) as n from events group by event_type")
def event_props(s, d):
    k = F.from_json("props", "k bigint")["k"]
    return table(s, d, "events").groupBy("event_type").agg(F.sum(k).alias("k"), F.count("*").alias("n"))


@operator("nbr_overlap", f"with l as (select dst as vid, list(distinct src) as n from ({_CHAIN}) group by dst) select e.src, e.dst, len(list_intersect(a.n, b.n)) as shared from ({_CHAIN}) e join l a on a.vid = e.src join l b on b.vid = e.dst")
def nbr_overlap(s, d):
    e = derive.basket_chain(s, d)
    lists = e.groupBy(F.col("dst").alias("vid")).agg(F.collect_set("src").alias("n"))
    a, b = lists.select(F.col("vid").alias("src"), F.col("n").alias("na")), lists.select(F.col("vid").alias("dst"), F.col("n").alias("nb"))
    return e.join(a, "src").join(b, "dst").select("src", "dst", F.size(F.array_intersect("na", "nb")).cast("long").alias("shared"))


@operator("dot_product", "select a.vec_id, round(list_sum(list_transform(range(1, 65), lambda i: a.embedding[i]::double * b.embedding[i]::double)), 6) as dot from embeddings a join embeddings b on b.vec_id = a.vec_id + 1")
def dot_product(s, d):
    from vertexalg.functions.vectors import dot

    v = table(s, d, "embeddings").select("vec_id", wide("embedding").alias("a"))
    nxt = v.select((F.col("vec_id") - 1).alias("vec_id"), F.col("a").alias("b"))
    return v.join(nxt, "vec_id").select("vec_id", F.round(dot(F.col("a"), F.col("b")), 6).alias("dot"))


@operator("knn", derive.KNN_SQL)
def knn(s, d):
    """The mesh of the 8 nearest vectors of every vector."""
    from vertexalg.operators.knn import nearest_vectors

    return nearest_vectors(table(s, d, "embeddings").select("vec_id", "embedding"), derive.NEIGHBOURS)


def degree_maps(degree: DataFrame) -> DataFrame:
    """(g, m): the degrees (part, degree) as maps, one for each range of 64 parts, so that a map is small however many there are."""
    return degree.groupBy(F.col("part").bitwiseAND(~63).alias("g")).agg(F.map_from_entries(F.collect_list(F.struct("part", "degree"))).alias("m"))


@operator("degree_map", f"select dst as part, count(*) as degree, count(*) > 30 as busy from ({derive.SQL['basket_chain']}) group by dst")
def degree_map(s, d):
    """In-degrees as maps, read back by their keys."""
    degree = derive.basket_chain(s, d).groupBy(F.col("dst").alias("part")).agg(F.count("*").alias("degree"))
    busy = F.map_filter("m", lambda _, n: n > 30)
    read = degree_maps(degree).select("m", busy.alias("b"), F.explode(F.map_keys("m")).alias("part"))
    return read.select("part", F.element_at("m", F.col("part")).alias("degree"), F.map_contains_key("b", F.col("part")).alias("busy"))


_PIECES = "' ' || replace({}.text, chr(10), ' ') || ' '"


def _runs(pieces: str, n: int):
    """All runs of n pieces, each as one text."""
    return F.transform(F.sequence(F.lit(1), F.size(pieces) - (n - 1)), lambda i: F.array_join(F.slice(pieces, i, n), " "))


@operator("benchmark_hits", f"select doc_id, item_id from documents d join benchmark b on length(b.text) > 0 and contains({_PIECES.format('d')}, {_PIECES.format('b')})")
def benchmark_hits(s, d):
    """Documents that hold a whole passage, piece by piece (pieces are parted by spaces or ends of lines).

    A passage's first three pieces (or all, if fewer) are joined with the documents' runs of as many, then all of it is checked."""
    padded = F.concat(F.lit(" "), F.translate("text", "\n", " "), F.lit(" "))
    pieces = F.split(F.translate("text", "\n", " "), " ")
    items = table(s, d, "benchmark").where("length(text) > 0").select("item_id", padded.alias("passage"), pieces.alias("p"))
    items = items.withColumn("n", F.least(F.size("p"), F.lit(3))).select("item_id", "passage", "n", F.array_join(F.slice("p", F.lit(1), F.col("n")), " ").alias("key"))
    docs = table(s, d, "documents").where("text is not null").select("doc_id", "text")
    # the pieces are a column of their own: inside the lambda they would be split anew for every place
    cut = docs.select("doc_id", pieces.alias("w"))
    found = None
    for n in sorted(r[0] for r in items.select("n").distinct().collect()):  # three numbers at most
        keys = cut.where(F.size("w") >= n).select("doc_id", F.explode(F.array_distinct(_runs("w", n))).alias("key"))
        near = keys.join(items.where(F.col("n") == n), "key").select("doc_id", "item_id", "passage").distinct()
        hits = near.join(docs, "doc_id").where(F.contains(padded, F.col("passage"))).select("doc_id", "item_id")
        found = hits if found is None else found.unionByName(hits)
    return docs.join(items, F.lit(False)).select("doc_id", "item_id") if found is None else found


_GOOD = "select doc_id from labels where quality = 1"


@operator("docshare_quality", S.components(derive.docshare_sql(f"(select * from documents where doc_id in ({_GOOD}))"), f"select doc_id as vid from ({_GOOD})"))
def docshare_quality(s, d):
    labels = table(s, d, "labels").select(F.col("doc_id").alias("vid"), "quality")
    # ties among the good documents only: the middle of a star must be one of them
    good = labels.where("quality = 1").select(F.col("vid").alias("doc_id"))
    edges = derive.shared_lines(table(s, d, "documents").join(good, "doc_id", "left_semi"))
    return components(Graph(edges, labels, directed=False).subgraph(F.col("quality") == 1))
