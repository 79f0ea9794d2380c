"""Queries of the engine and the SQL that checks them."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vertexalg.algorithms import cf
from vertexalg.algorithms.bfs import bfs, bfs_levels
from vertexalg.algorithms.components import components
from vertexalg.algorithms.degrees import degree_histogram, degree_stats, in_degree, out_degree
from vertexalg.algorithms.pagerank import pagerank
from vertexalg.algorithms.sssp import shortest_paths, sssp, sssp_run
from vertexalg.algorithms.triangles import global_clustering, triangle_count, triangle_list
from vertexalg.conf import written
from vertexalg.graphs import derive, prep, twins
from vertexalg.graphs.graph import Graph
from vertexalg.oracles import methods as S

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def add(name: str, query: Query, sql: str | None = None) -> None:
    if name in QUERIES:
        raise ValueError(f"{name} is registered twice")
    QUERIES[name] = query
    if sql is not None:
        ORACLES[name] = sql


def root_of(edges: DataFrame) -> int:
    """The smallest source id: the root of all traversals."""
    return edges.agg(F.min("src")).first()[0]


def _root_sql(name: str) -> str:
    return f"select min(src) from ({derive.SQL[name]})"


def ranked(df: DataFrame) -> DataFrame:
    return df.select("vid", F.round("rank", 6).alias("rank"))


@contextmanager
def released(g: Graph) -> Iterator[Graph]:
    """The layouts of a query's graph go when its program has run: the result is read from the shared folder."""
    try:
        yield g
    finally:
        g.unpersist()


def rank_query(name: str, strategy: str = "auto", **options) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        with released(derive.graph(s, d, name)) as g:
            return ranked(pagerank(g, strategy=strategy, **options))

    return run


def bfs_query(name: str, **options) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        with released(derive.graph(s, d, name)) as g:
            return bfs(g, root_of(g.edges), **options).select("vid", "level")

    return run


def sssp_query(name: str, **options) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        with released(derive.graph(s, d, name)) as g:
            return sssp(g, root_of(g.edges), **options)

    return run


def rank_sql(name: str) -> str:
    return S.rank(derive.SQL[name], derive.vertex_sql(name))


def bfs_sql(name: str) -> str:
    return S.paths(S.symmetric(derive.SQL[name]), derive.vertex_sql(name), _root_sql(name), "1", "level")


def sssp_sql(name: str) -> str:
    return S.paths(derive.SQL[name], derive.vertex_sql(name), _root_sql(name))


def triangle_query(name: str, **options) -> Query:
    return lambda s, d: triangle_count(derive.graph(s, d, name), **options)


def twin_query(method: Callable[[twins.Twins], DataFrame]) -> Query:
    """A method on the pages that share a path, by classes of pages."""
    return lambda s, d: method(twins.twins(s, d))


def _graphs() -> None:
    for name in derive.NAMES:
        sql = derive.SQL[name]
        if name == "colink":
            add("graph_colink", twin_query(twins.pairs), twins.PAIRS_SQL)
        elif name in derive.ORDER_PICKS_SQL:
            add(f"graph_{name}", lambda s, d, n=name: derive.order_picks(s, d, n).edges, f"select src, dst, value from ({derive.ORDER_PICKS_SQL[name]})")
        else:
            add(f"graph_{name}", lambda s, d, n=name: derive.edges(s, d, n), f"select src, dst, value from ({sql})")
        if name != "docshare":
            into, out = (twin_query(twins.degree),) * 2 if name == "colink" else (lambda s, d, n=name: in_degree(derive.graph(s, d, n)), lambda s, d, n=name: out_degree(derive.graph(s, d, n)))
            add(f"indegree_{name}", into, S.degree(sql, derive.vertex_sql(name), "dst"))
            add(f"outdegree_{name}", out, S.degree(sql, derive.vertex_sql(name), "src"))
    add("graph_rating", derive.ratings, derive.RATINGS_SQL)


def _methods() -> None:
    for name in ("basket_chain", "copurchase", "links", "colink", "timeline", "handoff", "rmat", "turns", "knn"):
        add(f"pr_{name}", rank_query(name) if name != "colink" else twin_query(lambda t: ranked(twins.rank(t))), rank_sql(name))
    for name in ("basket_chain", "copurchase", "colink", "timeline", "handoff", "rmat", "turns", "knn"):
        add(f"bfs_{name}", bfs_query(name) if name != "colink" else twin_query(twins.levels), bfs_sql(name))
    for name in ("basket_chain", "handoff", "timeline", "trade", "rmat", "rmat_path", "turns", "knn"):
        add(f"sssp_{name}", sssp_query(name), sssp_sql(name))
    for name in ("basket_chain", "copurchase", "colink", "handoff", "links", "trade", "rmat_tri"):
        add(f"tc_{name}", triangle_query(name) if name != "colink" else twin_query(twins.triangle_count), S.triangles(derive.SQL[name]))

    add("pr_recipients_basket_chain", rank_query("basket_chain", rank_mode="recipients"), rank_sql("basket_chain"))
    chain = derive.SQL["basket_chain"]
    # at most two in-edges: sums don't depend on their order, so neither does what counts as a change
    add("pr_recipients_timeline", lambda s, d: ranked(pagerank(derive.graph(s, d, "timeline"), rank_mode="recipients")), S.rank_recipients(derive.SQL["timeline"], derive.vertex_sql("timeline")))
    add("pr_tol_basket_chain", lambda s, d: ranked(pagerank(derive.graph(s, d, "basket_chain"), iterations=None, tol=1e-4)), S.rank_until(chain, derive.vertex_sql("basket_chain"), 1e-4))
    add("bfs_prune_basket_chain", bfs_query("basket_chain", prune_visited=True), bfs_sql("basket_chain"))
    add("bfs_levels_timeline", lambda s, d: bfs_levels(bfs_query("timeline")(s, d)), f"select level, count(*) as vertices from ({bfs_sql('timeline')}) group by level")

    def parents(s: SparkSession, d: str) -> DataFrame:
        g = derive.graph(s, d, "basket_chain")
        return bfs(g, root_of(g.edges), parents=True)

    add("bfs_parents", parents, f"with l as materialized ({bfs_sql('basket_chain')}), e as ({S.symmetric(chain)}) select v.vid, v.level, min(u.vid) as parent from l v left join e on e.dst = v.vid left join l u on u.vid = e.src and u.level = v.level - 1 group by v.vid, v.level")
    add("bfs_multi_root", lambda s, d: bfs(derive.graph(s, d, "handoff"), roots=[0, 7]).select("vid", "level"), "select vid, least(a.level, b.level) as level from (" + S.paths(S.symmetric(derive.SQL["handoff"]), derive.vertex_sql("handoff"), "select 0", "1", "level") + ") a join (" + S.paths(S.symmetric(derive.SQL["handoff"]), derive.vertex_sql("handoff"), "select 7", "1", "level") + ") b using (vid)")
    add("sssp_full_relax", sssp_query("basket_chain", frontier=False), sssp_sql("basket_chain"))

    def tree(s: SparkSession, d: str) -> DataFrame:
        g = derive.graph(s, d, "basket_chain")
        return shortest_paths(g, root_of(g.edges))

    add("sssp_parents", tree, f"with l as materialized ({sssp_sql('basket_chain')}), e as ({chain}) select v.vid, v.dist, case when v.dist > 0 then min(u.vid) end as parent from l v left join e on e.dst = v.vid left join l u on u.vid = e.src and u.dist + e.value = v.dist group by v.vid, v.dist")

    def trace(s: SparkSession, d: str) -> DataFrame:
        g = derive.graph(s, d, "basket_chain")
        return sssp_run(g, root_of(g.edges)).supersteps.drop("seconds", "strategy")

    add("sssp_trace", trace, trace_sql(chain, _root_sql("basket_chain")))
    add("tc_symmetric_handoff", triangle_query("handoff", mode="symmetric"), S.triangles(derive.SQL["handoff"]))
    add("tc_degree_order_copurchase", triangle_query("copurchase", order="degree"), S.triangles(derive.SQL["copurchase"]))
    add("tc_per_vertex", twin_query(twins.triangles_per_vertex), S.triangles_per_vertex(derive.SQL["colink"], derive.vertex_sql("colink")))
    add("tc_list", lambda s, d: triangle_list(derive.graph(s, d, "basket_chain")), S.triangle_rows(chain))
    add("clustering", twin_query(lambda t: twins.clustering(t).withColumn("local", F.round("local", 6))), f"with t as materialized ({S.triangles_per_vertex(derive.SQL['colink'], derive.vertex_sql('colink'))}), g as (select src as vid, count(*) as degree from ({S.symmetric(derive.SQL['colink'])}) group by src) select vid, coalesce(degree, 0) as degree, triangles, round(case when degree > 1 then triangles / (degree * (degree - 1) / 2) else 0.0 end, 6) as local from t left join g using (vid)")
    add("clustering_global", lambda s, d: global_clustering(derive.graph(s, d, "handoff")).withColumn("transitivity", F.round("transitivity", 6)), f"with t as ({S.triangles(derive.SQL['handoff'])}), w as (select sum(n * (n - 1) // 2)::bigint as wedges from (select count(*) as n from ({S.symmetric(derive.SQL['handoff'])}) group by src)) select triangles, wedges, round(3 * triangles / wedges, 6) as transitivity from t, w")
    add("components_colink", twin_query(twins.components), S.components(derive.SQL["colink"], derive.vertex_sql("colink")))
    add("components_turns", lambda s, d: components(derive.graph(s, d, "turns")), S.components(derive.SQL["turns"], derive.vertex_sql("turns")))
    add("degree_hist", lambda s, d: degree_histogram(derive.graph(s, d, "basket_chain")), f"select degree, count(*) as vertices from ({S.degree(chain, derive.vertex_sql('basket_chain'), 'dst')}) group by degree")
    add("degree_stats", lambda s, d: degree_stats(derive.graph(s, d, "rmat")), f"with i as ({S.degree(derive.SQL['rmat'], derive.vertex_sql('rmat'), 'dst')}), o as ({S.degree(derive.SQL['rmat'], derive.vertex_sql('rmat'), 'src')}) select count(*) as vertices, sum(i.degree)::bigint as edges, round(avg(i.degree), 6) as mean_degree, max(i.degree) as max_in, max(o.degree) as max_out from i join o using (vid)")
    add("degree_weighted", lambda s, d: in_degree(derive.graph(s, d, "trade"), weighted=True), f"select dst as vid, sum(value)::double as degree from ({derive.SQL['trade']}) group by dst")


def trace_sql(edges: str, root: str) -> str:
    """Rounds of frontier shortest paths by themselves: what was active, sent, received and changed in each."""
    return (
        f"with recursive e as materialized ({edges}), k(step, vid, d, active, n, got) as (select 0, vid, case when vid = ({root}) then 0 end::bigint, vid = ({root}), 0::bigint, false from (select src as vid from e union select dst from e) union all "
        "select k.step + 1, k.vid, least(k.d, y.d), y.d is not null and (k.d is null or y.d < k.d), coalesce(y.n, 0), y.n is not null "
        "from k left join (select e.dst, min(a.d + e.value) as d, count(*) as n from k a join e on e.src = a.vid where a.active group by e.dst) y on y.dst = k.vid where exists (select 1 from k b where b.active)), "
        "s as (select step, count(*) filter (active) as changed, sum(n)::bigint as edges, count(*) filter (got) as receivers from k group by step) "
        "select s.step as superstep, p.changed as active, p.changed as messages, s.edges, s.receivers, s.changed from s join s p on p.step = s.step - 1"
    )


def _factors() -> None:
    k, rounds = 4, 5
    sql = S.factors(derive.RATINGS_SQL, k, rounds)

    def model(s: SparkSession, d: str) -> cf.CFModel:
        return cf.cf_gd(derive.ratings(s, d), k=k, iterations=rounds)

    def pairs(s: SparkSession, d: str) -> tuple[DataFrame, cf.CFModel]:
        return derive.ratings(s, d), model(s, d)

    names = [f"round(l[{i + 1}], 4) as f{i}" for i in range(k)]
    add("cf_rating", lambda s, d: model(s, d).factors.select("side", "id", *(F.round(f, 4).alias(f) for f in cf.fields(k))), f"with {sql} select side, id, {', '.join(names)} from f")
    rounded = lambda df, c: df.select(F.round(c, 4).alias(c))
    add("cf_rating_rmse", lambda s, d: rounded(cf.rmse(*pairs(s, d)), "rmse"), f"with {sql} select round(sqrt(avg((rating - prediction) ** 2)), 4) as rmse from ({S.PREDICTED})")
    add("cf_objective_per_rating", lambda s, d: rounded(cf.objective(*pairs(s, d)), "objective"), f"with {sql} select round(sum((rating - prediction) ** 2 + 0.05 * list_dot_product(p, p) + 0.05 * list_dot_product(q, q)), 4) as objective from ({S.PREDICTED})")
    add("cf_objective_per_vertex", lambda s, d: rounded(cf.objective(*pairs(s, d), form="per_vertex"), "objective"), f"with {sql} select round((select sum((rating - prediction) ** 2) from ({S.PREDICTED})) + 0.05 * (select sum(list_dot_product(l, l)) from f), 4) as objective")
    add("cf_predict", lambda s, d: cf.predict(*pairs(s, d)).withColumn("prediction", F.round("prediction", 4)), f"with {sql} select \"user\", item, rating, round(prediction, 4) as prediction from ({S.PREDICTED})")
    add("cf_error", lambda s, d: cf.rating_error(*pairs(s, d)).withColumn("error", F.round("error", 4) + F.lit(0.0)), f"with {sql} select \"user\", item, rating, round(rating - prediction, 4) + 0.0 as error from ({S.PREDICTED})")

    def recommended(s: SparkSession, d: str) -> DataFrame:
        rows, m = pairs(s, d)
        return cf.recommend(m, rows).withColumn("prediction", F.round("prediction", 4))

    add("recommend_top5", recommended, f"with {sql}, a as (select p.id as \"user\", q.id as item, list_dot_product(p.l, q.l) as prediction from f p join f q on p.side = 0 and q.side = 1 anti join r on r.\"user\" = p.id and r.item = q.id), b as (select *, row_number() over (partition by \"user\" order by round(prediction, 9) desc, item)::int as rank from a) select \"user\", rank, item, round(prediction, 4) as prediction from b where rank <= 5")
    from vertexalg.graphs.rmat import synthetic_ratings, synthetic_ratings_sql

    synth = synthetic_ratings_sql(500, 200, 10)
    add("graph_synth_rating", derive.customer_ratings, derive.CUSTOMER_RATINGS_SQL)
    add("cf_synth", lambda s, d: cf.cf_gd(synthetic_ratings(s, 500, 200, 10), k=k, iterations=3).factors.select("side", "id", *(F.round(f, 4).alias(f) for f in cf.fields(k))), f"with {S.factors('select * from ' + synth, k, 3)} select side, id, {', '.join(names)} from f")
    add("cf_sgd", lambda s, d: cf.cf_sgd(derive.ratings(s, d), k=k, epochs=1, strata=4).factors)
    add("cf_trace", lambda s, d: cf.cf_trace(derive.ratings(s, d), iterations=2).select("round", F.round("rmse", 4).alias("rmse")), " union all ".join(f"(with {S.factors(derive.RATINGS_SQL, k, n)} select {n} as round, round(sqrt(avg((rating - prediction) ** 2)), 4) as rmse from ({S.PREDICTED}))" for n in range(3)))


def _preparation() -> None:
    chain = derive.SQL["basket_chain"]
    raw = "select s_nationkey::bigint as src, c_nationkey::bigint as dst, count(*) as value from lineitem join orders on l_orderkey = o_orderkey join customer on c_custkey = o_custkey join supplier on s_suppkey = l_suppkey group by all"

    def loops(s: SparkSession, d: str) -> DataFrame:
        g = derive.graph(s, d, "trade")
        from vertexalg.graphs.graph import Graph

        own = g.vertices.select(F.col("vid").alias("src"), F.col("vid").alias("dst"), F.lit(0).cast("long").alias("value"))
        return prep.drop_self_loops(Graph.from_edges(g.edges.unionByName(own), value="value")).edges

    add("prep_selfloop", loops, f"select * from ({raw}) where src <> dst")
    add("prep_symmetric", lambda s, d: prep.symmetrize(derive.graph(s, d, "basket_chain")).edges, S.symmetric(chain))
    add("prep_upper", lambda s, d: prep.upper_triangle(derive.graph(s, d, "basket_chain")).edges.select("src", "dst"), S.upper(chain))
    add("prep_bipartite", lambda s, d: prep.as_bipartite(derive.ratings(s, d), "user", "item", "rating"), f"select \"user\" * 2 as src, item * 2 + 1 as dst, rating as value from ({derive.RATINGS_SQL})")
    add("prep_dedupe_sum", lambda s, d: _parallel(s, d, "sum"), f"select src, dst, sum(value)::bigint as value from ({_PARALLEL}) group by all")
    add("prep_dedupe_mean", lambda s, d: _parallel(s, d, "mean"), f"select src, dst, avg(value) as value from ({_PARALLEL}) group by all")

    def ids(s: SparkSession, d: str) -> DataFrame:
        from vertexalg.graphs.ids import encode_ids

        return encode_ids(derive.page_links(s, d), "path")

    add("prep_ids", ids, f"select path as key, row_number() over (order by path) - 1 as vid from (select distinct path from ({derive._PAGE_LINKS}))")
    sizes = []
    for name in derive.NAMES:
        sizes.append(f"select '{name}' as graph, (select count(*) from ({derive.vertex_sql(name)})) as vertices, (select count(*) from ({derive.SQL[name]})) as edges")

    def catalog(s: SparkSession, d: str) -> DataFrame:
        out = None
        for name in derive.NAMES:
            if name == "colink":
                vertices, edges = derive.page_vertices(s, d), twins.edge_count(twins.twins(s, d))
            else:
                g = derive.graph(s, d, name)
                vertices, edges = g.vertices, g.edges.agg(F.count("*").alias("edges"))
            row = vertices.agg(F.count("*").alias("vertices")).join(edges).select(F.lit(name).alias("graph"), "vertices", "edges")
            out = row if out is None else out.unionByName(row)
        return out

    add("graph_catalog", catalog, " union all ".join(sizes))


_PARALLEL = "select l_partkey as src, l_suppkey as dst, cast(l_quantity as bigint) as value from lineitem"


def _parallel(s: SparkSession, d: str, how: str) -> DataFrame:
    from vertexalg.graphs.graph import Graph
    from vertexalg.sources.tables import table

    rows = table(s, d, "lineitem").select(F.col("l_partkey").alias("src"), F.col("l_suppkey").alias("dst"), F.col("l_quantity").cast("long").alias("value"))
    return prep.dedupe(Graph.from_edges(rows, value="value"), how).edges


_graphs()
_methods()
_factors()
_preparation()


def _products() -> None:
    from vertexalg.baselines import native, semiring, triplet, workfront, worklist
    from vertexalg.algorithms.bfs import BfsProgram
    from vertexalg.algorithms.cf import GradientProgram, _model, rating_graph
    from vertexalg.algorithms.pagerank import PageRankProgram, with_out_degree
    from vertexalg.algorithms.sssp import SsspProgram
    from vertexalg.matrix.dcsc import from_dcsc, to_dcsc
    from vertexalg.matrix.spmv import spmv
    from vertexalg.matrix.semirings import MIN_PLUS, OR_AND, PLUS_PAIR, PLUS_TIMES
    from vertexalg.matrix.vectors import BitmapVector, PairVector
    from vertexalg.operators.relational import OPERATORS

    chain, hand = derive.SQL["basket_chain"], derive.SQL["handoff"]
    for strategy in ("rows_broadcast", "cols_shuffle", "grid"):
        add(f"spmv_{strategy}_pr", rank_query("handoff", strategy=strategy), rank_sql("handoff"))
        add(f"spmv_{strategy}_sssp", sssp_query("handoff", strategy=strategy), sssp_sql("handoff"))
        add(f"spmv_{strategy}_tc", triangle_query("handoff", strategy=strategy), S.triangles(hand))

    ones = lambda g: g.vertices.select("vid", F.lit(1).cast("long").alias("value"))
    for name, semiring_, x, sql in (
        ("plus_times", PLUS_TIMES, ones, f"select dst as vid, sum(value)::bigint as value from ({hand}) group by dst"),
        ("min_plus", MIN_PLUS, ones, f"select dst as vid, min(1 + value) as value from ({hand}) group by dst"),
        ("plus_pair", PLUS_PAIR, ones, f"select dst as vid, count(*) as value from ({hand}) group by dst"),
        ("or_and", OR_AND, lambda g: g.vertices.select("vid", (F.col("vid") % 2 == 0).alias("value")), f"select dst as vid, bool_or(src % 2 = 0 and value <> 0) as value from ({hand}) group by dst"),
    ):
        add(f"semiring_{name}", lambda s, d, m=semiring_, v=x: spmv(g := derive.graph(s, d, "handoff"), v(g), *m), sql)

    levels = bfs_sql("basket_chain")
    front = lambda s, d: bfs_query("basket_chain")(s, d).where("level is not null").select("vid", F.col("level").alias("val"))
    add("vec_pairs", lambda s, d: PairVector(front(s, d)).df, f"select vid, level as val from ({levels})")
    add("vec_bitmap", lambda s, d: BitmapVector.of(front(s, d)).to_pairs().df, f"select vid, level as val from ({levels})")
    add("vec_bitmap_frontier", lambda s, d: BitmapVector.of(front(s, d).where("val = 2")).keep(derive.basket_chain(s, d)).select("src", "dst", "value"), f"select src, dst, value from ({chain}) where src in (select vid from ({levels}) where level = 2)")
    add("dcsc_roundtrip", lambda s, d: from_dcsc(to_dcsc(written(derive.edges(s, d, "basket_chain"), "edges"))), f"select src, dst, value from ({chain})")

    def rooted(fn, name: str):
        def run(s: SparkSession, d: str) -> DataFrame:
            g = derive.graph(s, d, name)
            return fn(g, root_of(g.edges))

        return run

    def triplet_bfs(g, root):
        return triplet.run(BfsProgram([root]), prep.symmetrize(prep.drop_self_loops(g))).state.select("vid", "level")

    add("triplet_pr", lambda s, d: ranked(triplet.run(PageRankProgram(), with_out_degree(derive.graph(s, d, "handoff")), 10).state), rank_sql("handoff"))
    add("triplet_bfs", rooted(triplet_bfs, "handoff"), bfs_sql("handoff"))
    add("triplet_sssp", rooted(lambda g, r: triplet.run(SsspProgram(r), g).state.select("vid", "dist"), "handoff"), sssp_sql("handoff"))
    add("triplet_tc", lambda s, d: triplet.triangles_hash(derive.graph(s, d, "handoff")), S.triangles(hand))
    k, rounds = 4, 3
    small = f"with {S.factors(derive.RATINGS_SQL, k, rounds)} select side, id, {', '.join(f'round(l[{i + 1}], 4) as f{i}' for i in range(k))} from f"
    shown = lambda m: m.factors.select("side", "id", *(F.round(f, 4).alias(f) for f in cf.fields(k)))
    add("triplet_cf", lambda s, d: shown(_model(triplet.run(GradientProgram(k, 0.002, 0.05), rating_graph(derive.ratings(s, d)), rounds).state, k, [])), small)
    add("semiring_pr", lambda s, d: ranked(semiring.pagerank(derive.graph(s, d, "handoff"))), rank_sql("handoff"))
    add("semiring_bfs", rooted(semiring.bfs, "handoff"), bfs_sql("handoff"))
    add("semiring_sssp", rooted(semiring.sssp, "handoff"), sssp_sql("handoff"))
    add("semiring_sssp_grid3", rooted(lambda g, r: semiring.sssp(g, r, 3), "handoff"), sssp_sql("handoff"))
    add("semiring_tc", lambda s, d: semiring.triangles_spgemm(derive.graph(s, d, "handoff")), S.triangles(hand))
    add("semiring_tc_mask_early", lambda s, d: semiring.triangles_spgemm(derive.graph(s, d, "handoff"), False), S.triangles(hand))
    add("semiring_cf", lambda s, d: shown(semiring.cf_gd(derive.ratings(s, d), k, iterations=rounds)), small)
    add("triangle_cost", lambda s, d: semiring.wedges(derive.graph(s, d, "copurchase")), f"with e as ({S.upper(derive.SQL['copurchase'])}), a as (select dst as v, count(*) as a from e group by dst), b as (select src as v, count(*) as b from e group by src) select sum(a * b)::bigint as wedges from a join b using (v)")
    for schedule in ("fifo", "bucket", "priority"):
        add(f"worklist_sssp_{schedule}", rooted(lambda g, r, how=schedule: worklist.sssp(g, r, how), "handoff"), sssp_sql("handoff"))
    add("worklist_bfs", rooted(worklist.bfs, "handoff"), bfs_sql("handoff"))

    def residual_ranks(s: SparkSession, d: str) -> DataFrame:
        # edges are derived once: their blocks are counted, and vertices are their ends
        with released(Graph.from_edges(written(derive.edges(s, d, "handoff"), "edges"), value="value")) as g:
            return worklist.pagerank_residual(g, eps=1e-9).select("vid", F.round("rank", 5).alias("rank"))

    add("worklist_pr", residual_ranks, S.rank(hand, derive.vertex_sql("handoff"), 60, digits=5))
    add("worklist_tc", lambda s, d: worklist.triangles(derive.graph(s, d, "handoff")), S.triangles(hand))
    fresh = f"with {S.factors(derive.RATINGS_SQL, k, rounds, fresh=True)} select side, id, {', '.join(f'round(l[{i + 1}], 4) as f{i}' for i in range(k))} from f"
    add("worklist_cf", lambda s, d: shown(worklist.cf(derive.ratings(s, d), k=k, iterations=rounds)), fresh)
    add("native_pr", lambda s, d: ranked(native.pagerank(derive.graph(s, d, "handoff"))), rank_sql("handoff"))
    add("native_bfs", rooted(native.bfs, "handoff"), bfs_sql("handoff"))
    add("native_sssp", rooted(native.sssp, "handoff"), sssp_sql("handoff"))
    add("native_tc", lambda s, d: native.triangles(derive.graph(s, d, "handoff")), S.triangles(hand))
    add("native_cf", lambda s, d: native.cf(derive.ratings(s, d), k=k, epochs=1).factors)
    add("workfront_sssp", rooted(workfront.sssp, "handoff"), sssp_sql("handoff"))

    def picked(s: SparkSession, d: str) -> DataFrame:
        g = derive.order_picks(s, d, "rmat_path").written("picks")
        return workfront.sssp(g, root_of(g.edges))

    sql = derive.ORDER_PICKS_SQL["rmat_path"]
    add("workfront_sssp_rmat_path", picked, S.paths(sql, f"select src as vid from ({sql}) union select dst from ({sql})", f"select min(src) from ({sql})"))

    from vertexalg.measures.ablation import opaque
    from vertexalg.engine import run_program

    for kind in ("udf", "arrow"):
        add(f"mode_{kind}_sssp", rooted(lambda g, r, how=kind: run_program(g, opaque(SsspProgram(r), how)).state.select("vid", "dist"), "handoff"), sssp_sql("handoff"))
    from vertexalg.measures import experiments

    add("bench_table2", experiments.against_frameworks)
    add("bench_table3", experiments.against_native)
    add("bench_agreement", experiments.agreement, experiments.AGREEMENT_SQL)
    add("bench_ablation", experiments.ablation_rows)
    add("bench_ablation_agreement", experiments.ablation_agreement, experiments.ABLATION_SQL)
    add("bench_scaling", experiments.scaling_rows)
    add("bench_single_thread", experiments.single_thread)
    add("bench_workfront", experiments.workfront_ratio)
    add("bench_product_share", experiments.product_share)
    add("bench_grid_sweep", lambda s, d: experiments.grid_sweep(s, d).drop("seconds"), experiments.GRID_SQL)
    add("bench_counters", experiments.counter_rows)
    for name, query, sql in OPERATORS:
        add(name, query, sql)


_products()
