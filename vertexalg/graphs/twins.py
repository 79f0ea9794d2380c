"""The graph of pages that share a path, held by classes instead of pairs.

Pages with the same paths are twins: each is tied to the other and both to the same pages. A class of twins goes by its least page. Links
between classes are spelled out, links between pages never are, and none is lost: two pages are tied if they are in one class or in
linked classes (pages without a path are in none). What a method finds on the whole graph follows from classes, their sizes and
links, so copies of pages cost one row each.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vertexalg.algorithms import components as labels
from vertexalg.algorithms.bfs import BfsProgram
from vertexalg.algorithms.pagerank import PageRankProgram
from vertexalg.conf import written
from vertexalg.engine import run_program
from vertexalg.graphs import derive
from vertexalg.graphs.graph import Graph
from vertexalg.graphs.prep import degree_order


class TwinRankProgram(PageRankProgram):
    """Ranks of classes: an edge's value is the number of pages that send along it."""

    def process(self, m, e, dst):
        return m * e


@dataclass
class Twins:
    """vertices (vid): all pages; members (vid, cls): pages with a path; classes (cls, n); links (src, dst, value): both arcs between
    linked classes, value the pages of src."""

    vertices: DataFrame
    members: DataFrame
    classes: DataFrame
    links: DataFrame

    def graph(self) -> Graph:
        return Graph(self.links, self.classes.select(F.col("cls").alias("vid")), False)

    def by_page(self, found: DataFrame) -> DataFrame:
        """(vid, cls, ...) of all pages, from (cls, ...); null for pages without a path."""
        return self.vertices.join(self.members.join(found, "cls"), "vid", "left")

    def sums(self) -> DataFrame:
        """(cls, n, near, degree): pages in linked classes, and pages tied to each page of the class."""
        near = self.links.groupBy(F.col("dst").alias("cls")).agg(F.sum("value").alias("near"))
        return self.classes.join(near, "cls", "left").na.fill(0, ["near"]).withColumn("degree", F.col("near") + F.col("n") - 1)


def twins(spark: SparkSession, d: str) -> Twins:
    paths = derive.page_links(spark, d).where("page_id is not null").groupBy(F.col("page_id").alias("vid")).agg(F.array_sort(F.collect_list("path")).alias("paths"))
    own = written(paths.withColumn("key", F.sha2(F.to_json("paths"), 256)), "paths")
    kinds = written(own.groupBy("key").agg(F.min("vid").alias("cls"), F.count("*").alias("n"), F.first("paths").alias("paths")), "classes")
    members = own.select("vid", "key").join(kinds.select("key", "cls"), "key").select("vid", "cls")
    ends = kinds.select("cls", "n", F.explode("paths").alias("path"))
    a, b = ends.select("path", F.col("cls").alias("src"), F.col("n").alias("value")), ends.select("path", F.col("cls").alias("dst"))
    links = written(a.join(b, "path").where("src <> dst").select("src", "dst", "value").distinct(), "links")
    return Twins(derive.page_vertices(spark, d).distinct(), members, kinds.select("cls", "n"), links)


def pairs(t: Twins) -> DataFrame:
    """(src, dst, value): links between classes (value 1), and each page with its class (value 0)."""
    one = lambda n: F.lit(n).cast("long").alias("value")
    return t.links.select("src", "dst", one(1)).unionByName(t.members.select(F.col("vid").alias("src"), F.col("cls").alias("dst"), one(0)))


def degree(t: Twins) -> DataFrame:
    """(vid, degree): ties are mutual, so it is in- and out-degree."""
    return t.by_page(t.sums().select("cls", "degree")).select("vid", F.coalesce("degree", F.lit(0)).alias("degree"))


def edge_count(t: Twins) -> DataFrame:
    """(edges): of the whole graph."""
    return t.sums().agg(F.coalesce(F.sum(F.col("n") * F.col("degree")), F.lit(0)).alias("edges"))


def rank(t: Twins, iterations: int = 10, r: float = 0.15) -> DataFrame:
    """(vid, rank) after the rounds (one at least): twins always have the same rank."""
    inside = t.classes.where("n > 1").select(F.col("cls").alias("src"), F.col("cls").alias("dst"), (F.col("n") - 1).alias("value"))
    vertices = t.sums().select(F.col("cls").alias("vid"), F.col("degree").alias("outdeg"))
    if t.classes.isEmpty():  # the engine counts nothing on a graph without vertices
        return t.vertices.select("vid", F.lit(r).alias("rank"))
    g = Graph(t.links.unionByName(inside), vertices, False)
    found = run_program(g, TwinRankProgram(r), iterations).state.select(F.col("vid").alias("cls"), "rank")
    g.unpersist()
    return t.by_page(found).select("vid", F.coalesce("rank", F.lit(r)).alias("rank"))


def levels(t: Twins) -> DataFrame:
    """(vid, level) from the least page that has a tie; null where unreached. Twins of the root are one step from it."""
    tied = t.sums().where("degree > 0").select("cls")
    root = tied.agg(F.min("cls")).first()[0]  # the least page of its class is the class's name
    g = t.graph()
    found = run_program(g, BfsProgram([root])).state.select(F.col("vid").alias("cls"), "level") if root is not None else t.classes.select("cls", F.lit(None).cast("long").alias("level"))
    g.unpersist()
    return t.by_page(found).select("vid", F.when((F.col("level") == 0) & (F.col("vid") != F.col("cls")), F.lit(1).cast("long")).otherwise(F.col("level")).alias("level"))


def components(t: Twins) -> DataFrame:
    """(vid, component)."""
    if t.classes.isEmpty():
        return t.vertices.select("vid", F.col("vid").alias("component"))
    g = t.graph()
    found = labels.components(g).withColumnRenamed("vid", "cls")
    g.unpersist()
    return t.by_page(found).select("vid", F.coalesce("component", "vid").alias("component"))


def _triangles(t: Twins) -> DataFrame:
    """(cls, n, degree, triangles): of each page of the class. Its two others are twins of it, one twin and one page near, two of one
    class near, or of two linked classes; the last are found by meeting lists along the links, without pairs of them being moved."""
    e = degree_order(t.graph()).edges.select("src", "dst")
    sized = e.join(t.classes.select(F.col("cls").alias("dst"), F.col("n").alias("_n")), "dst")
    lists = sized.groupBy("src").agg(F.array_sort(F.collect_list(F.struct("dst", "_n"))).alias("l"))
    a, b = lists.select("src", F.col("l").alias("a")), lists.select(F.col("src").alias("dst"), F.col("l").alias("b"))
    n_of = lambda end: t.classes.select(F.col("cls").alias(end), F.col("n").alias(f"n_{end}"))
    met = e.join(a, "src").join(b, "dst").select("src", "dst", F.array_intersect("a", "b").alias("c")).where("size(c) > 0").join(n_of("src"), "src").join(n_of("dst"), "dst")
    common = F.aggregate("c", F.lit(0).cast("long"), lambda s, x: s + x["_n"])
    own = F.array(F.struct(F.col("src").alias("cls"), (F.col("n_dst") * common).alias("m")), F.struct(F.col("dst").alias("cls"), (F.col("n_src") * common).alias("m")))
    third = F.transform("c", lambda x: F.struct(x["dst"].alias("cls"), (F.col("n_src") * F.col("n_dst")).alias("m")))
    apart = met.select(F.inline(F.concat(own, third))).groupBy("cls").agg(F.sum("m").alias("apart"))
    two = t.links.groupBy(F.col("dst").alias("cls")).agg(F.sum(F.expr("value * (value - 1) div 2")).alias("two"))
    rows = t.sums().join(apart, "cls", "left").join(two, "cls", "left").na.fill(0, ["apart", "two"])
    return rows.select("cls", "n", "degree", F.expr("(n - 1) * (n - 2) div 2 + (n - 1) * near + two + apart").alias("triangles"))


def triangle_count(t: Twins) -> DataFrame:
    return _triangles(t).agg(F.expr("cast(coalesce(sum(n * triangles), 0) div 3 as bigint)").alias("triangles"))


def triangles_per_vertex(t: Twins) -> DataFrame:
    return t.by_page(_triangles(t).select("cls", "triangles")).select("vid", F.coalesce("triangles", F.lit(0)).alias("triangles"))


def clustering(t: Twins) -> DataFrame:
    """(vid, degree, triangles, local): local clustering coefficient, 0 under degree 2."""
    both = t.by_page(_triangles(t).select("cls", "degree", "triangles")).na.fill(0, ["degree", "triangles"])
    ties = F.col("degree") * (F.col("degree") - 1) / 2
    return both.select("vid", "degree", "triangles", F.when(F.col("degree") > 1, F.col("triangles") / ties).otherwise(0.0).alias("local"))


PAIRS_SQL = (
    f"with l as materialized (select * from ({derive._PAGE_LINKS}) where page_id is not null), p as (select page_id, list(path order by path) as paths from l group by page_id), "
    "m as materialized (select page_id, min(page_id) over (partition by paths) as cls from p), c as materialized (select distinct path, cls from l join m using (page_id)) "
    "select distinct a.cls as src, b.cls as dst, 1::bigint as value from c a join c b using (path) where a.cls <> b.cls union all select page_id, cls, 0::bigint from m"
)
