"""A graph: edges (src, dst, value), vertices (vid, ...), and the layouts of its matrix that have been built."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.storagelevel import StorageLevel

from vertexalg.conf import EngineConf, written


class Graph:
    """form: what preparation has made of the edges ('symmetric': both arcs of each, 'upper': no cycles), so that it need not be made again."""

    def __init__(self, edges: DataFrame, vertices: DataFrame, directed: bool = True, conf: EngineConf = EngineConf(), form: str | None = None) -> None:
        self.edges, self.vertices, self.directed, self.conf, self.form = edges, vertices, directed, conf, form
        self._layouts: dict[str, DataFrame] = {}
        self.grids: dict[int, Graph] = {}
        self.unit = False  # whether every edge is known to have weight 1

    @classmethod
    def from_edges(cls, df: DataFrame, src: str = "src", dst: str = "dst", value: str | Column | None = None, directed: bool = True, vertices: DataFrame | None = None, conf: EngineConf = EngineConf()) -> Graph:
        """Without value every edge has 1; without vertices they are the ends of edges. Edges with a null end are no edges."""
        given = F.lit(1).cast("long") if value is None else (F.col(value) if isinstance(value, str) else value)
        edges = df.select(F.col(src).cast("long").alias("src"), F.col(dst).cast("long").alias("dst"), given.alias("value")).where("src is not null and dst is not null")
        if vertices is None:
            vertices = edges.select(F.explode(F.array("src", "dst")).alias("vid")).distinct()
        return cls(edges, vertices, directed, conf)

    @property
    def spark(self):
        return self.edges.sparkSession

    def blocks(self) -> int:
        return self.conf.blocks(self.spark)

    def arcs(self, direction: str = "out") -> DataFrame:
        """Edges as (src sends, dst receives, value): 'out' along them, 'in' against them, or 'both'."""
        forward = self.edges.select("src", "dst", "value")
        back = self.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "value")
        return {"out": forward, "in": back, "both": forward.unionByName(back)}[direction]

    def kept(self, name: str, build: Callable[[], DataFrame]) -> DataFrame:
        """A layout by its name, built and kept at its first use."""
        if name not in self._layouts:
            self._layouts[name] = build().persist(StorageLevel.MEMORY_AND_DISK)
        return self._layouts[name]

    def layout(self, key: str, direction: str = "out") -> DataFrame:
        """Arcs dealt by key ('src' or 'dst') into blocks, sorted by it, and kept: one shuffle per graph, none per superstep."""
        return self.kept(f"{key} {direction}", lambda: self.arcs(direction).repartition(self.blocks(), key).sortWithinPartitions(key))

    def grid(self, q: int, direction: str = "out") -> DataFrame:
        """Arcs with their cell (_row, _col) of a q x q grid, dealt and sorted by what a message meets them on, and kept."""
        block = lambda c: F.pmod(F.xxhash64(c), F.lit(q)).cast("int")
        keys = ("_row", "_col", "src")
        return self.kept(f"grid {q} {direction}", lambda: self.arcs(direction).withColumn("_row", block("dst")).withColumn("_col", block("src")).repartition(self.blocks(), *keys).sortWithinPartitions(*keys))

    def persist(self, *layouts: str) -> Graph:
        """Build layouts now: 'dst', 'src' (with a direction after a space if it isn't 'out') or 'columns'."""
        from vertexalg.matrix.columns import columns

        for name in layouts or ("dst",):
            kind, _, direction = name.partition(" ")
            (columns(self, direction or "out") if kind == "columns" else self.layout(kind, direction or "out")).count()
        return self

    def unpersist(self) -> None:
        for df in self._layouts.values():
            df.unpersist()
        self._layouts.clear()
        for g in self.grids.values():
            g.unpersist()

    def reverse(self) -> Graph:
        return Graph(self.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "value"), self.vertices, self.directed, self.conf)

    def subgraph(self, keep: Column) -> Graph:
        """Vertices that pass, and edges whose both ends do."""
        left = self.vertices.where(keep)
        ids = left.select("vid")
        edges = self.edges.join(ids.withColumnRenamed("vid", "src"), "src", "left_semi").join(ids.withColumnRenamed("vid", "dst"), "dst", "left_semi")
        return Graph(edges.select("src", "dst", "value"), left, self.directed, self.conf)

    def with_edges(self, edges: DataFrame, directed: bool | None = None, form: str | None = None) -> Graph:
        return Graph(edges, self.vertices, self.directed if directed is None else directed, self.conf, form)

    def written(self, name: str = "graph") -> Graph:
        """The same graph read back from the shared folder: what made it is not made again."""
        out = Graph(written(self.edges, name), written(self.vertices, name), self.directed, self.conf, self.form)
        out.unit = self.unit
        return out
