"""Graphs from streams of events: windowed degrees, sessions, running degrees, and distances that follow inserts."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from vertexalg.algorithms.sssp import SsspProgram
from vertexalg.engine import run_program
from vertexalg.graphs.graph import Graph

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def event_stream(spark: SparkSession, folder: str, files_per_trigger: int = 1) -> DataFrame:
    """Parquet files of events as they arrive, with ts as a timestamp that a watermark can follow."""
    rows = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def stream_edges(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """(ts, src, dst): user to event type, late rows beyond the watermark dropped by what follows."""
    kind = F.pmod(F.xxhash64("event_type"), F.lit(1000))
    return events.withWatermark("ts", late).select("ts", "event_id", F.col("user_id").alias("src"), kind.alias("dst"))


def window_degree(edges: DataFrame, size: str = "1 day", slide: str | None = None) -> DataFrame:
    """(start, vid, degree) per window and source; the same code for a batch and a stream."""
    window = F.window("ts", size, slide) if slide else F.window("ts", size)
    return edges.groupBy(window.alias("w"), F.col("src").alias("vid")).agg(F.count("*").alias("degree")).select(F.col("w.start").alias("start"), "vid", "degree")


def without_repeats(edges: DataFrame) -> DataFrame:
    return edges.dropDuplicatesWithinWatermark(["event_id"])


def user_sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    """(user_id, start, events) per session."""
    return events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("events")).select("user_id", F.col("w.start").alias("start"), "events")


class RunningDegree(StatefulProcessor):
    """Keeps each vertex's in-degree; emits the new one with every micro-batch that touches it."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.degree = handle.getValueState("degree", "n bigint")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timer_values) -> Iterator[pd.DataFrame]:
        n = (self.degree.get()[0] if self.degree.exists() else 0) + sum(len(x) for x in rows)
        self.degree.update((n,))
        yield pd.DataFrame({"vid": [key[0]], "degree": [n]})

    def close(self) -> None:
        pass


def running_degree(edges: DataFrame) -> DataFrame:
    return edges.groupBy("dst").transformWithStateInPandas(RunningDegree(), "vid bigint, degree bigint", "Update", "None")


def follow_distances(source: int, on_result: Callable[[DataFrame, int], None]) -> Callable[[DataFrame, int], None]:
    """For foreachBatch on edges (src, dst, value): after each batch of inserts distances are right again. A batch starts from
    the last distances, and only vertices with new out-edges begin active. Deletions need a run from the start."""
    held: dict[str, DataFrame] = {}

    def batch(new: DataFrame, number: int) -> None:
        from vertexalg.conf import written

        fresh = written(new.select("src", "dst", "value"), "inserts")
        edges = fresh if "edges" not in held else written(held["edges"].unionByName(fresh), "edges")
        g = Graph.from_edges(edges, value="value")
        touched = fresh.select(F.col("src").alias("vid")).distinct().withColumn("touched", F.lit(True))
        old = held["state"] if "state" in held else g.vertices.select("vid", F.lit(None).cast("long").alias("dist"))
        dist = F.when(F.col("vid") == source, F.lit(0).cast("long")).otherwise(F.col("dist"))
        start = g.vertices.join(old.select("vid", "dist"), "vid", "left").join(touched, "vid", "left")
        start = start.select("vid", dist.alias("dist"), F.coalesce("touched", F.lit(False)).alias("active"))
        held["edges"], held["state"] = edges, run_program(g, SsspProgram(source), start=start).state.select("vid", "dist")
        on_result(held["state"], number)

    return batch
