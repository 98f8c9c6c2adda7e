"""Edge streams: windows, deduplication, running degrees and micro-batch refresh of a search."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from levelgraph.bfs.hybrid import bfs
from levelgraph.graph.build import Graph

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, folder: str, pattern: str = "events.parquet", files_per_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("pathGlobFilter", pattern).option("maxFilesPerTrigger", files_per_batch).parquet(folder)


def user_type_edges(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """User - event type edges with their time; later rows than ``delay`` are dropped by the watermark."""
    return events.withWatermark("ts", delay).select("ts", (F.col("user_id") * 2).alias("src"), (F.abs(F.xxhash64("event_type")) % 1024 * 2 + 1).alias("dst"))


def windowed_counts(edges: DataFrame, length: str = "1 day", slide: str | None = None) -> DataFrame:
    """Edges and distinct-source estimate of each tumbling or sliding window."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return edges.groupBy(w.alias("w")).agg(F.count("*").alias("edges"), F.approx_count_distinct("src").alias("sources")).select(F.col("w.start").alias("start"), "edges", "sources")


def session_counts(edges: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return edges.groupBy(F.session_window("ts", gap).alias("w"), "src").agg(F.count("*").alias("edges")).select(F.col("w.start").alias("start"), "src", "edges")


def distinct_edges(edges: DataFrame) -> DataFrame:
    """One row per pair within the watermark's reach."""
    return edges.dropDuplicatesWithinWatermark(["src", "dst"])


def running_degrees(edges: DataFrame) -> DataFrame:
    """Degree of each source so far, updated in every micro-batch."""

    def update(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n = (state.get[0] if state.exists else 0) + sum(map(len, frames))
        state.update((n,))
        yield pd.DataFrame({"v": [key[0]], "deg": [n]})

    return edges.groupBy("src").applyInPandasWithState(update, "v long, deg long", "n long", "update", GroupStateTimeout.NoTimeout)


def meetings(events: DataFrame, seconds: int = 60) -> DataFrame:
    """Edges between users who did the same kind of thing within ``seconds`` of each other."""
    a = events.select(F.col("ts").alias("ta"), F.col("user_id").alias("src"), F.col("event_type").alias("ka")).withWatermark("ta", "10 minutes")
    b = events.select(F.col("ts").alias("tb"), F.col("user_id").alias("dst"), F.col("event_type").alias("kb")).withWatermark("tb", "10 minutes")
    near = F.expr(f"ka = kb and src < dst and tb between ta - interval {seconds} seconds and ta + interval {seconds} seconds")
    return a.join(b, near).select("src", "dst")


def refresh_search(source: int, sink: Callable[[DataFrame, int], None], folder: str) -> Callable[[DataFrame, int], None]:
    """A ``foreachBatch`` function: adds a batch's edges to the table in ``folder`` and searches again.

    Batches are written under their number, so one that is replayed replaces itself."""

    def run(batch: DataFrame, number: int) -> None:
        batch.select("src", "dst").write.mode("overwrite").parquet(f"{folder}/batch={number}")
        raw = batch.sparkSession.read.schema("src long, dst long, batch int").parquet(folder).select("src", "dst")
        vertices = raw.select(F.explode(F.array("src", "dst")).alias("v")).distinct()
        sink(bfs(Graph(raw, vertices, "stream"), source).result, number)

    return run
