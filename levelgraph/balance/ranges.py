"""Cutting labels into ranges, and frontier lists into slices."""

from __future__ import annotations

import heapq

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from levelgraph.graph.build import Graph
from levelgraph.graph.rank import global_rank

LINE_BITS = 512


def equal_cuts(blocks: int, s: int) -> list[int]:
    return [blocks * k // s for k in range(s + 1)]


def descending_cuts(blocks: int, s: int) -> list[int]:
    """Range k of s weighs s - k, so lengths fall by an arithmetic sequence."""
    return [blocks * k * (2 * s + 1 - k) // (s * (s + 1)) for k in range(s + 1)]


def label_ranges(n_labels: int, s: int, block: int = LINE_BITS, kind: str = "descending") -> list[tuple[int, int, int]]:
    """``(rid, lo, hi)`` with ``hi`` exclusive, cut at whole blocks; empty ranges are dropped."""
    blocks = -(-n_labels // block)
    cuts = (descending_cuts if kind == "descending" else equal_cuts)(blocks, s)
    parts = [(a * block, min(b * block, n_labels)) for a, b in zip(cuts, cuts[1:], strict=False) if a < b]
    return [(k, a, b) for k, (a, b) in enumerate(parts)]


def range_table(spark: SparkSession, n_labels: int, s: int, block: int = LINE_BITS, kind: str = "descending") -> DataFrame:
    return spark.createDataFrame(label_ranges(n_labels, s, block, kind), "rid int, lo long, hi long")


def with_range(df: DataFrame, ranges: DataFrame, label: str = "v") -> DataFrame:
    """Adds the range of each label; the table of ranges has lambda * workers rows."""
    return df.join(F.broadcast(ranges), (F.col(label) >= F.col("lo")) & (F.col(label) < F.col("hi")))


def default_lambda(n_vertices: int) -> int:
    """10 ranges per worker below 2**26 vertices, 24 from there on."""
    return 10 if n_vertices < 1 << 26 else 24


def placed_frontier(graph: Graph, depths: DataFrame) -> DataFrame:
    """Each reached vertex with its degree, step and place ``j`` of ``n`` in its frontier list (by id)."""
    ranked = global_rank(depths.join(graph.degrees, "v").select("v", "depth", "deg"), ["depth", "v"], "at")
    first = ranked.groupBy("depth").agg(F.min("at").alias("first"), F.count("*").alias("n"))
    return ranked.join(F.broadcast(first), "depth").select("v", F.col("depth").alias("step"), "deg", (F.col("at") - F.col("first")).alias("j"), "n")


def static_slots(frontier: DataFrame, workers: int) -> DataFrame:
    """Edges per worker when the frontier list is cut into equal runs of vertices."""
    slot = F.expr(f"j * {workers} div n")
    return frontier.groupBy("step", slot.alias("slot")).agg(F.sum("deg").alias("edges"))


def sliced_slots(frontier: DataFrame, workers: int) -> DataFrame:
    """Edges per worker when every list is cut into equal slices; leftovers of list j go to worker j mod t.

    The equal slices are summed once per step, so no list is exploded."""
    even = frontier.groupBy("step").agg(F.sum(F.expr(f"deg div {workers}")).alias("edges"))
    even = even.select("step", F.explode(F.sequence(F.lit(0), F.lit(workers - 1))).alias("slot"), "edges")
    left = frontier.groupBy("step", F.expr(f"j % {workers}").alias("slot")).agg(F.sum(F.expr(f"deg % {workers}")).alias("edges"))
    return even.select("step", F.col("slot").cast("long").alias("slot"), "edges").union(left).groupBy("step", "slot").agg(F.sum("edges").alias("edges")).where("edges > 0")


def imbalance(slots: DataFrame, workers: int) -> DataFrame:
    """Largest and mean load, idle workers and coefficient of variation over all ``workers``, per step."""
    per = slots.groupBy("step").agg(F.max("edges").alias("max_edges"), F.sum("edges").alias("total"), F.count("*").alias("busy"), F.sum(F.col("edges") * F.col("edges")).alias("squares"))
    mean = F.col("total") / workers
    spread = F.sqrt(F.greatest(F.col("squares") / workers - mean * mean, F.lit(0.0))) / mean
    return per.select("step", "max_edges", F.round(mean, 6).alias("mean_edges"), (F.lit(workers) - F.col("busy")).alias("idle"), F.round(spread, 6).alias("variation"))


def lambda_table(spark: SparkSession) -> DataFrame:
    """Ranges per worker that :func:`default_lambda` gives by scale."""
    return spark.createDataFrame([(k, default_lambda(1 << k)) for k in range(20, 33)], "scale long, lam long")


def range_work(graph: Graph, depths: DataFrame, ranges: DataFrame) -> DataFrame:
    """Unvisited vertices and their degree sum per range and bottom-up step."""
    deep = depths.agg(F.max("depth").alias("d")).first()["d"] or 0
    rows = graph.degrees.join(depths.select("v", "depth"), "v", "left").select("v", "deg", F.coalesce("depth", F.lit(deep + 1)).alias("depth"))
    steps = with_range(rows, ranges).where("depth > 0").select("rid", "v", "deg", F.explode(F.sequence(F.lit(0), F.col("depth") - 1)).alias("step"))
    return steps.groupBy("step", "rid").agg(F.count("*").alias("unvisited"), F.sum("deg").alias("degree_sum"))


def live_range_size(n_labels_vertices: DataFrame, depths: DataFrame, ranges: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """Sum over ranges of the stretch from the first to the last unvisited label, after each step; for each of ``keys`` of the depths."""
    deep = depths.agg(F.max("depth").alias("d")).first()["d"] or 0
    if keys:
        # a row for each label and source, as the state of that many searches is
        each = [r.asDict() for r in depths.select(*keys).distinct().collect()]
        n_labels_vertices = n_labels_vertices.select("v", F.explode(F.array(*[F.struct(*[F.lit(e[k]).alias(k) for k in keys]) for e in each])).alias("_k")).select("v", "_k.*")
    rows = n_labels_vertices.join(depths.select(*keys, "v", "depth"), [*keys, "v"], "left").select(*keys, "v", F.coalesce("depth", F.lit(deep + 1)).alias("depth"))
    spans = with_range(rows, ranges).where("depth > 0").select(*keys, "rid", "v", F.explode(F.sequence(F.lit(0), F.least(F.col("depth") - 1, F.lit(deep)))).alias("step"))
    spans = spans.groupBy(*keys, "step", "rid").agg((F.max("v") - F.min("v") + 1).alias("live"))
    return spans.groupBy(*keys, "step").agg(F.sum("live").alias("live_size"))


def simulate_pulling(work: list[float], workers: int) -> tuple[float, float]:
    """Makespan when idle workers pull the next range in list order, and the mean load."""
    heap = [0.0] * workers
    heapq.heapify(heap)
    for w in work:
        heapq.heappush(heap, heapq.heappop(heap) + w)
    return max(heap), sum(work) / workers


def pulling_report(work: DataFrame, workers: int) -> DataFrame:
    """Makespan over mean of each step's ranges (lambda * workers small rows a step)."""
    spark = work.sparkSession
    steps: dict[int, list[tuple[int, int]]] = {}
    for r in work.select("step", "rid", "degree_sum").collect():
        steps.setdefault(r["step"], []).append((r["rid"], r["degree_sum"]))
    rows = []
    for step, parts in sorted(steps.items()):
        span, mean = simulate_pulling([float(w) for _, w in sorted(parts)], workers)
        rows.append((step, span, mean, span / mean if mean else 1.0))
    return spark.createDataFrame(rows, "step int, makespan double, mean double, ratio double")


