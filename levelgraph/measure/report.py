"""Throughput, scaling, energy and cost figures from runs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from levelgraph.plans.published import CACHE, SCALING


def teps_summary(runs: DataFrame) -> DataFrame:
    """Of ``edges, seconds``: mean, harmonic mean, extremes and quartiles of edges per second."""
    t = runs.select((F.col("edges") / F.col("seconds")).alias("teps"))
    q = lambda p: F.expr(f"percentile(teps, {p})")
    return t.agg(F.count("*").alias("runs"), F.avg("teps").alias("mean"), (F.count("*") / F.sum(1 / F.col("teps"))).alias("harmonic_mean"), F.min("teps").alias("min"), q(0.25).alias("q1"), q(0.5).alias("median"), q(0.75).alias("q3"), F.max("teps").alias("max"))


def mteps_per_watt(mteps: float, watts: float) -> float:
    return mteps / watts


def scaling_report(runs: DataFrame) -> DataFrame:
    """Of ``variant, threads, teps``: speedup over one thread and efficiency."""
    one = runs.where("threads = 1").select("variant", F.col("teps").alias("base"))
    return runs.join(one, "variant").select("variant", "threads", "teps", (F.col("teps") / F.col("base")).alias("speedup"), (F.col("teps") / F.col("base") / F.col("threads")).alias("efficiency"))


def amortisation(reorder_seconds: float, with_order: float, without_order: float) -> float:
    """Searches after which reordering has paid for itself; infinite where it gains nothing."""
    gain = without_order - with_order
    return reorder_seconds / gain if gain > 0 else float("inf")


def partial_efficiency(runs: DataFrame, value: str = "seconds") -> DataFrame:
    """Best value over ratios divided by each ratio's value: 1 for the best."""
    best = F.min(value).over(Window.partitionBy("graph"))
    return runs.withColumn("efficiency", best / F.col(value))


def cache_report(before: DataFrame, after: DataFrame) -> DataFrame:
    """Of single rows ``references, misses``: rates and reductions in percent."""
    b, a = before.select(F.col("references").alias("rb"), F.col("misses").alias("mb")), after.select(F.col("references").alias("ra"), F.col("misses").alias("ma"))
    both = b.join(F.broadcast(a), how="cross")  # two single rows
    cut = lambda x, y: F.round(100 * (1 - F.col(y) / F.col(x)), 6)
    return both.select("rb", "ra", cut("rb", "ra").alias("references_cut"), "mb", "ma", cut("mb", "ma").alias("misses_cut"), F.round(100 * F.col("mb") / F.col("rb"), 6).alias("rate_before"), F.round(100 * F.col("ma") / F.col("ra"), 6).alias("rate_after"))


def amortisation_table(costs: DataFrame) -> DataFrame:
    """Of ``row, reorder, with_order, without_order``: speedup, and runs that pay for the order (null where it gains nothing)."""
    gain = F.col("without_order") - F.col("with_order")
    runs = F.when(gain > 0, F.round(F.col("reorder") / gain)).cast("long")
    return costs.select("row", F.round(F.col("without_order") / F.col("with_order"), 6).alias("speedup"), runs.alias("runs"))


def published_check(spark: SparkSession) -> DataFrame:
    """Printed reductions, rates and speedups beside what the printed counts give."""
    rows = []
    for scale, r0, r1, rc, m0, m1, mc, p0, p1 in CACHE:
        rows += [("references_cut", scale, rc, 100 * (1 - r1 / r0)), ("misses_cut", scale, mc, 100 * (1 - m1 / m0)), ("rate_before", scale, p0, 100 * m0 / r0), ("rate_after", scale, p1, 100 * m1 / r1)]
    for n, g0, s0, g1, s1 in SCALING:
        rows += [("speedup_plain", n, s0, g0 / SCALING[0][1]), ("speedup_reordered", n, s1, g1 / SCALING[0][3])]
    return spark.createDataFrame([(t, k, p, round(v, 4)) for t, k, p, v in rows], "table string, row long, printed double, recomputed double")
