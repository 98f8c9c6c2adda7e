"""Locality measures of an ordering."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelgraph.graph.build import Graph, relabel


def labelled_edges(graph: Graph, perm: DataFrame) -> DataFrame:
    return relabel(graph.edges, perm).select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"))


def bandwidth(edges: DataFrame) -> DataFrame:
    """Largest label distance of an edge, and the sum over rows of the distance to their leftmost neighbour."""
    widest = F.max(F.col("v") - F.col("u"))
    # the leftmost neighbour of a row matters only where it lies left of the diagonal
    left = edges.groupBy("v").agg(F.min("u").alias("u"))
    profile = left.agg(F.coalesce(F.sum(F.col("v") - F.col("u")), F.lit(0)).alias("profile"))
    return edges.agg(F.coalesce(widest, F.lit(0)).alias("bandwidth")).join(F.broadcast(profile), how="cross")  # two single rows


def gap_stats(edges: DataFrame) -> DataFrame:
    gap = edges.select((F.col("v") - F.col("u")).alias("g"))
    return gap.agg(F.round(F.avg("g"), 6).alias("mean_gap"), F.expr("cast(percentile_disc(0.5) within group (order by g) as long)").alias("p50"), F.expr("cast(percentile_disc(0.95) within group (order by g) as long)").alias("p95"))


def spy_grid(edges: DataFrame, n_labels: int, bins: int = 16) -> DataFrame:
    """Arcs per tile of a bins x bins picture of the adjacency matrix."""
    width = max(1, -(-n_labels // bins))
    arcs = edges.select(F.explode(F.array(F.struct(F.col("u").alias("a"), F.col("v").alias("b")), F.struct(F.col("v").alias("a"), F.col("u").alias("b")))).alias("x"))
    return arcs.groupBy(F.expr(f"x.a div {width}").alias("row_tile"), F.expr(f"x.b div {width}").alias("col_tile")).agg(F.count("*").alias("arcs"))


def touched_tiles(edges: DataFrame, line_bits: int = 512) -> DataFrame:
    grid = edges.select(F.expr(f"u div {line_bits}").alias("a"), F.expr(f"v div {line_bits}").alias("b"))
    both = grid.union(grid.select("b", "a")).distinct()
    return both.agg(F.count("*").alias("tiles"))


def envelope_curve(edges: DataFrame, n_labels: int, bins: int = 16) -> DataFrame:
    """Least and largest row label in each band of columns."""
    width = max(1, -(-n_labels // bins))
    both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    return both.groupBy(F.expr(f"v div {width}").alias("band")).agg(F.min("u").alias("lo"), F.max("u").alias("hi"))


def degree_by_label(graph: Graph, perm: DataFrame, parts: int = 4) -> DataFrame:
    """Mean degree of each of ``parts`` equal stretches of the labels of non-isolated vertices."""
    n = graph.degrees.count()
    joined = graph.degrees.join(perm.select("v", "label"), "v")
    return joined.groupBy(F.expr(f"label * {parts} div {max(n, 1)}").alias("part")).agg(F.count("*").alias("n"), F.sum("deg").alias("degree_sum"), F.round(F.avg("deg"), 6).alias("mean_deg"))


def component_census(perm: DataFrame) -> DataFrame:
    """Components by size, with the label range that those of one size span."""
    comps = perm.where("comp is not null").groupBy("comp").agg(F.count("*").alias("size"), F.min("label").alias("lo"), F.max("label").alias("hi"))
    return comps.groupBy("size").agg(F.count("*").alias("n_components"), F.min("lo").alias("first_label"), F.max("hi").alias("last_label"))
