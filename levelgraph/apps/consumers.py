"""Applications of breadth-first search."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelgraph.bfs.hybrid import bfs, bfs_many
from levelgraph.graph.build import Graph
from levelgraph.reorder.components import star_contraction
from levelgraph.runtime import discard, materialize


def components(graph: Graph) -> DataFrame:
    """``v, comp`` for every vertex: the least id it reaches."""
    found = star_contraction(graph.edges, "u", "v")
    return graph.vertices.select("v").join(found, "v", "left").select("v", F.coalesce("comp", "v").alias("comp"))


def shortest_path(graph: Graph, source: int, target: int) -> DataFrame:
    """``hop, v`` along one shortest path; empty if there is none.  Follows parents with one narrow filter a hop."""
    run = bfs(graph, source, target=target)
    rows, v = [], target
    found = run.result.where(F.col("v") == target).first()
    while found is not None:
        rows.append((found["depth"], found["v"]))
        if found["depth"] == 0:
            break
        v = found["parent"]
        found = run.result.where(F.col("v") == v).first()
    return graph.spark.createDataFrame(rows, "hop long, v long")


def spanning_forest(graph: Graph, max_levels: int | None = None) -> DataFrame:
    """One tree per component, all grown at once from the least id of each: ``v, parent, comp``."""
    comps = materialize(components(graph), "forest_comps")
    level = materialize(comps.where("v = comp").select("v", F.col("v").alias("parent"), "comp"), "forest")
    every, before, depth = level, level.limit(0), 0
    while max_levels is None or depth < max_levels:
        known = before.select("v").union(level.select("v"))
        grown = level.join(graph.arcs, F.col("v") == F.col("src")).groupBy(F.col("dst").alias("v")).agg(F.min("src").alias("parent"), F.first("comp").alias("comp"))
        fresh = materialize(grown.join(known, "v", "left_anti"), "forest")
        depth += 1
        if fresh.isEmpty():
            discard(fresh)
            break
        before, level, every = level, fresh, every.union(fresh)
    return every


def eccentricity(graph: Graph, sources: list[int]) -> DataFrame:
    return bfs_many(graph, sources).groupBy("source").agg(F.max("depth").alias("eccentricity"))


def closeness(graph: Graph, sources: list[int]) -> DataFrame:
    """Reached vertices, sum of distances, and the usual quotient of each source."""
    d = bfs_many(graph, sources).groupBy("source").agg(F.count("*").alias("reached"), F.sum("depth").alias("total"))
    return d.withColumn("closeness", F.round(F.when(F.col("total") > 0, (F.col("reached") - 1) / F.col("total")).otherwise(0.0), 6))


def bipartite_conflicts(graph: Graph) -> DataFrame:
    """Edges whose ends get the same colour when every component is coloured by parity of depth."""
    comps = components(graph)
    level = materialize(comps.where("v = comp").select("v", F.lit(0).alias("depth")), "colour")
    every, before, depth = level, level.limit(0), 0
    while True:
        depth += 1
        known = before.select("v").union(level.select("v"))
        fresh = level.select(F.col("v").alias("src")).join(graph.arcs, "src").select(F.col("dst").alias("v")).distinct().join(known, "v", "left_anti")
        fresh = materialize(fresh.withColumn("depth", F.lit(depth)), "colour")
        if fresh.isEmpty():
            break
        before, level, every = level, fresh, every.union(fresh)
    a, b = every.select(F.col("v").alias("u"), F.col("depth").alias("du")), every.select("v", F.col("depth").alias("dv"))
    return graph.edges.join(a, "u").join(b, "v").where("du % 2 = dv % 2").select("u", "v")


def betweenness(graph: Graph, sources: list[int]) -> DataFrame:
    """Sampled betweenness: shortest paths counted level by level, then dependencies summed backwards."""
    d = materialize(bfs_many(graph, sources), "between_depth")
    deep = d.agg(F.max("depth").alias("d")).first()["d"] or 0
    arcs = graph.arcs
    step = d.select("source", F.col("v").alias("src"), F.col("depth").alias("ds")).join(arcs, "src").join(d.select("source", F.col("v").alias("dst"), F.col("depth").alias("dd")), ["source", "dst"]).where("dd = ds + 1")
    step = materialize(step.select("source", "src", "dst", "ds"), "between_steps")
    sigma = d.where("depth = 0").select("source", "v", "depth", F.lit(1.0).alias("paths"))
    levels = [materialize(sigma, "between_paths")]
    for k in range(deep):
        part = levels[-1].select("source", F.col("v").alias("src"), "paths").join(step.where(F.col("ds") == k), ["source", "src"]).groupBy("source", F.col("dst").alias("v")).agg(F.sum("paths").alias("paths"))
        levels.append(materialize(part.select("source", "v", F.lit(k + 1).alias("depth"), "paths"), "between_paths"))
    below = levels[-1].select("source", "v", "paths", F.lit(0.0).alias("dep"))
    total = below
    for k in range(deep - 1, -1, -1):
        up = step.where(F.col("ds") == k).join(below.select("source", F.col("v").alias("dst"), F.col("paths").alias("pw"), "dep"), ["source", "dst"])
        share = up.join(levels[k].select("source", F.col("v").alias("src"), F.col("paths").alias("pv")), ["source", "src"]).groupBy("source", "src").agg(F.sum(F.col("pv") / F.col("pw") * (1 + F.col("dep"))).alias("dep"))
        below = levels[k].join(share.withColumnRenamed("src", "v"), ["source", "v"], "left").select("source", "v", "paths", F.coalesce("dep", F.lit(0.0)).alias("dep"))
        below = materialize(below, "between_dep")
        total = total.union(below)
    return total.where("v <> source").groupBy("v").agg(F.round(F.sum("dep"), 6).alias("betweenness"))
