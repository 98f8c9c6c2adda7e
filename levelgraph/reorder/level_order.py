"""Reverse level orders: a breadth-first visit by increasing degree, reversed.

The sequential queue is equivalent to a level-by-level rule: a vertex of the next level is claimed
by its earliest-placed neighbour in the current one, so the next level is the set of unvisited
neighbours sorted by (place of the earliest parent, degree, id).  All components advance together,
ordered by the least (degree, id) of each.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from levelgraph.graph.build import Graph
from levelgraph.graph.rank import global_rank, ranked_rows
from levelgraph.reorder.components import star_contraction
from levelgraph.runtime import discard, materialize

SMALL_CAP = 64


def component_of(arcs: DataFrame, degrees: DataFrame) -> DataFrame:
    """``v, deg, comp`` with ``comp`` the least id of the component."""
    comps = star_contraction(arcs, "src", "dst")
    return degrees.join(comps, "v", "left").select("v", "deg", F.coalesce("comp", "v").alias("comp"))


def _farthest(arcs: DataFrame, seeds: DataFrame, degrees: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Eccentricity of each component's seed, and its least-degree vertex of the last level."""
    level = materialize(seeds.select("comp", F.col("seed").alias("v"), F.lit(0).alias("level")), "peripheral")
    seen, depth = level, 0
    while True:
        reached = level.join(arcs, F.col("v") == F.col("src")).select("comp", F.col("dst").alias("v")).distinct()
        depth += 1
        level = materialize(reached.join(seen.where(F.col("level") >= depth - 2).select("v"), "v", "left_anti").select("comp", "v", F.lit(depth).alias("level")), "peripheral")
        if level.isEmpty():
            break
        seen = seen.union(level)
    last = seen.groupBy("comp").agg(F.max("level").alias("ecc"))
    ends = seen.join(last, "comp").where("level = ecc").join(degrees, "v")
    return last, ends.groupBy("comp").agg(F.min(F.struct("deg", "v")).alias("x")).select("comp", F.col("x.v").alias("seed"))


def _seeds(arcs: DataFrame, placed: DataFrame, degrees: DataFrame, start: str) -> DataFrame:
    """``comp, seed, by`` where ``by`` orders the components."""
    least = placed.groupBy("comp").agg(F.min(F.struct("deg", "v")).alias("by"), F.count("*").alias("size"))
    seeds = least.select("comp", F.col("by.v").alias("seed"), "by", "size")
    if start != "min_degree":
        seeds = materialize(seeds, "seeds")
    if start == "pseudo_peripheral":
        now = seeds.select("comp", "seed")
        ecc, ends = _farthest(arcs, now, degrees)
        for _ in range(8):
            new_ecc, new_ends = _farthest(arcs, ends, degrees)
            grown = materialize(ecc.join(new_ecc.withColumnRenamed("ecc", "new"), "comp").join(now, "comp").join(ends.withColumnRenamed("seed", "end"), "comp").select("comp", "ecc", "new", F.when(F.col("new") > F.col("ecc"), F.col("end")).otherwise(F.col("seed")).alias("seed")), "grown")
            now = grown.select("comp", "seed")
            if grown.where("new > ecc").isEmpty():
                break
            ecc, ends = new_ecc, new_ends
        seeds = seeds.drop("seed").join(now, "comp")
    elif start != "min_degree":
        raise ValueError(f"unknown start {start!r}")
    return seeds


def _visit_small(rows: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Sequential visits of whole small components, one row of lists for each."""
    for pdf in rows:
        out = []
        for comp, seed, arcs in zip(pdf["comp"], pdf["seed"], pdf["arcs"], strict=True):
            lists: dict[int, list] = {}
            for a in arcs:
                lists.setdefault(a["src"], []).append((a["deg"], a["dst"]))
            order, level = [seed], {seed: 0}
            for v in order:
                for _, w in sorted(lists.get(v, ())):
                    if w not in level:
                        level[w] = level[v] + 1
                        order.append(w)
            out += [(comp, v, level[v], k) for k, v in enumerate(order)]
        yield pd.DataFrame(out, columns=["comp", "v", "level", "pos"])


def visit_order(arcs: DataFrame, degrees: DataFrame, start: str = "min_degree", small_cap: int = SMALL_CAP) -> DataFrame:
    """``visit, v, comp, level``: place of each vertex in the sequential visit of all components."""
    placed = materialize(component_of(arcs, degrees), "placed")
    seeds = materialize(_seeds(arcs, placed, degrees, start), "seeds")
    ranked = global_rank(seeds, ["by.deg", "by.v"], "comp_rank").select("comp", "seed", "size", "comp_rank")
    deg = degrees.select("v", "deg")

    small = ranked.where(F.col("size") <= small_cap)
    inside = arcs.join(placed.select(F.col("v").alias("src"), "comp"), "src").join(small.select("comp", "seed"), "comp").join(deg.select(F.col("v").alias("dst"), "deg"), "dst")
    # at most small_cap ** 2 arcs a group
    packed = inside.groupBy("comp", "seed").agg(F.collect_list(F.struct("src", "dst", "deg")).alias("arcs"))
    visited = [packed.mapInPandas(_visit_small, "comp long, v long, level int, pos long")]

    large = ranked.where(F.col("size") > small_cap)
    level = materialize(large.select("comp", F.col("seed").alias("v"), F.lit(0).alias("level"), F.col("comp_rank").alias("pos")), "level")
    before, depth, n = level.limit(0), 0, level.count()
    while n:
        visited.append(level)
        known = before.select("v").union(level.select("v"))
        claimed = level.join(arcs, F.col("v") == F.col("src")).groupBy(F.col("dst").alias("v")).agg(F.min(F.struct("pos", "comp")).alias("p"))
        fresh = claimed.join(known, "v", "left_anti").join(deg, "v")
        depth += 1
        # the ranked rows are on disk already, and their number is the test for the end
        ranked_level = global_rank(fresh.select("v", F.col("p.comp").alias("comp"), F.col("p.pos").alias("at"), "deg"), ["at", "deg", "v"], "pos")
        before, level, n = level, ranked_level.select("comp", "v", F.lit(depth).alias("level"), "pos"), ranked_rows(ranked_level)
    every = visited[0]
    for part in visited[1:]:
        every = every.union(part.select("comp", "v", "level", "pos"))
    every = every.join(ranked.select("comp", "comp_rank"), "comp")
    ranked_visit = global_rank(every, ["comp_rank", "level", "pos"], "visit")
    out = ranked_visit.select("visit", "v", "comp", "level")
    out._levelgraph_rows = ranked_rows(ranked_visit)
    discard(placed)
    return out


def _with_isolated(graph: Graph, labelled: DataFrame, isolated: str) -> DataFrame:
    if isolated == "drop":
        return labelled
    n = labelled.count()
    lone = global_rank(graph.isolated(), ["v"], "label").select((F.col("label") + n).alias("label"), "v", F.lit(None).cast("long").alias("comp"), F.lit(None).cast("int").alias("level"))
    return labelled.union(lone)


def reverse_level_order(graph: Graph, start: str = "min_degree", reverse: bool = True, isolated: str = "append", small_cap: int = SMALL_CAP) -> DataFrame:
    """Permutation ``label, v, comp, level``; isolated vertices come last or are left out."""
    visit = visit_order(graph.arcs, graph.degrees, start, small_cap)
    n = ranked_rows(visit)
    label = F.lit(n - 1) - F.col("visit") if reverse else F.col("visit")
    return _with_isolated(graph, visit.select(label.alias("label"), "v", "comp", "level"), isolated)


def partial_level_order(graph: Graph, p: float, select: str = "degree_desc", isolated: str = "append", small_cap: int = SMALL_CAP) -> DataFrame:
    """Reorders the ceil(p * n) vertices chosen by ``select`` only.

    The other non-isolated vertices keep their natural order and come first, then the reordered
    block, isolated vertices last.  A chosen vertex without a chosen neighbour counts as not
    chosen.  With p = 1 this is the full order, with p = 0 the natural one.
    """
    if select == "visit_prefix":
        visit = visit_order(graph.arcs, graph.degrees, small_cap=small_cap)
        n = graph.degrees.count()
        picked = visit.where(F.col("visit") < F.ceil(F.lit(p) * n)).select("v")
        block = visit.join(picked, "v").select("v", "comp", "level", F.col("visit"))
    else:
        order = {"degree_desc": [F.desc("deg"), "v"], "degree_asc": ["deg", "v"]}[select]
        n = graph.degrees.count()
        picked = materialize(global_rank(graph.degrees, order, "at").where(F.col("at") < F.ceil(F.lit(p) * n)).select("v"), "picked")
        arcs = graph.arcs.join(picked.withColumnRenamed("v", "src"), "src", "left_semi").join(picked.withColumnRenamed("v", "dst"), "dst", "left_semi")
        arcs = materialize(arcs, "induced")
        degrees = materialize(arcs.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("deg")), "induced_degrees")
        block = visit_order(arcs, degrees, small_cap=small_cap)
    block = materialize(block, "block")
    rest = global_rank(graph.degrees.select("v").join(block.select("v"), "v", "left_anti"), ["v"], "label")
    labelled = rest.select("label", "v", F.lit(None).cast("long").alias("comp"), F.lit(None).cast("int").alias("level")).union(
        block.select((F.lit(n - 1) - F.col("visit")).alias("label"), "v", "comp", "level")
    )
    return _with_isolated(graph, labelled, isolated)


def degree_order(graph: Graph, desc: bool = False, isolated: str = "append") -> DataFrame:
    order = [F.desc("deg"), "v"] if desc else ["deg", "v"]
    ranked = global_rank(graph.degrees, order, "label")
    return _with_isolated(graph, ranked.select("label", "v", F.lit(None).cast("long").alias("comp"), F.lit(None).cast("int").alias("level")), isolated)


def natural_order(graph: Graph, isolated: str = "keep") -> DataFrame:
    """Dense labels by id over all vertices (``keep``), over the others only (``drop``), or with isolated ones last."""
    if isolated == "keep":
        return global_rank(graph.vertices.select("v"), ["v"], "label").select("label", "v", F.lit(None).cast("long").alias("comp"), F.lit(None).cast("int").alias("level"))
    ranked = global_rank(graph.degrees.select("v"), ["v"], "label")
    return _with_isolated(graph, ranked.select("label", "v", F.lit(None).cast("long").alias("comp"), F.lit(None).cast("int").alias("level")), isolated)


def random_order(graph: Graph, seed: int = 7, isolated: str = "keep") -> DataFrame:
    """A fixed shuffle of the labels: rank of an md5 of seed and id."""
    base = graph.vertices.select("v") if isolated == "keep" else graph.degrees.select("v")
    hashed = base.withColumn("h", F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("v").cast("string"))))
    return global_rank(hashed, ["h", "v"], "label").select("label", "v", F.lit(None).cast("long").alias("comp"), F.lit(None).cast("int").alias("level"))


def perm_invert(perm: DataFrame) -> DataFrame:
    return perm.select(F.col("v").alias("label"), F.col("label").alias("v"))


def perm_compose(first: DataFrame, second: DataFrame) -> DataFrame:
    """Labels of ``second`` given to the labels of ``first``."""
    return first.select("v", F.col("label").alias("mid")).join(second.select(F.col("v").alias("mid"), "label"), "mid").select("label", "v")


def bijection_violations(perm: DataFrame, n: int) -> DataFrame:
    """Labels or vertices that do not occur exactly once, or labels outside [0, n); empty for a permutation."""
    twice = perm.groupBy("label").count().where("count <> 1").select(F.lit("label").alias("what"), F.col("label").alias("id"))
    again = perm.groupBy("v").count().where("count <> 1").select(F.lit("v").alias("what"), F.col("v").alias("id"))
    outside = perm.where((F.col("label") < 0) | (F.col("label") >= n)).select(F.lit("range").alias("what"), F.col("label").alias("id"))
    return twice.union(again).union(outside)
