"""Breadth-first search by levels: top-down, bottom-up and switching between them.

Each level is one plan.  Its result is written, which cuts the lineage and yields the counters for
the next decision.  Steps come in two forms with the same results: joins of tables, and scans of
lists stored by range with visited and frontier sets as packed words, which are at most 32 MB.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from levelgraph.balance.ranges import default_lambda, label_ranges
from levelgraph.bfs import kernels
from levelgraph.bitmap import words as bw
from levelgraph.graph.build import Graph, with_places
from levelgraph.graph.rank import global_rank
from levelgraph.plans.switch import ALPHA, BETA, StepState, choose
from levelgraph.runtime import discard, materialize

# a frontier of at most this many vertices is sent to every executor
BROADCAST_ROWS = 1 << 17
LEVEL = "v long, parent long, depth int, deg long"

VARIANTS = {
    "base": dict(order="id", two_pass=False, trim=False, ranges="equal", vectorized=False),
    "no_isolated": dict(order="id", two_pass=False, trim=False, ranges="equal", vectorized=False),
    "reordered": dict(order="id", two_pass=False, trim=False, ranges="equal", vectorized=False),
    "reordered_lb": dict(order="deg_desc", two_pass=True, trim=True, ranges="descending", vectorized=False),
    "reordered_lb_vec": dict(order="deg_desc", two_pass=True, trim=True, ranges="descending", vectorized=True),
}


@dataclass
class BfsRun:
    result: DataFrame
    steps: list[dict] = field(default_factory=list)
    seconds: float = 0.0

    def step_log(self) -> DataFrame:
        columns = "step int, direction string, phase int, frontier_vertices long, frontier_edges long, unexplored_edges long, inspected_edges long, discovered long, top_hits long, live_range_size long, seconds double"
        names = [c.split()[0] for c in columns.split(", ")]
        return self.result.sparkSession.createDataFrame([tuple(s.get(n) for n in names) for s in self.steps], columns)


def lists_in_order(graph: Graph, order: str) -> DataFrame:
    """Ranked arcs with the place in lists by ``deg_desc``, ``deg_asc`` or ``id``."""
    if order == "deg_desc":
        return graph.ranked_arcs
    keys = {"deg_asc": ["dst_deg", "dst"], "id": ["dst"]}[order]
    held = graph.__dict__.setdefault("_lists", {})
    if order not in held:
        held[order] = materialize(with_places(graph.ranked_arcs.drop("place"), keys, graph.totals["max"]), f"{graph.name}_lists_{order}")
    return held[order]


def _sized(df: DataFrame, rows: int) -> DataFrame:
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df


def top_down_step(arcs: DataFrame, degrees: DataFrame, frontier: DataFrame, before: DataFrame, n_frontier: int, depth: int, balance: str | None = None, workers: int = 8) -> DataFrame:
    """Neighbours of the frontier that are not in the last two levels, each with its best parent.

    In an undirected graph a neighbour of level k lies in level k - 1, k or k + 1, so the whole
    visited set need not be joined.  ``balance`` deals the frontier's arcs to ``workers`` tasks
    first: by runs of vertices (``static``) or by slices of every list (``sliced``).
    """
    f = frontier.select(F.col("v").alias("src"), F.col("deg").alias("src_deg"))
    if balance is None:
        looked_at = arcs.join(_sized(f, n_frontier), "src")
    else:
        looked_at = dealt_arcs(arcs, frontier, n_frontier, balance, workers)
    reached = looked_at.groupBy(F.col("dst").alias("v")).agg(F.max(F.struct("src_deg", (-F.col("src")).alias("k"))).alias("p"))
    known = before.select("v").union(frontier.select("v"))
    fresh = reached.join(known, "v", "left_anti").join(degrees, "v")
    return fresh.select("v", (-F.col("p.k")).alias("parent"), F.lit(depth).alias("depth"), "deg", F.lit(None).cast("long").alias("place"))


def dealt_arcs(arcs: DataFrame, frontier: DataFrame, n_frontier: int, balance: str, workers: int) -> DataFrame:
    """The frontier's arcs ``src, src_deg, dst, slot``, those of slot k in task k.

    ``static``: the frontier by id in equal runs of vertices, a run a task.  ``sliced``: every list
    by id in equal slices, slice k to task k, what is left of the j-th list to task j mod t."""
    placed = global_rank(frontier.select("v", "deg"), ["v"], "j").select(F.col("v").alias("src"), F.col("deg").alias("src_deg"), "j")
    mine = arcs.select("src", "dst").join(_sized(placed, n_frontier), "src")
    if balance == "static":
        slot = F.expr(f"j * {workers} div {n_frontier}")
    else:
        mine = place_in_lists(mine, ["src_deg", "j"])
        q = F.expr(f"src_deg div {workers}")
        slot = F.when((q > 0) & (F.col("i") < q * workers), F.expr(f"i div greatest(src_deg div {workers}, 1)")).otherwise(F.col("j") % workers)
    return mine.withColumn("slot", slot.cast("int")).repartitionById(workers, F.col("slot")).select("src", "src_deg", "dst", "slot")


def place_in_lists(arcs: DataFrame, keep: list[str]) -> DataFrame:
    """Adds ``i``: place of ``dst`` in the list of ``src`` by id.  Lists are numbered through one range sort, so a hub's is not one task's."""
    ranked = global_rank(arcs.select("src", "dst", *keep), ["src", "dst"], "at")
    first = ranked.groupBy("src").agg(F.min("at").alias("first"))
    return ranked.join(first, "src").withColumn("i", F.col("at") - F.col("first")).drop("at", "first")


def _best(hits: DataFrame, depth: int) -> DataFrame:
    found = hits.groupBy(F.col("src").alias("v")).agg(F.max(F.struct("dst_deg", (-F.col("dst")).alias("k"))).alias("p"), F.min("place").alias("place"), F.first("deg").alias("deg"))
    return found.select("v", (-F.col("p.k")).alias("parent"), F.lit(depth).alias("depth"), "deg", "place")


def _live(unvisited: DataFrame, ranges: list[tuple[int, int, int]]) -> list[tuple[int, int]]:
    """Trimmed stretch of each range that still holds unvisited labels (one small row a range)."""
    spark = unvisited.sparkSession
    table = spark.createDataFrame(ranges, "rid int, lo long, hi long")
    rows = unvisited.join(F.broadcast(table), (F.col("v") >= F.col("lo")) & (F.col("v") < F.col("hi"))).groupBy("rid").agg(F.min("v").alias("a"), F.max("v").alias("b")).collect()
    return sorted((r["a"], r["b"]) for r in rows)


def _within(column: str, live: list[tuple[int, int]], most: int = 48):
    """A literal filter over the live stretches, joined where they touch; it reaches the scan of the lists."""
    merged: list[list[int]] = []
    for a, b in live:
        if merged and a <= merged[-1][1] + 1:
            merged[-1][1] = max(merged[-1][1], b)
        else:
            merged.append([a, b])
    while len(merged) > most:
        gaps = sorted(range(1, len(merged)), key=lambda i: merged[i][0] - merged[i - 1][1])[: len(merged) - most]
        for i in sorted(gaps, reverse=True):
            merged[i - 1][1] = merged[i][1]
            del merged[i]
    out = F.lit(False)
    for a, b in merged:
        out = out | F.col(column).between(a, b)
    return out


def bottom_up_step(lists: DataFrame, unvisited: DataFrame, frontier: DataFrame, n_frontier: int, depth: int, two_pass: bool = True, live: list[tuple[int, int]] | None = None) -> tuple[DataFrame, int | None]:
    """Unvisited vertices with a frontier neighbour: best parent and place of the first hit.

    With ``two_pass`` the top neighbours alone are probed first (a narrow scan), and only vertices
    that missed go on to the rest of their lists.  Returns also the hits of the first pass.
    """
    f = _sized(frontier.select(F.col("v").alias("dst")), n_frontier)
    if live is not None:
        lists = lists.where(_within("src", live))
    waiting = unvisited.select(F.col("v").alias("src"))
    if not two_pass:
        return _best(lists.join(waiting, "src", "left_semi").join(f, "dst"), depth), None
    top = materialize(_best(lists.where("place = 0").join(waiting, "src", "left_semi").join(f, "dst"), depth), "top_pass")
    missed = waiting.join(top.select(F.col("v").alias("src")), "src", "left_anti")
    rest = _best(lists.where("place > 0").join(missed, "src", "left_semi").join(f, "dst"), depth)
    return top.union(rest), top.count()


def bfs(
    graph: Graph, source: int, mode: str = "hybrid", alpha: float = ALPHA, beta: float = BETA, guard: bool = True, order: str = "deg_desc",
    two_pass: bool = True, trim: bool = True, ranges: str = "descending", workers: int | None = None, lam: int | None = None, block: int = 512,
    max_depth: int | None = None, target: int | None = None, vectorized: bool | None = None, phase_plan: tuple[str, str, str] | None = None,
) -> BfsRun:
    """Breadth-first tree of ``source``: ``v, parent, depth`` of every reached vertex.

    The parent is the frontier neighbour of highest degree (least id on ties) whatever the
    direction, so every mode and option returns the same rows.  An isolated source reaches itself.

    ``vectorized`` steps scan lists stored by range, with visited and frontier sets as packed words
    (:mod:`levelgraph.bfs.kernels`); they need lists by decreasing degree and labels from 0 to
    ``MAX_LABELS``, and are the default where both hold.  The other steps are joins.  ``phase_plan``
    names the kernel of each phase: ``static`` or ``sliced`` top-down steps before and after a
    ``full`` (descending ranges, two passes, trimmed) or ``plain`` (equal ranges) bottom-up phase.
    """
    spark = graph.spark
    if phase_plan is not None:
        full = phase_plan[1] == "full"
        two_pass, trim, ranges = full, full, "descending" if full else "equal"
    total = graph.totals
    n_labels = total["top"] + 1
    fits = order == "deg_desc" and 0 <= total["least"] and n_labels <= bw.MAX_LABELS and source >= 0
    vectorized = fits and phase_plan is None if vectorized is None else vectorized and fits
    workers = workers or spark.sparkContext.defaultParallelism
    s = max(1, (lam or default_lambda(total["n"])) * workers)
    own = graph.degree_of(source)
    state = (_WordState if vectorized else _TableState)(graph, source, own, total, order, two_pass and order == "deg_desc", trim, (s, block, ranges), workers, phase_plan)
    began = time.perf_counter()
    depth, now, left = 0, "top_down", False
    n_f, m_f, m_u, n_prev = 1, own, total["m"] - own, 0
    run = BfsRun(state.every().select("v", "parent", "depth"))
    while n_f and m_f and (max_depth is None or depth < max_depth):
        turn = choose(now, left, StepState(n_f, m_f, m_u, n_prev, total["n"]), alpha, beta, guard) if mode == "hybrid" else mode
        left = left or (now == "bottom_up" and turn == "top_down")
        phase = 2 if turn == "bottom_up" else 3 if left else 1
        step_began = time.perf_counter()
        got = state.advance(turn, phase, depth + 1, n_f, target)
        inspected = m_f if turn == "top_down" else got["probes"] + m_u - got["m"]
        run.steps.append(
            dict(step=depth, direction=turn, phase=phase, frontier_vertices=n_f, frontier_edges=m_f, unexplored_edges=m_u, inspected_edges=inspected, discovered=got["n"], top_hits=got["top_hits"] if turn == "bottom_up" and state.two_pass else None, live_range_size=got["live"], seconds=time.perf_counter() - step_began)
        )
        n_prev, n_f, m_f, m_u, now = n_f, got["n"], got["m"], m_u - got["m"], turn
        depth += 1
        if got["hit"]:
            break
    run.seconds = time.perf_counter() - began
    run.result = state.every().select("v", "parent", "depth")
    return run


def prepare(graph: Graph, workers: int | None = None, lam: int | None = None, block: int = 512, ranges: str = "descending") -> None:
    """Writes what a search reads, so that the first one does not pay for it."""
    graph.ranked_arcs.count()
    total = graph.totals
    if 0 <= total["least"] and total["top"] < bw.MAX_LABELS:
        workers = workers or graph.spark.sparkContext.defaultParallelism
        kernels.range_lists(graph, total["top"] + 1, max(1, (lam or default_lambda(total["n"])) * workers), block, ranges)


def _counted(target: int | None) -> list[Column]:
    return [
        F.count("*").alias("n"), F.coalesce(F.sum("deg"), F.lit(0)).alias("m"), F.coalesce(F.sum(F.col("place") + 1), F.lit(0)).alias("probes"),
        F.coalesce(F.sum((F.col("place") == 0).cast("long")), F.lit(0)).alias("top_hits"),
        F.coalesce(F.max((F.col("v") == F.lit(target if target is not None else -1)).cast("int")), F.lit(0)).alias("hit"),
    ]


class _TableState:
    """Levels as tables; steps are joins, which have no bound on the labels."""

    def __init__(self, graph, source, own, total, order, two_pass, trim, cuts, workers, phase_plan):
        self.graph, self.two_pass, self.trim, self.workers, self.phase_plan = graph, two_pass, trim, workers, phase_plan
        self.lists = lists_in_order(graph, order)
        self.ranges = label_ranges(total["top"] + 1, *cuts)
        self.level = graph.spark.createDataFrame([(source, source, 0, own, None)], LEVEL + ", place long")
        self.before = self.level.limit(0)
        self.levels = [self.level]
        self.unvisited = None

    def every(self) -> DataFrame:
        out = self.levels[0]
        for part in self.levels[1:]:
            out = out.union(part)
        return out

    def advance(self, turn: str, phase: int, depth: int, n_f: int, target: int | None) -> dict:
        live = None
        if turn == "bottom_up":
            # written once, then only made smaller by each step's finds
            waiting = self.graph.degrees.join(self.every().select("v"), "v", "left_anti") if self.unvisited is None else self.unvisited.join(self.level.select("v"), "v", "left_anti")
            waiting = materialize(waiting.select("v", "deg"), "unvisited")
            discard(self.unvisited)
            self.unvisited = waiting
            live = _live(waiting, self.ranges) if self.trim else None
            fresh, _ = bottom_up_step(self.lists, waiting, self.level, n_f, depth, self.two_pass, live)
        else:
            balance = self.phase_plan[phase - 1] if self.phase_plan else None
            fresh = top_down_step(self.graph.arcs, self.graph.degrees, self.level, self.before, n_f, depth, balance, self.workers)
        fresh = materialize(fresh, "bfs_level")
        got = fresh.agg(*_counted(target)).first().asDict()
        self.before, self.level = self.level, fresh
        self.levels.append(fresh)
        return got | {"live": sum(b - a + 1 for a, b in live) if live is not None else None}


class _WordState:
    """Visited and frontier sets as packed words; levels are written, their words come back with the counters."""

    def __init__(self, graph, source, own, total, order, two_pass, trim, cuts, workers, phase_plan):
        self.graph, self.two_pass, self.trim = graph, two_pass, trim
        self.n_labels = max(total["top"], source) + 1
        self.lists, self.ranges = kernels.range_lists(graph, total["top"] + 1, *cuts)
        self.chunked = total["max"] > kernels.MAX_LIST
        self.bytes = 8 * total["m"]
        # labels without a list never wait for a parent
        self.visited = ~graph.packed(self.n_labels)
        self.frontier = bw.pack(np.array([source]), self.n_labels)
        self.visited = bw.merge(self.visited, self.frontier)
        self.levels = [graph.spark.createDataFrame([(source, source, 0)], "v long, parent long, depth int")]

    def every(self) -> DataFrame:
        out = self.levels[0]
        for part in self.levels[1:]:
            out = out.union(part.select("v", "parent", "depth"))
        return out

    def _files(self, stretches: list[tuple[int, int, int]]) -> DataFrame:
        """Lists of the ranges that hold one of the stretches, read from their first label to their last."""
        rids = [rid for rid, _, _ in stretches]
        near = _within("v", [(a, b) for _, a, b in stretches])
        return self.lists.where(F.col("rid").isin(rids) & near) if len(rids) < len(self.ranges) else self.lists.where(near)

    def _write(self, fresh: DataFrame, depth: int, target: int | None) -> dict:
        fresh = materialize(fresh.withColumn("depth", F.lit(depth)), "bfs_level")
        rows = bw.cells(fresh, "v", *_counted(target)).collect()  # at most labels / 32768 rows of 4 KB
        self.levels.append(fresh)
        got = {k: sum(r[k] for r in rows) for k in ("n", "m", "probes", "top_hits", "hit")}
        found = bw.from_cells(rows, self.n_labels)
        self.visited = bw.merge(self.visited, found)
        return got | {"found": found}

    def advance(self, turn: str, phase: int, depth: int, n_f: int, target: int | None) -> dict:
        sc = self.graph.spark.sparkContext
        live = None
        if turn == "bottom_up":
            stretches = bw.live_stretches(self.visited, self.ranges) if self.trim else [(rid, lo, hi - 1) for rid, lo, hi in self.ranges]
            live = sum(b - a + 1 for _, a, b in stretches) if self.trim else None
            step = kernels.bottom_up
        else:
            stretches = bw.live_stretches(~self.frontier, self.ranges)
            step = kernels.top_down
        seen, now = sc.broadcast(self.visited), sc.broadcast(self.frontier)
        if turn == "bottom_up" and self.two_pass and self.bytes > kernels.SPLIT_BYTES:
            first = self._write(kernels.top_pass(self._files(stretches), seen, now), depth, target)
            seen.unpersist()
            seen, stretches = sc.broadcast(self.visited), bw.live_stretches(self.visited, self.ranges)
            second = self._write(self._best(step(self._files(stretches), seen, now)), depth, target)
            got = {k: first[k] + second[k] for k in ("n", "m", "probes", "top_hits", "hit")} | {"found": bw.merge(first["found"], second["found"])}
        else:
            fresh = step(self._files(stretches), seen, now)
            got = self._write(self._best(fresh) if turn == "bottom_up" else fresh, depth, target)
        seen.unpersist()
        now.unpersist()
        self.frontier = got.pop("found")
        return got | {"live": live}

    def _best(self, found: DataFrame) -> DataFrame:
        return kernels.least_place(found) if self.chunked else found


def bfs_many(graph: Graph, sources: list[int], max_depth: int | None = None) -> DataFrame:
    """Depths from many sources in one loop: ``source, v, depth``.  Visited state is keyed by source."""
    spark = graph.spark
    level = spark.createDataFrame([(s, s, 0) for s in dict.fromkeys(sources)], "source long, v long, depth int")
    before, every, depth = level.limit(0), level, 0
    while max_depth is None or depth < max_depth:
        depth += 1
        known = before.select("source", "v").union(level.select("source", "v"))
        reached = level.join(graph.arcs, F.col("v") == F.col("src")).select("source", F.col("dst").alias("v")).distinct()
        fresh = materialize(reached.join(known, ["source", "v"], "left_anti").withColumn("depth", F.lit(depth)), "bfs_many")
        if fresh.isEmpty():
            discard(fresh)
            break
        before, level, every = level, fresh, every.union(fresh)
    return every


def sample_sources(graph: Graph, k: int = 64, seed: int = 7) -> DataFrame:
    """The first ``k`` non-isolated vertices by a hash of seed and id: ``rank, v``."""
    hashed = graph.degrees.select("v", F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("v").cast("string"))).alias("h"))
    return hashed.orderBy("h", "v").limit(k).withColumn("rank", F.row_number().over(Window.orderBy("h", "v")).cast("long")).select("rank", "v")


def validate(graph: Graph, result: DataFrame, source: int) -> DataFrame:
    """Rules of a breadth-first tree with how much each checked and how much broke it."""
    r = result.select("v", "parent", "depth")
    parent = r.select(F.col("v").alias("parent"), F.col("depth").alias("parent_depth"))
    tree = r.where(F.col("v") != source).join(parent, "parent", "left")
    level = tree.agg(F.count("*").alias("checked"), F.coalesce(F.sum((~F.coalesce(F.col("parent_depth") + 1 == F.col("depth"), F.lit(False))).cast("long")), F.lit(0)).alias("violations")).select(F.lit("parent_is_one_level_up").alias("rule"), "checked", "violations")
    arcs = graph.arcs.select(F.col("src").alias("parent"), F.col("dst").alias("v"), F.lit(1).alias("there"))
    real = tree.join(arcs, ["parent", "v"], "left").agg(F.count("*").alias("checked"), F.coalesce(F.sum(F.isnull("there").cast("long")), F.lit(0)).alias("violations")).select(F.lit("parent_arc_exists").alias("rule"), "checked", "violations")
    ends = graph.edges.join(r.select(F.col("v").alias("u"), F.col("depth").alias("du")), "u", "left").join(r.select("v", F.col("depth").alias("dv")), "v", "left")
    span = ends.where("du is not null and dv is not null").agg(F.count("*").alias("checked"), F.coalesce(F.sum((F.abs(F.col("du") - F.col("dv")) > 1).cast("long")), F.lit(0)).alias("violations")).select(F.lit("edge_spans_one_level").alias("rule"), "checked", "violations")
    whole = ends.where("du is not null or dv is not null").agg(F.count("*").alias("checked"), F.coalesce(F.sum((F.isnull("du") | F.isnull("dv")).cast("long")), F.lit(0)).alias("violations")).select(F.lit("component_is_whole").alias("rule"), "checked", "violations")
    root = r.where(F.col("v") == source).agg(F.count("*").alias("checked"), F.coalesce(F.sum(((F.col("parent") != F.col("v")) | (F.col("depth") != 0)).cast("long")), F.lit(0)).alias("violations")).select(F.lit("source_is_root").alias("rule"), "checked", "violations")
    return level.union(real).union(span).union(whole).union(root)
