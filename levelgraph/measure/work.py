"""Work of a search in closed form from its depths, and the line-trace model of locality."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from levelgraph.balance.ranges import with_range
from levelgraph.bfs import kernels
from levelgraph.bfs.hybrid import lists_in_order
from levelgraph.bitmap import words as bw
from levelgraph.graph.build import Graph
from levelgraph.graph.rank import global_rank
from levelgraph.runtime import materialize


def level_sizes(graph: Graph, depths: DataFrame) -> DataFrame:
    """Frontier size and degree sum of each step."""
    return depths.join(graph.degrees, "v").groupBy(F.col("depth").alias("step")).agg(F.count("*").alias("frontier_vertices"), F.sum("deg").alias("frontier_edges"))


def frontier_profile(graph: Graph, depths: DataFrame) -> DataFrame:
    rows = depths.join(graph.degrees, "v").groupBy(F.col("depth").alias("step"))
    return rows.agg(F.count("*").alias("frontier_vertices"), F.sum("deg").alias("frontier_edges"), F.max("deg").alias("max_degree"), F.round(F.avg("deg"), 6).alias("mean_degree"))


def inspected_top_down(graph: Graph, depths: DataFrame) -> DataFrame:
    """A top-down step looks at every arc of its frontier."""
    return level_sizes(graph, depths).select("step", F.col("frontier_edges").alias("inspected_edges"))


def first_hits(graph: Graph, depths: DataFrame, order: str) -> DataFrame:
    """For each reached vertex but the source, the place in its list of its first neighbour one level up."""
    lists = lists_in_order(graph, order)
    d = depths.select(F.col("v").alias("src"), F.col("depth").alias("ds"))
    e = depths.select(F.col("v").alias("dst"), F.col("depth").alias("dd"))
    return lists.join(d, "src").join(e, "dst").where("ds = dd + 1").groupBy("src", "ds").agg(F.min("place").alias("place"), F.first("deg").alias("deg"))


def inspected_bottom_up(graph: Graph, depths: DataFrame, order: str = "deg_desc") -> DataFrame:
    """A bottom-up step looks at each unvisited list up to the first hit, at all of it where there is none.

    A vertex of depth d hits at step d - 1 only, so earlier steps read its whole list and later
    ones none of it; vertices out of reach are read whole in every step."""
    hits = first_hits(graph, depths, order)
    deep = depths.agg(F.max("depth").alias("d")).first()["d"] or 0
    hit = hits.groupBy((F.col("ds") - 1).alias("step")).agg(F.sum(F.col("place") + 1).alias("n"))
    rows = graph.degrees.join(depths.select("v", "depth"), "v", "left").select("deg", F.coalesce("depth", F.lit(deep + 2)).alias("depth"))
    rows = rows.groupBy("depth").agg(F.sum("deg").alias("deg")).where("depth >= 2")  # a row for each level
    missed = rows.select("deg", F.explode(F.sequence(F.lit(0), F.least(F.col("depth") - 2, F.lit(deep)))).alias("step")).groupBy("step").agg(F.sum("deg").alias("n"))
    return hit.union(missed).groupBy("step").agg(F.sum("n").alias("inspected_edges"))


def top_pass_hits(graph: Graph, depths: DataFrame) -> DataFrame:
    """Unvisited vertices of each bottom-up step whose top neighbour is in the frontier, and the others."""
    deep = depths.agg(F.max("depth").alias("d")).first()["d"] or 0
    top = graph.ranked_arcs.where("place = 0").select(F.col("src").alias("v"), "dst")
    rows = top.join(depths.select("v", "depth"), "v", "left").join(depths.select(F.col("v").alias("dst"), F.col("depth").alias("dd")), "dst", "left")
    rows = rows.select(F.coalesce("depth", F.lit(deep + 1)).alias("depth"), F.coalesce("dd", F.lit(-1)).alias("dd")).groupBy("depth", "dd").agg(F.count("*").alias("n"))
    steps = rows.where("depth > 0").select("n", "dd", F.explode(F.sequence(F.lit(0), F.col("depth") - 1)).alias("step"))
    return steps.groupBy("step").agg(F.sum("n").alias("unvisited"), F.sum(F.when(F.col("dd") == F.col("step"), F.col("n")).otherwise(0)).alias("hits")).select("step", "unvisited", "hits", (F.col("unvisited") - F.col("hits")).alias("misses"))


def probe_trace(graph: Graph, depths: DataFrame, step: int, order: str = "deg_desc", line_bits: int = 64) -> DataFrame:
    """Bitmap lines in the order in which one bottom-up step probes them: ``v, i, line``.

    Vertices by id; each first its own visited bit (i = 0), then its list up to the first hit."""
    lists = lists_in_order(graph, order)
    waiting = graph.degrees.join(depths.select("v", "depth"), "v", "left").where(F.isnull("depth") | (F.col("depth") > step)).select("v", "deg")
    now = depths.where(F.col("depth") == step).select(F.col("v").alias("dst"), F.lit(1).alias("in_frontier"))
    arcs = lists.join(waiting.select(F.col("v").alias("src")), "src", "left_semi").join(now, "dst", "left")
    stop = arcs.where("in_frontier = 1").groupBy("src").agg(F.min("place").alias("stop"))
    probes = arcs.join(stop, "src", "left").where("stop is null or place <= stop").select(F.col("src").alias("v"), (F.col("place") + 1).alias("i"), F.expr(f"dst div {line_bits}").alias("line"))
    return waiting.select("v", F.lit(0).cast("long").alias("i"), F.expr(f"v div {line_bits}").alias("line")).union(probes)


def line_switches(trace: DataFrame) -> DataFrame:
    """References, and references whose line differs from the one before (a cache of one line).

    Switches inside a vertex need only its own rows; those between vertices need the last line of
    the vertex before, found by global rank."""
    from pyspark.sql import Window

    inner = trace.withColumn("was", F.lag("line").over(Window.partitionBy("v").orderBy("i")))
    per = inner.groupBy("v").agg(F.count("*").alias("refs"), F.sum((F.col("was") != F.col("line")).cast("long")).alias("inner"), F.min_by("line", "i").alias("first"), F.max_by("line", "i").alias("last"))
    ranked = global_rank(per, ["v"], "at")
    before = ranked.select((F.col("at") + 1).alias("at"), F.col("last").alias("before"))
    rows = ranked.join(before, "at", "left")
    return rows.agg(F.coalesce(F.sum("refs"), F.lit(0)).alias("references"), F.coalesce(F.sum(F.coalesce("inner", F.lit(0)) + (F.isnull("before") | (F.col("before") != F.col("first"))).cast("long")), F.lit(0)).alias("switches"))


def line_misses(trace: DataFrame, capacity: int, shards: int = 1) -> DataFrame:
    """Misses of least-recently-used caches of ``capacity`` lines; one cache for each of ``shards`` runs of vertices.

    The model is sequential by nature: one shard replays the whole trace on one worker."""
    from collections import OrderedDict

    def replay(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        cache, refs, misses = OrderedDict(), 0, 0
        for pdf in frames:
            for line in pdf["line"].tolist():
                refs += 1
                if line in cache:
                    cache.move_to_end(line)
                else:
                    misses += 1
                    cache[line] = None
                    if len(cache) > capacity:
                        cache.popitem(last=False)
        yield pd.DataFrame({"references": [refs], "misses": [misses]})

    dealt = trace.repartitionByRange(shards, "v").sortWithinPartitions("v", "i") if shards > 1 else trace.coalesce(1).sortWithinPartitions("v", "i")
    return dealt.mapInPandas(replay, "references long, misses long").agg(F.sum("references").alias("references"), F.sum("misses").alias("misses"))


def probe_traces(graph: Graph, depths: DataFrame, steps: tuple[int, ...], line_bits: int = 64) -> DataFrame:
    """Lines that bottom-up steps of several searches probe: ``source, step, v, i, line`` from depths ``source, v, depth``."""
    lists = graph.ranked_arcs
    sources = [r["source"] for r in depths.select("source").distinct().collect()]  # the sampled sources
    if not sources:
        return graph.degrees.limit(0).select(*[F.lit(0).cast("long").alias(c) for c in ("source", "step", "v", "i", "line")])
    here, there = depths.select("source", F.col("v").alias("src"), F.col("depth").alias("ds")), depths.select("source", F.col("v").alias("dst"), F.col("depth").alias("dd"))
    stop = lists.join(here, "src").join(there, ["source", "dst"]).where("ds = dd + 1").groupBy("source", F.col("src").alias("v")).agg(F.min("place").alias("stop"))
    each = graph.degrees.select("v", F.explode(F.array(*map(F.lit, sources))).alias("source")).join(depths, ["source", "v"], "left")
    each = each.select("source", "v", "depth", F.explode(F.array(*[F.lit(k).cast("long") for k in steps])).alias("step")).where("depth is null or depth > step").join(stop, ["source", "v"], "left")
    probes = each.join(lists.select(F.col("src").alias("v"), "dst", "place"), "v").where("depth is null or depth <> step + 1 or place <= stop")
    own = each.select("source", "step", "v", F.lit(0).cast("long").alias("i"), F.expr(f"v div {line_bits}").alias("line"))
    return own.union(probes.select("source", "step", "v", F.col("place") + 1, F.expr(f"dst div {line_bits}")))


def switches_by_source(trace: DataFrame) -> DataFrame:
    """``source, references, switches`` of a cache of one line that each step starts empty."""
    from pyspark.sql import Window

    keys = ["source", "step", "v"]
    inner = trace.withColumn("was", F.lag("line").over(Window.partitionBy(*keys).orderBy("i")))
    per = inner.groupBy(*keys).agg(F.count("*").alias("refs"), F.sum((F.col("was") != F.col("line")).cast("long")).alias("inner"), F.min_by("line", "i").alias("first"), F.max_by("line", "i").alias("last"))
    ranked = global_rank(per, keys, "at")
    before = ranked.select((F.col("at") + 1).alias("at"), "source", "step", F.col("last").alias("before"))
    rows = ranked.join(before, ["at", "source", "step"], "left")
    new = F.coalesce("inner", F.lit(0)) + (F.isnull("before") | (F.col("before") != F.col("first"))).cast("long")
    return rows.groupBy("source").agg(F.sum("refs").alias("references"), F.sum(new).alias("switches"))


# bytes of packed sets that one scan of the lists takes along at most
SET_BYTES = 1 << 26
RUNS = "source long, step int, at long, refs long, switches long, first long, last long"


def _line_lists(graph: Graph) -> DataFrame:
    """``at, v, nbrs``: lists by decreasing degree in the order of the ids, numbered inside each written file.

    The range shuffle that sorts the lists also gathers them, so arcs are moved twice in all; for graphs
    whose longest list is bounded."""
    if "_line_lists" not in graph.__dict__:
        degree = graph.degrees.select(F.col("v").alias("dst"), (-F.col("deg")).alias("k"))
        arcs = graph.arcs.join(degree, "dst").repartitionByRange("src")
        lists = arcs.groupBy("src").agg(F.array_sort(F.collect_list(F.struct("k", "dst"))).alias("x"))
        lists = lists.select(F.col("src").alias("v"), F.col("x.dst").alias("nbrs")).sortWithinPartitions("v")
        graph.__dict__["_line_lists"] = materialize(lists.withColumn("at", F.monotonically_increasing_id()), f"{graph.name}_line_lists")
    return graph.__dict__["_line_lists"]


def _scan_switches(lists: DataFrame, sets, line_bits: int) -> DataFrame:
    """``RUNS`` rows: references and switches of each search and step in one stretch of neighbouring lists.

    ``sets`` broadcasts ``(source, step, visited, frontier)``.  Lines and their changes depend on the
    list alone and are made once for all searches; a search only tells which lists it reads, and how far."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column("v").to_numpy()
            column = batch.column("nbrs")
            flat, offsets = column.values.to_numpy(zero_copy_only=False), column.offsets.to_numpy().astype(np.int64)
            # a task may read several files, or parts of them
            cuts = np.flatnonzero(np.diff(batch.column("at").to_numpy()) != 1) + 1
            out = []
            for a, b in zip([0, *cuts.tolist()], [*cuts.tolist(), len(ids)], strict=True):
                if a == b:
                    continue
                v, nbrs = ids[a:b], flat[offsets[a] : offsets[b]]
                starts, ends = offsets[a:b] - offsets[a], offsets[a + 1 : b + 1] - offsets[a]
                lines, own = nbrs // line_bits, v // line_bits
                changed = np.ones(len(lines), dtype=np.int64)
                changed[1:] = lines[1:] != lines[:-1]
                changed[starts] = lines[starts] != own
                upto = np.cumsum(changed)
                before = upto[starts] - changed[starts]
                for source, step, visited, frontier in sets.value:
                    stop = ends - 1
                    hit = np.flatnonzero(bw.holds(frontier, nbrs))
                    if len(hit):
                        owner, where = np.unique(np.searchsorted(starts, hit, side="right") - 1, return_index=True)
                        stop[owner] = hit[where]
                    w = np.flatnonzero(~bw.holds(visited, v))
                    if not len(w):
                        continue
                    at, first, last = stop[w], own[w], lines[stop[w]]
                    inner = int((upto[at] - before[w]).sum())
                    out.append((source, step, int(v[0]), int((at - starts[w] + 2).sum()), inner + int((first[1:] != last[:-1]).sum()), int(first[0]), int(last[-1])))
            if out:
                columns = list(zip(*out, strict=True))
                types = (pa.int64(), pa.int32(), *[pa.int64()] * 5)
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types, strict=True)], names=[x.split()[0] for x in RUNS.split(", ")])

    return lists.select("at", "v", "nbrs").mapInArrow(run, RUNS)


def source_switches(graph: Graph, depths: DataFrame, steps: tuple[int, ...], line_bits: int = 64) -> DataFrame:
    """``source, references, switches`` of :func:`switches_by_source` over :func:`probe_traces`, without the trace.

    Depths up to the last of ``steps`` are enough: a vertex that hits has a neighbour in the frontier, and
    all others are read whole.  Stored lists are scanned in the order of the labels with the visited and
    frontier sets as packed words; a scan takes as many searches as fit ``SET_BYTES``.  Only sums and the
    lines at the ends of stretches leave a task.  Labels beyond packed sets, and lists too long for one
    row, go through the trace."""
    total = graph.totals
    n_labels = total["top"] + 1
    if total["least"] < 0 or n_labels > bw.MAX_LABELS or total["max"] > kernels.MAX_LIST:
        return switches_by_source(probe_traces(graph, depths, steps, line_bits))
    near = depths.where(F.col("depth") <= max(steps))
    sources = sorted(r["source"] for r in near.select("source").distinct().collect())  # the sampled sources
    lists = _line_lists(graph)
    at_once = max(1, SET_BYTES // (2 * len(steps) * bw.empty(n_labels).nbytes))
    # the same numbers of buckets and bits as bw.cells, for each search and level
    at = F.col("v") + 1
    found = near.groupBy("source", "depth", F.bitmap_bucket_number(at).alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(at)).alias("bits"))
    parts = None
    for k in range(0, len(sources), at_once):
        chosen = sources[k : k + at_once]
        levels: dict[tuple, list] = {}
        for r in found.where(F.col("source").isin(chosen)).collect():  # SET_BYTES at most
            levels.setdefault((r["source"], r["depth"]), []).append(r)
        sets = []
        for source in chosen:
            for step in steps:
                seen = [r for d in range(step + 1) for r in levels.get((source, d), ())]
                sets.append((source, step, bw.from_cells(seen, n_labels), bw.from_cells(levels.get((source, step), []), n_labels)))
        part = _scan_switches(lists, graph.spark.sparkContext.broadcast(sets), line_bits)
        parts = part if parts is None else parts.union(part)
    if parts is None:
        parts = graph.spark.createDataFrame([], RUNS)
    # a row for each search, step and some thousand vertices
    was = F.lag("last").over(Window.partitionBy("source", "step").orderBy("at"))
    rows = parts.withColumn("was", was).withColumn("new", (F.isnull("was") | (F.col("was") != F.col("first"))).cast("long"))
    return rows.groupBy("source").agg(F.sum("refs").alias("references"), F.sum(F.col("switches") + F.col("new")).alias("switches"))


def range_inspection(graph: Graph, depths: DataFrame, ranges: DataFrame) -> DataFrame:
    """Unvisited vertices, their degree sum and the arcs a bottom-up step looks at, by step and range."""
    deep = depths.agg(F.max("depth").alias("d")).first()["d"] or 0
    hits = first_hits(graph, depths, "deg_desc").select(F.col("src").alias("v"), (F.col("place") + 1).alias("probes"))
    rows = graph.degrees.join(depths.select("v", "depth"), "v", "left").join(hits, "v", "left").select("v", "deg", F.coalesce("depth", F.lit(deep + 2)).alias("depth"), "probes")
    steps = with_range(rows, ranges).where("depth > 0").select("rid", "deg", "depth", "probes", F.explode(F.sequence(F.lit(0), F.least(F.col("depth") - 1, F.lit(deep)))).alias("step"))
    looked_at = F.when(F.col("depth") == F.col("step") + 1, F.coalesce("probes", "deg")).otherwise(F.col("deg"))
    return steps.groupBy("step", "rid").agg(F.count("*").alias("unvisited"), F.sum("deg").alias("degree_sum"), F.sum(looked_at).alias("inspected_edges"))


def teps_edges(graph: Graph, result: DataFrame, source: int) -> DataFrame:
    """Raw and simple edges inside the reached component."""
    r = result.select("v")
    raw = graph.raw_edges.join(r.withColumnRenamed("v", "src"), "src", "left_semi").agg(F.count("*").alias("raw_edges"))
    simple = graph.edges.join(r.withColumnRenamed("v", "u"), "u", "left_semi").agg(F.count("*").alias("simple_edges"))
    return raw.join(F.broadcast(simple), how="cross").select(F.lit(source).cast("long").alias("source"), "raw_edges", "simple_edges")  # two single rows


def footprint(graph: Graph, id_bytes: int = 8) -> DataFrame:
    """Bytes of compressed rows with and without the isolated vertices in the offsets."""
    s = graph.stats()
    dst = F.col("simple_edges") * 2 * id_bytes
    return s.select((F.col("vertices") * id_bytes + id_bytes + dst).alias("all_bytes"), (F.col("non_isolated") * id_bytes + id_bytes + dst).alias("trimmed_bytes"), (F.col("vertices") - F.col("non_isolated")).alias("isolated"))
