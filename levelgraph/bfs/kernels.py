"""Steps of a search over packed sets: one scan of the lists, no shuffle bottom-up.

Lists are stored by range of labels, one file a range, neighbours by decreasing degree.  A step is
one ``mapInArrow`` over the files of the ranges that are still live; visited and frontier sets come
along as packed words.  A task owns the lines of its ranges, so nothing is locked, and visited bits
are merged once after the step, whole words at a time.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelgraph.balance.ranges import label_ranges
from levelgraph.bitmap import words as bw
from levelgraph.graph.build import Graph
from levelgraph.runtime import materialize

# neighbours in one row of a list at most; longer lists are several rows
MAX_LIST = 1 << 16
# places of a list that are looked at together: most lists are left after the first
CHUNKS = (1, 8, 64, 1024)
# a step whose lists hold more bytes than this reads top neighbours in a scan of their own first
SPLIT_BYTES = 1 << 30
FOUND = "v long, parent long, place long, deg long"
REACHED = "v long, parent long, parent_deg long, deg long"


def range_lists(graph: Graph, n_labels: int, s: int, block: int, kind: str, max_list: int = MAX_LIST) -> tuple[DataFrame, list[tuple[int, int, int]]]:
    """``rid, v, chunk, deg, top, nbrs, degs`` sorted by ``v`` in a file for each range, and the ranges."""
    cuts = label_ranges(n_labels, s, block, kind)
    held = graph.__dict__.setdefault("_range_lists", {})
    key = (n_labels, s, block, kind, max_list)
    if key not in held:
        table = F.broadcast(graph.spark.createDataFrame(cuts, "rid int, lo long, hi long"))  # lambda * workers rows
        # the range is part of the grouping, so each list is put together where it is written
        arcs = graph.ranked_arcs.withColumn("chunk", F.expr(f"cast(place div {max_list} as int)"))
        lists = arcs.groupBy(F.col("src").alias("v"), "chunk").agg(F.first("deg").alias("deg"), F.array_sort(F.collect_list(F.struct("place", "dst", "dst_deg"))).alias("x"))
        lists = lists.join(table, (F.col("v") >= F.col("lo")) & (F.col("v") < F.col("hi")))
        lists = lists.select("rid", "v", "chunk", "deg", F.col("x")[0]["dst"].alias("top"), F.col("x.dst").alias("nbrs"), F.col("x.dst_deg").alias("degs"))
        dealt = lists.repartitionById(len(cuts), F.col("rid")).sortWithinPartitions("v", "chunk") if cuts else lists
        held[key] = materialize(dealt, f"{graph.name}_ranges")
    return held[key], cuts


def _bit_rows(words: np.ndarray, labels: np.ndarray) -> np.ndarray:
    return bw.holds(words, labels) if len(labels) else np.zeros(0, dtype=bool)


def first_hits(frontier: np.ndarray, flat: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Place of the first member of ``frontier`` in each list, -1 where there is none.

    Places are looked at in chunks of growing size, and lists that have hit take no further part."""
    out = np.full(len(starts), -1, dtype=np.int64)
    waiting, at = np.arange(len(starts)), 0
    for width in (*CHUNKS, None):
        waiting = waiting[(ends - starts)[waiting] > at]
        if not len(waiting):
            break
        lo = starts[waiting] + at
        hi = ends[waiting] if width is None else np.minimum(lo + width, ends[waiting])
        n = hi - lo
        begin = np.cumsum(n) - n
        index = np.arange(int(n.sum())) - np.repeat(begin, n) + np.repeat(lo, n)
        hit = np.flatnonzero(_bit_rows(frontier, flat[index]))
        owner = np.searchsorted(begin, hit, side="right") - 1
        first, where = np.unique(owner, return_index=True)
        out[waiting[first]] = index[hit[where]] - starts[waiting[first]]
        keep = np.ones(len(waiting), dtype=bool)
        keep[first] = False
        waiting, at = waiting[keep], at + (width or 0)
    return out


def _lists(column: pa.Array, dtype=np.int64) -> tuple[np.ndarray, np.ndarray]:
    return column.values.to_numpy(zero_copy_only=False).astype(dtype, copy=False), column.offsets.to_numpy(zero_copy_only=False).astype(np.int64)


def bottom_up(lists: DataFrame, visited, frontier, max_list: int = MAX_LIST) -> DataFrame:
    """Unvisited vertices with a neighbour in the frontier: ``FOUND`` rows, one for each list row that hits.

    The parent is the first hit of a list by decreasing degree, so the neighbour of highest degree."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen, now = visited.value, frontier.value
        for batch in batches:
            v = batch.column("v").to_numpy()
            waiting = np.flatnonzero(~_bit_rows(seen, v))
            flat, offsets = _lists(batch.column("nbrs"))
            place = first_hits(now, flat, offsets[waiting], offsets[waiting + 1])
            hit, place = waiting[place >= 0], place[place >= 0]
            chunk = batch.column("chunk").to_numpy()[hit].astype(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(v[hit]), pa.array(flat[offsets[hit] + place]), pa.array(place + chunk * max_list), pa.array(batch.column("deg").to_numpy()[hit])], names=["v", "parent", "place", "deg"])

    return lists.select("v", "chunk", "deg", "nbrs").mapInArrow(run, FOUND)


def top_pass(lists: DataFrame, visited, frontier) -> DataFrame:
    """The first pass alone: unvisited vertices whose top neighbour is in the frontier; reads no lists."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen, now = visited.value, frontier.value
        for batch in batches:
            v, top = batch.column("v").to_numpy(), batch.column("top").to_numpy()
            hit = ~_bit_rows(seen, v) & _bit_rows(now, top)
            yield pa.RecordBatch.from_arrays([pa.array(v[hit]), pa.array(top[hit]), pa.array(np.zeros(int(hit.sum()), np.int64)), pa.array(batch.column("deg").to_numpy()[hit])], names=["v", "parent", "place", "deg"])

    return lists.where("chunk = 0").select("v", "top", "deg").mapInArrow(run, FOUND)


def least_place(found: DataFrame) -> DataFrame:
    """One row a vertex where lists of several rows may hit more than once."""
    return found.groupBy("v").agg(F.min(F.struct("place", "parent", "deg")).alias("x")).select("v", "x.parent", "x.place", "x.deg")


def top_down(lists: DataFrame, visited, frontier) -> DataFrame:
    """Unvisited neighbours of the frontier with their best parent; only those are shuffled, one a task and vertex at most."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen, now = visited.value, frontier.value
        for batch in batches:
            rows = np.flatnonzero(_bit_rows(now, batch.column("v").to_numpy()))
            flat, offsets = _lists(batch.column("nbrs"))
            degs, _ = _lists(batch.column("degs"))
            n = offsets[rows + 1] - offsets[rows]
            index = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n) + np.repeat(offsets[rows], n)
            flat, degs, owner = flat[index], degs[index], np.repeat(rows, n)
            new = ~_bit_rows(seen, flat)
            flat, degs, owner = flat[new], degs[new], owner[new]
            src, src_deg = batch.column("v").to_numpy()[owner], batch.column("deg").to_numpy()[owner]
            order = np.lexsort((src, -src_deg, flat))
            flat, degs, src, src_deg = flat[order], degs[order], src[order], src_deg[order]
            first = np.ones(len(flat), dtype=bool)
            first[1:] = flat[1:] != flat[:-1]
            yield pa.RecordBatch.from_arrays([pa.array(x[first]) for x in (flat, src, src_deg, degs)], names=["v", "parent", "parent_deg", "deg"])

    reached = lists.select("v", "deg", "nbrs", "degs").mapInArrow(run, REACHED)
    best = reached.groupBy("v").agg(F.max(F.struct("parent_deg", (-F.col("parent")).alias("k"))).alias("p"), F.first("deg").alias("deg"))
    return best.select("v", (-F.col("p.k")).alias("parent"), F.lit(None).cast("long").alias("place"), "deg")
