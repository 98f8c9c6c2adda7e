"""Undirected graphs as DataFrames: cleaning, degrees, adjacency, compressed rows, relabelling."""

from __future__ import annotations

from functools import cached_property

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from levelgraph.bitmap import words as bw
from levelgraph.graph.rank import global_rank
from levelgraph.runtime import materialize

RAW = ("src", "dst")
# arcs of a list that one task numbers at most
HUB_LIST = 1 << 20


def require_columns(df: DataFrame, *names: str) -> DataFrame:
    missing = [n for n in names if n not in df.columns]
    if missing:
        raise ValueError(f"columns {missing} are missing; there are {df.columns}")
    return df


def edges_from(df: DataFrame, src: Column | str, dst: Column | str) -> DataFrame:
    """Raw edges of any table: one row per input row, loops and repeats kept."""
    src, dst = (F.expr(x) if isinstance(x, str) else x for x in (src, dst))
    return df.select(src.cast("long").alias("src"), dst.cast("long").alias("dst"))


def drop_loops(raw: DataFrame) -> DataFrame:
    return raw.where("src <> dst")


def simple_edges(raw: DataFrame) -> DataFrame:
    """One row ``u < v`` per unordered pair, without loops."""
    return drop_loops(raw).select(F.least("src", "dst").alias("u"), F.greatest("src", "dst").alias("v")).distinct()


def to_arcs(edges: DataFrame) -> DataFrame:
    """Both directions of each edge from one scan."""
    both = F.explode(F.array(F.struct(F.col("u").alias("src"), F.col("v").alias("dst")), F.struct(F.col("v").alias("src"), F.col("u").alias("dst"))))
    return edges.select(both.alias("arc")).select("arc.src", "arc.dst")


class Graph:
    """A graph given by raw edges and all its vertices; derived tables are written once and reused."""

    def __init__(self, raw: DataFrame, vertices: DataFrame, name: str = "graph"):
        self.raw, self.vertices, self.name = require_columns(raw, *RAW), require_columns(vertices, "v"), name
        self.spark = raw.sparkSession

    @cached_property
    def raw_edges(self) -> DataFrame:
        return materialize(self.raw.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst")), f"{self.name}_raw")

    @cached_property
    def edges(self) -> DataFrame:
        return materialize(simple_edges(self.raw_edges), f"{self.name}_edges")

    @cached_property
    def arcs(self) -> DataFrame:
        return materialize(to_arcs(self.edges), f"{self.name}_arcs")

    @cached_property
    def degrees(self) -> DataFrame:
        """Simple degree of every vertex that has an arc."""
        return materialize(self.arcs.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("deg")), f"{self.name}_degrees")

    @cached_property
    def ranked_arcs(self) -> DataFrame:
        """Arcs with the degrees of both ends and the place of ``dst`` in the list of ``src`` by
        decreasing degree (ties by id); place 0 is the top neighbour."""
        d = self.degrees
        both = self.arcs.join(d.select(F.col("v").alias("dst"), F.col("deg").alias("dst_deg")), "dst").join(d.select(F.col("v").alias("src"), "deg"), "src")
        placed = with_places(both, [F.desc("dst_deg"), "dst"], self.totals["max"])
        return materialize(placed.select("src", "dst", "deg", "dst_deg", "place"), f"{self.name}_lists")

    @cached_property
    def totals(self) -> dict:
        """``n`` vertices with an arc, ``m`` arcs, greatest degree ``max``, ``least`` and ``top`` id."""
        d = self.degrees
        zero = lambda c: F.coalesce(c, F.lit(0))
        return d.agg(F.count("*").alias("n"), zero(F.sum("deg")).alias("m"), zero(F.max("deg")).alias("max"), zero(F.min("v")).alias("least"), zero(F.max("v")).alias("top")).first().asDict()

    def degree_of(self, v: int) -> int:
        row = self.degrees.where(F.col("v") == v).select("deg").first()
        return row["deg"] if row else 0

    def packed(self, n_labels: int):
        """The vertices that have an arc as packed words (checked by the caller to be few enough)."""
        if "_packed" not in self.__dict__:
            self.__dict__["_packed"] = bw.cells(self.degrees.select("v")).collect()  # at most labels / 32768 rows of 4 KB
        return bw.from_cells(self.__dict__["_packed"], n_labels)

    def raw_degrees(self) -> DataFrame:
        """``v, deg, raw_deg`` of every vertex that has an arc: distinct neighbours, and ends of raw edges (a loop has two)."""
        ends = self.raw_edges.select(F.explode(F.array("src", "dst")).alias("v")).groupBy("v").agg(F.count("*").alias("raw_deg"))
        return self.degrees.join(ends, "v").select("v", "deg", "raw_deg")

    def isolated(self) -> DataFrame:
        return self.vertices.select("v").join(self.degrees.select("v"), "v", "left_anti")

    def stats(self) -> DataFrame:
        n = self.vertices.agg(F.count("*").alias("vertices"))
        raw = self.raw_edges.agg(F.count("*").alias("raw_edges"), F.sum((F.col("src") == F.col("dst")).cast("long")).alias("loops"))
        deg = self.degrees.agg(F.count("*").alias("non_isolated"), F.expr("sum(deg) div 2").alias("simple_edges"), F.max("deg").alias("max_degree"))
        out = n.join(F.broadcast(raw), how="cross").join(F.broadcast(deg), how="cross")  # three single rows
        return out.select("vertices", "non_isolated", "raw_edges", F.coalesce("loops", F.lit(0)).alias("loops"), F.coalesce("simple_edges", F.lit(0)).alias("simple_edges"), F.coalesce("max_degree", F.lit(0)).alias("max_degree"))


def with_places(rows: DataFrame, order: list, most: int) -> DataFrame:
    """Adds ``place``: position in the list of ``src`` under ``order``; rows hold ``src`` and ``deg``, ``most`` is the longest list.

    Lists up to ``HUB_LIST`` are numbered in one task each; those of hubs through one range sort of
    all their arcs, so no list is too long for a task."""
    numbered = rows.where(F.col("deg") <= HUB_LIST) if most > HUB_LIST else rows
    numbered = numbered.withColumn("place", (F.row_number().over(Window.partitionBy("src").orderBy(*order)) - 1).cast("long"))
    if most <= HUB_LIST:
        return numbered
    ranked = global_rank(rows.where(F.col("deg") > HUB_LIST), ["src", *order], "_rank")
    first = F.broadcast(ranked.groupBy("src").agg(F.min("_rank").alias("_first")))  # a row a hub: all arcs / HUB_LIST at most
    hubs = ranked.join(first, "src").withColumn("place", F.col("_rank") - F.col("_first"))
    return numbered.unionByName(hubs.select(*numbered.columns))


def degree_histogram(graph: Graph) -> DataFrame:
    zero = graph.isolated().agg(F.count("*").alias("n")).select(F.lit(0).cast("long").alias("deg"), "n").where("n > 0")
    return graph.degrees.groupBy("deg").agg(F.count("*").alias("n")).union(zero)


def edge_share(graph: Graph, buckets: int = 100) -> DataFrame:
    """Share of all arcs that end in the first k of ``buckets`` equal parts of the vertices by degree."""
    ranked = global_rank(graph.degrees, [F.desc("deg"), "v"])
    n = graph.degrees.count()
    part = F.floor(F.col("rank") * buckets / max(n, 1)).cast("int")
    per = ranked.groupBy(part.alias("bucket")).agg(F.sum("deg").alias("arcs"))  # at most `buckets` rows
    run = Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, 0)
    return per.select("bucket", (F.sum("arcs").over(run) / F.sum("arcs").over(Window.partitionBy())).alias("share"))


def drop_isolated(graph: Graph) -> DataFrame:
    """Dense labels over the non-isolated vertices in their natural order."""
    return global_rank(graph.degrees.select("v"), ["v"], "label").select("label", "v")


def to_csr(graph: Graph) -> tuple[DataFrame, DataFrame]:
    """Compressed rows: ``offsets(v, row_start, row_end)`` over all vertices and ``dst(pos, w)``."""
    dst = global_rank(graph.arcs, ["src", "dst"], "pos")
    filled = dst.groupBy(F.col("src").alias("v")).agg(F.min("pos").alias("row_start"), (F.max("pos") + 1).alias("row_end"))
    # a vertex without arcs starts and ends where the vertices before it end
    lone = graph.isolated().select("v")
    marks = filled.select("v", F.col("row_end").alias("e")).union(lone.select("v", F.lit(None).cast("long")))
    ranked = global_rank(marks, ["v"], "at")
    width = 4096
    block = ranked.groupBy(F.expr(f"at div {width}").alias("b")).agg(F.max("e").alias("m"))
    upto = Window.orderBy("b").rowsBetween(Window.unboundedPreceding, -1)  # a row for each 4096 vertices
    before = block.select("b", F.max("m").over(upto).alias("before"))
    inside = Window.partitionBy("b").orderBy("at").rowsBetween(Window.unboundedPreceding, 0)
    filled_up = ranked.withColumn("b", F.expr(f"at div {width}")).join(before, "b").withColumn("end", F.coalesce(F.greatest(F.max("e").over(inside), "before"), F.lit(0)))
    starts = filled.select("v", "row_start")
    offsets = filled_up.join(starts, "v", "left").select("v", F.coalesce("row_start", "end").alias("row_start"), F.col("end").alias("row_end"))
    return offsets, dst.select("pos", F.col("dst").alias("w"))


def neighbors(csr: tuple[DataFrame, DataFrame], v: int) -> DataFrame:
    """Neighbours of one vertex: its slice becomes a literal range on the sorted positions."""
    offsets, dst = csr
    row = offsets.where(F.col("v") == v).first()
    lo, hi = (row["row_start"], row["row_end"]) if row else (0, 0)
    return dst.where((F.col("pos") >= lo) & (F.col("pos") < hi)).select(F.lit(v).cast("long").alias("v"), "w")


def adjacency(graph: Graph, order: str = "deg_desc", max_list: int = 65536) -> DataFrame:
    """Neighbour lists ``v, chunk, deg, nbrs`` by ``id``, ``deg_asc`` or ``deg_desc``; long lists are cut
    into numbered chunks, so a hub is several rows of bounded size."""
    keys = {"id": ["dst"], "deg_asc": ["dst_deg", "dst"], "deg_desc": [F.desc("dst_deg"), "dst"]}[order]
    placed = with_places(graph.ranked_arcs.drop("place"), keys, graph.totals["max"]).withColumnRenamed("place", "at")
    lists = placed.groupBy(F.col("src").alias("v"), F.expr(f"at div {max_list}").alias("chunk")).agg(F.first("deg").alias("deg"), F.array_sort(F.collect_list(F.struct("at", "dst"))).alias("x"))
    return lists.select("v", "chunk", "deg", F.col("x.dst").alias("nbrs"))


def split_top(lists: DataFrame) -> DataFrame:
    """Separates the first neighbour of each list from the rest."""
    first = F.when(F.col("chunk") == 0, F.get("nbrs", F.lit(0)))
    rest = F.when(F.col("chunk") == 0, F.slice("nbrs", F.lit(2), F.size("nbrs"))).otherwise(F.col("nbrs"))
    return lists.select("v", "chunk", "deg", first.alias("top_nbr"), rest.alias("rest"))


def relabel(edges: DataFrame, perm: DataFrame, a: str = "u", b: str = "v") -> DataFrame:
    """Edges with both ends replaced by their labels; the topology does not change."""
    p = perm.select("label", F.col("v").alias("_v"))
    out = edges.join(p, F.col(a) == F.col("_v")).select(*edges.columns, F.col("label").alias("_a"))
    out = out.join(p, F.col(b) == F.col("_v")).select("_a", F.col("label").alias("_b"))
    return out.select(F.col("_a").alias(a), F.col("_b").alias(b))
