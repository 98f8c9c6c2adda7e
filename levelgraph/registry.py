"""Where queries are registered, and what several of them share of one graph."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from levelgraph.bfs import hybrid
from levelgraph.graph import build
from levelgraph.graph.workloads import load
from levelgraph.reorder import level_order as lo
from levelgraph.reorder import locality as loc
from levelgraph.runtime import materialize

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


class Prepared:
    """What several queries need of one graph, made once per session and input."""

    _held: dict[tuple, Prepared] = {}

    def __init__(self, spark: SparkSession, sf: str, name: str):
        self.graph = load(spark, sf, name)
        self.spark, self.name = spark, name
        self._made: dict[str, object] = {}

    @classmethod
    def of(cls, spark: SparkSession, sf: str, name: str) -> Prepared:
        key = (spark.sparkContext.applicationId, sf, name)
        if key not in cls._held:
            cls._held[key] = cls(spark, sf, name)
        return cls._held[key]

    def make(self, key: str, build: Callable[[], object]):
        if key not in self._made:
            self._made[key] = build()
        return self._made[key]

    @property
    def source(self) -> int:
        return self.make("source", lambda: hybrid.sample_sources(self.graph, 1).first()["v"])

    @property
    def run(self) -> hybrid.BfsRun:
        return self.make("run", lambda: hybrid.bfs(self.graph, self.source))

    @property
    def depths(self) -> DataFrame:
        return self.make("depths", lambda: materialize(self.run.result.select("v", F.col("depth").cast("long").alias("depth")), "depths"))

    def perm(self, kind: str) -> DataFrame:
        made = {"rlo": lambda: lo.reverse_level_order(self.graph), "natural": lambda: lo.natural_order(self.graph), "degree": lambda: lo.degree_order(self.graph)}
        return self.make(f"perm_{kind}", lambda: materialize(made[kind]().select("label", "v", "comp"), f"perm_{kind}"))

    def labelled(self, kind: str) -> DataFrame:
        return self.make(f"edges_{kind}", lambda: materialize(loc.labelled_edges(self.graph, self.perm(kind)), f"edges_{kind}"))

    @property
    def tidy(self) -> build.Graph:
        """The graph under its reversed level order, without isolated vertices."""
        def built() -> build.Graph:
            edges, perm = self.labelled("rlo"), self.perm("rlo").where("comp is not null")
            return build.Graph(edges.select(F.col("u").alias("src"), F.col("v").alias("dst")), perm.select(F.col("label").alias("v")), f"{self.name}_tidy")

        return self.make("tidy", built)

    def many(self, k: int) -> DataFrame:
        """Depths from the first ``k`` sampled sources."""
        sources = lambda: [r["v"] for r in hybrid.sample_sources(self.graph, k).collect()]
        return self.make(f"many_{k}", lambda: materialize(hybrid.bfs_many(self.graph, sources()).select("source", "v", F.col("depth").cast("long").alias("depth")), "many"))

    def near(self, k: int, levels: int) -> DataFrame:
        """What ``many`` has of the first ``levels`` levels, for what no deeper one changes."""
        if f"many_{k}" in self._made:
            return self.many(k).where(F.col("depth") <= levels)
        sources = lambda: [r["v"] for r in hybrid.sample_sources(self.graph, k).collect()]
        return self.make(f"near_{k}_{levels}", lambda: materialize(hybrid.bfs_many(self.graph, sources(), levels).select("source", "v", F.col("depth").cast("long").alias("depth")), "near"))

    def label_depths(self, kind: str) -> DataFrame:
        """Depths with labels in place of ids."""
        return self.make(f"depths_{kind}", lambda: materialize(self.depths.join(self.perm(kind), "v").select(F.col("label").alias("v"), "depth"), f"depths_{kind}"))


def longs(df: DataFrame) -> DataFrame:
    return df.select(*[F.col(c).cast("long").alias(c) if t in ("int", "smallint", "tinyint", "bigint") or t.startswith("decimal") else F.col(c) for c, t in df.dtypes])


def add(name: str, query: Callable[[Prepared], DataFrame], sql: str | None, graph: str) -> None:
    QUERIES[name] = lambda spark, sf: longs(query(Prepared.of(spark, sf, graph)))
    if sql:
        ORACLES[name] = sql


def plain(name: str, query: Callable[[SparkSession, str], DataFrame], sql: str | None) -> None:
    QUERIES[name] = lambda spark, sf: longs(query(spark, sf))
    if sql:
        ORACLES[name] = sql
