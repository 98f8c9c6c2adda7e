"""Reading and writing graphs: edge lists in common text formats, Parquet layouts, a generator source."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import StructType

from levelgraph.balance.ranges import label_ranges
from levelgraph.graph.build import Graph

EDGES = "src long, dst long"


def read_edge_list(spark: SparkSession, path: str, kind: str = "text") -> DataFrame:
    """Raw edges from white-space separated text with # or % comments, or from csv, json, orc or parquet."""
    if kind == "text":
        lines = spark.read.text(path).where(~F.col("value").rlike(r"^\s*([#%]|$)"))
        parts = F.split(F.trim("value"), r"[\s,]+")
        return lines.select(parts[0].cast("long").alias("src"), parts[1].cast("long").alias("dst"))
    return spark.read.schema(EDGES).format(kind).load(path)


def write_graph(graph: Graph, path: str, ranges: int = 16) -> None:
    """Arcs by range of ``src``, sorted inside, so filters on ``src`` skip files and row groups; vertices beside them."""
    top = graph.vertices.agg(F.coalesce(F.max("v"), F.lit(0)).alias("m")).first()["m"]
    cuts = [hi for _, _, hi in label_ranges(top + 1, ranges)]
    rid = F.lit(0)
    for k, hi in enumerate(cuts[:-1]):
        rid = F.when(F.col("src") >= hi, k + 1).otherwise(rid) if k == 0 else F.when(F.col("src") >= hi, F.lit(k + 1)).otherwise(rid)
    arcs = graph.arcs.withColumn("rid", rid).repartition("rid").sortWithinPartitions("rid", "src", "dst")
    arcs.write.mode("overwrite").partitionBy("rid").parquet(f"{path}/arcs")
    graph.raw_edges.write.mode("overwrite").parquet(f"{path}/raw")
    graph.vertices.select("v").write.mode("overwrite").parquet(f"{path}/vertices")


def read_graph(spark: SparkSession, path: str, name: str = "stored") -> Graph:
    graph = Graph(spark.read.schema(EDGES).parquet(f"{path}/raw"), spark.read.schema("v long").parquet(f"{path}/vertices"), name)
    graph.__dict__["arcs"] = spark.read.parquet(f"{path}/arcs").select("src", "dst")
    return graph


def write_table(df: DataFrame, path: str, kind: str = "parquet") -> None:
    """A report or an edge list as parquet, orc, json or csv (with a header)."""
    if kind not in ("parquet", "orc", "json", "csv"):
        raise ValueError(f"unknown format {kind!r}")
    writer = df.write.mode("overwrite").format(kind)
    (writer.option("header", True) if kind == "csv" else writer).save(path)


def save_bucketed(graph: Graph, table: str, buckets: int = 64) -> None:
    """Arcs as a catalogue table bucketed and sorted by ``src``: joins on ``src`` with equal buckets need no shuffle."""
    graph.arcs.write.mode("overwrite").bucketBy(buckets, "src").sortBy("src", "dst").saveAsTable(table)


def register_views(graph: Graph, prefix: str = "") -> None:
    for name in ("vertices", "edges", "arcs", "degrees"):
        getattr(graph, name).createOrReplaceTempView(f"{prefix}{name}")


class _Stretch(InputPartition):
    def __init__(self, lo: int, hi: int):
        super().__init__((lo, hi))


class _KroneckerReader(DataSourceReader):
    def __init__(self, scale: int, edgefactor: int, seed: int, parts: int):
        self.scale, self.total, self.seed, self.parts = scale, edgefactor << scale, seed, parts

    def partitions(self) -> list[InputPartition]:
        cuts = [self.total * k // self.parts for k in range(self.parts + 1)]
        return [_Stretch(a, b) for a, b in zip(cuts, cuts[1:], strict=False)]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        lo, hi = partition.value
        for e in range(lo, hi):
            src = dst = 0
            for k in range(self.scale):
                r = int(hashlib.md5(f"{self.seed}:{e}:{k}".encode()).hexdigest()[:8], 16) / 4294967296.0
                src |= (r >= 0.76) << k
                dst |= (0.57 <= r < 0.76 or r >= 0.95) << k
            yield src, dst


class KroneckerSource(DataSource):
    """``spark.read.format("kronecker")`` with options scale, edgefactor, seed and parts."""

    @classmethod
    def name(cls) -> str:
        return "kronecker"

    def schema(self) -> str:
        return EDGES

    def reader(self, schema: StructType) -> DataSourceReader:
        o = self.options
        return _KroneckerReader(int(o.get("scale", 10)), int(o.get("edgefactor", 16)), int(o.get("seed", 7)), int(o.get("parts", 8)))
