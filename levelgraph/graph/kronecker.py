"""Kronecker graphs: every edge picks a quadrant of the adjacency matrix for each bit of its ends."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from levelgraph.graph.build import Graph
from levelgraph.graph.rank import global_rank

PROBABILITIES = (0.57, 0.19, 0.19, 0.05)
EDGEFACTOR = 16
SEED = 7


def draw(seed: int, e: Column, bit: int) -> Column:
    """A number in [0, 1) from the first 8 hex digits of an md5, the same in any engine."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), e.cast("string"), F.lit(str(bit)))), 1, 8), 16, 10).cast("long") / F.lit(float(1 << 32))


def kronecker_from(df: DataFrame, id_column: str, scale: int, probs: tuple[float, ...] = PROBABILITIES, seed: int = SEED) -> DataFrame:
    """Raw edges with the edge index taken from a column."""
    a, b, c, _ = probs
    e = df.select(F.col(id_column).cast("long").alias("e"), *[draw(seed, F.col(id_column), k).alias(f"r{k}") for k in range(scale)])
    src = dst = F.lit(0).cast("long")
    for k in range(scale):
        r = F.col(f"r{k}")
        src = src + F.when(r >= round(a + b, 10), F.lit(1 << k)).otherwise(F.lit(0))
        dst = dst + F.when(((r >= a) & (r < round(a + b, 10))) | (r >= round(a + b + c, 10)), F.lit(1 << k)).otherwise(F.lit(0))
    return e.select("e", src.alias("src"), dst.alias("dst"))


def kronecker(spark: SparkSession, scale: int, edgefactor: int = EDGEFACTOR, probs: tuple[float, ...] = PROBABILITIES, seed: int = SEED, shuffle_labels: bool = False) -> Graph:
    """Graph of 2**scale vertices and edgefactor * 2**scale raw edges."""
    n = 1 << scale
    raw = kronecker_from(spark.range(n * edgefactor).withColumnRenamed("id", "e"), "e", scale, probs, seed)
    vertices = spark.range(n).withColumnRenamed("id", "v")
    if shuffle_labels:
        places = global_rank(vertices.withColumn("h", F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("v").cast("string")))), ["h", "v"], "to").select("v", "to")
        raw = raw.join(places.withColumnRenamed("v", "src"), "src").select(F.col("to").alias("src"), "dst")
        raw = raw.join(places.withColumnRenamed("v", "dst"), "dst").select("src", F.col("to").alias("dst"))
    return Graph(raw.select("src", "dst"), vertices, f"kron{scale}")


def quadrants(spark: SparkSession, scale: int, edgefactor: int = EDGEFACTOR, seed: int = SEED) -> DataFrame:
    """How often each quadrant (0 to 3, row first) is drawn for each bit."""
    a, b, c, _ = PROBABILITIES
    e = spark.range((1 << scale) * edgefactor).withColumnRenamed("id", "e")
    parts = []
    for k in range(scale):
        r = draw(seed, F.col("e"), k)
        parts.append(F.struct(F.lit(k).cast("long").alias("bit"), F.when(r < a, 0).when(r < round(a + b, 10), 1).when(r < round(a + b + c, 10), 2).otherwise(3).cast("long").alias("quadrant")))
    return e.select(F.explode(F.array(*parts)).alias("x")).groupBy("x.bit", "x.quadrant").agg(F.count("*").alias("n"))
