"""Connected components by alternating star contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelgraph.runtime import discard, materialize


def _fingerprint(e: DataFrame) -> tuple:
    row = e.agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("u", "v")).alias("x")).first()
    return row["n"], row["x"]


def star_contraction(edges: DataFrame, a: str = "u", b: str = "v") -> DataFrame:
    """Components of an undirected edge table.

    Returns ``(v, comp)`` for every vertex that has a proper edge and is not the least of its
    component; ``comp`` is the least reachable id.  Loops and repeated edges are harmless.
    Each round halves distances in every component, so few rounds are needed even for paths;
    minima are taken by pre-aggregated groupings and hubs are left to skew-aware joins.
    """
    e = (
        edges.where(F.col(a) != F.col(b))
        .select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v"))
        .distinct()
    )
    e = materialize(e, "stars")
    state = _fingerprint(e)
    while state[0]:
        both = e.select(F.col("u").alias("x"), F.col("v").alias("y")).union(e.select("v", "u"))
        least = both.groupBy("x").agg(F.min("y").alias("m")).select("x", F.least("x", "m").alias("m"))
        large = (
            both.where("y > x").join(least, "x")
            .select(F.col("y").alias("u"), F.col("m").alias("v")).distinct()
        )
        root = large.groupBy("u").agg(F.min("v").alias("m"))
        small = (
            large.join(root, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
            .union(root.select("u", F.col("m").alias("v"))).distinct()
        )
        small = materialize(small, "stars")
        new_state = _fingerprint(small)
        discard(e)
        e = small
        if new_state == state:
            break
        state = new_state
    return e.select(F.col("u").alias("v"), F.col("v").alias("comp"))
