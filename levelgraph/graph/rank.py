"""Dense positions under a total order without a single-task window."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from levelgraph.runtime import materialize


def global_rank(df: DataFrame, order: list[Column | str], name: str = "rank", tag: str = "ranked") -> DataFrame:
    """Adds ``name``: 0-based dense position of each row under ``order`` (which should be total).

    Rows are range-partitioned and sorted; each partition numbers its rows, and the sizes of the
    partitions before it (one small row each) shift them.  The sorted rows are written before the
    sizes are counted, so a second sampling of the ranges can not disturb the numbering.  The result
    reads the written rows, and :func:`ranked_rows` tells their number.
    """
    part = df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_at", F.monotonically_increasing_id())
    part = materialize(part, tag)
    sizes = part.groupBy(F.shiftright("_at", 33).alias("p")).agg(F.count("*").alias("n")).orderBy("p").collect()
    offsets, total = [], 0
    for row in sizes:
        offsets.append((row["p"], total))
        total += row["n"]
    shift = F.lit(0).cast("long")
    if len(offsets) > 1:
        table = df.sparkSession.createDataFrame(offsets, "p long, off long")
        part = part.withColumn("p", F.shiftright("_at", 33)).join(F.broadcast(table), "p").drop("p")
        shift = F.col("off")
    low = F.col("_at").bitwiseAND(F.lit((1 << 33) - 1))
    out = part.withColumn(name, shift + low).drop("_at", "off")
    out._levelgraph_rows = total
    return out


def ranked_rows(ranked: DataFrame) -> int:
    """Rows of a result of :func:`global_rank`, known from its numbering."""
    return ranked._levelgraph_rows
