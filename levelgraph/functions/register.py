"""SQL functions over frontiers, ranges and bitmaps."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from levelgraph.balance.ranges import label_ranges
from levelgraph.bfs import kernels
from levelgraph.bitmap import words as bw
from levelgraph.sources.io import _KroneckerReader


class DescendingRanges:
    """Block-aligned label ranges of falling length."""

    def eval(self, n_labels: int, s: int, block: int) -> Iterator[tuple]:
        yield from label_ranges(n_labels, s, block)


class SliceSlots:
    """Edges of the j-th list of a frontier that each of t workers gets."""

    def eval(self, deg: int, j: int, t: int) -> Iterator[tuple]:
        for w in range(t):
            n = deg // t + (deg % t if w == j % t else 0)
            if n:
                yield w, n


class KroneckerEdges:
    """Raw edges of a Kronecker graph, drawn as the generator draws them; for small scales, as one row makes them all."""

    def eval(self, scale: int, edgefactor: int, seed: int) -> Iterator[tuple]:
        reader = _KroneckerReader(scale, edgefactor, seed, 1)
        for stretch in reader.partitions():
            yield from reader.read(stretch)


def in_frontier(frontier: np.ndarray):
    """A vectorised test of labels against a packed set (see :mod:`levelgraph.bitmap.words`), as a column function."""

    def test(v: pd.Series) -> pd.Series:
        return pd.Series(bw.holds(frontier, v.to_numpy()))

    return F.pandas_udf(test, "boolean")


def popcount(lanes: pd.Series) -> pd.Series:
    """Bits that are set in blocks of 64-bit lanes."""
    return lanes.map(lambda x: int(np.bitwise_count(np.asarray(x, dtype=np.int64).view(np.uint64)).sum()))


def bottom_up_block(lists: DataFrame, visited: np.ndarray, frontier: np.ndarray) -> DataFrame:
    """One bottom-up step over lists stored by range (:func:`levelgraph.bfs.kernels.range_lists`): ``v, parent, place, deg``."""
    sc = lists.sparkSession.sparkContext
    return kernels.least_place(kernels.bottom_up(lists, sc.broadcast(visited), sc.broadcast(frontier)))


def imbalance_of(work: pd.Series) -> float:
    """Largest over mean."""
    return float(work.max() / work.mean()) if len(work) and work.mean() else 1.0


def register(spark: SparkSession) -> None:
    spark.udtf.register("descending_ranges", F.udtf(DescendingRanges, returnType="rid int, lo long, hi long"))
    spark.udtf.register("slice_slots", F.udtf(SliceSlots, returnType="slot int, edges long"))
    spark.udtf.register("kronecker_edges", F.udtf(KroneckerEdges, returnType="src long, dst long"))
    spark.udf.register("popcount", F.pandas_udf(popcount, "long"))
    spark.udf.register("imbalance_of", F.pandas_udf(imbalance_of, "double"))
    spark.sql("create or replace temporary function block_of(v bigint) returns bigint return v div 512")
    spark.sql("create or replace temporary function static_slot(j bigint, n bigint, t bigint) returns bigint return j * t div n")
