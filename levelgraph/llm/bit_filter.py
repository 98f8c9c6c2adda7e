"""A bit filter of bounded size over ids: names the rows that may be meant, so only those have to move."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from levelgraph.runtime import discard, materialize

# bits at most (32 MB); more ids only let more rows pass
MAX_BITS = 1 << 28


class BitFilter:
    """Built by one aggregation; each executor gets a copy.  Never misses an id that it was built from."""

    def __init__(self, ids: DataFrame, column: str, max_bits: int = MAX_BITS):
        ids = materialize(ids.select(F.col(column).cast("long").alias("id")).where("id is not null"), "filter_ids")
        self.bits = min(max_bits, 1 << max(20, (16 * ids.count()).bit_length()))
        cells = ids.select(self.slot("id").alias("s")).groupBy(F.bitmap_bucket_number("s").alias("b")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("s")).alias("m"))
        held = np.zeros(self.bits // 8, dtype=np.uint8)
        for row in cells.toLocalIterator():  # at most bits / 32768 rows of 4 KB
            part = np.frombuffer(row["m"], dtype=np.uint8)
            lo = (row["b"] - 1) * len(part)
            held[lo : lo + len(part)] |= part
        self.shared = ids.sparkSession.sparkContext.broadcast(held)
        discard(ids)

    def slot(self, column: str) -> Column:
        return F.pmod(F.xxhash64(F.col(column).cast("long")), F.lit(self.bits)) + 1

    def holds(self, slots: np.ndarray) -> np.ndarray:
        """Which of the slots (worked out by :meth:`slot`) are set."""
        at = slots.astype(np.int64) - 1
        return (self.shared.value[at >> 3] >> (at & 7).astype(np.uint8) & 1).astype(bool)


def exclude(docs: DataFrame, ids: DataFrame, column: str) -> DataFrame:
    """Rows of ``docs`` whose ``column`` is not among ``ids``, all columns kept; null ids stay.

    Rows that the filter lets go by need no join; the others, few more than those named, are
    joined exactly.  Columns may have any names.  An empty table on either side is no special case."""
    ids = materialize(ids.select(F.col(column).cast("long").alias("_gone")), "excluded")
    named = BitFilter(ids, "_gone")
    names = docs.columns
    rows = docs.toDF(*[f"c{k}" for k in range(len(names))])
    key = f"c{names.index(column)}"

    def side(want: bool) -> DataFrame:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                hit = named.holds(batch.column(batch.num_columns - 1).to_numpy())
                yield batch.select(list(range(batch.num_columns - 1))).filter(pa.array(hit == want))

        return rows.select("*", named.slot(key).alias("slot")).mapInArrow(run, rows.schema)

    free, named_rows = side(False), side(True)
    kept = named_rows.join(ids, named_rows[key].cast("long") == ids["_gone"], "left_anti")
    return free.union(kept.select(*rows.columns)).toDF(*names)
