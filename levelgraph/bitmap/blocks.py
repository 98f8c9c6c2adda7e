"""Vertex sets as 512-bit blocks: built, merged and tested by whole 64-bit words."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BLOCK_BITS = 512
_LANES = BLOCK_BITS // 64


def _lane(v: Column, k: int) -> Column:
    inside = F.expr("v % 512 div 64") == k
    return F.coalesce(F.bit_or(F.when(inside, F.expr("shiftleft(1L, cast(v % 64 as int))"))), F.lit(0).cast("long"))


def pack_blocks(ids: DataFrame) -> DataFrame:
    """``block, bits`` with eight 64-bit lanes a block, from non-negative ids ``v``; partial ORs before the shuffle."""
    return ids.groupBy(F.expr(f"v div {BLOCK_BITS}").alias("block")).agg(*[_lane(F.col("v"), k).alias(f"w{k}") for k in range(_LANES)]).select("block", F.array(*[f"w{k}" for k in range(_LANES)]).alias("bits"))


def _merge(a: DataFrame, b: DataFrame, how: str, op) -> DataFrame:
    none = F.array(*[F.lit(0).cast("long")] * _LANES)
    x, y = a.select("block", F.col("bits").alias("x")), b.select("block", F.col("bits").alias("y"))
    return x.join(y, "block", how).select("block", F.zip_with(F.coalesce("x", none), F.coalesce("y", none), op).alias("bits"))


def or_blocks(a: DataFrame, b: DataFrame) -> DataFrame:
    return _merge(a, b, "full", lambda p, q: p.bitwiseOR(q))


def and_not_blocks(a: DataFrame, b: DataFrame) -> DataFrame:
    """Bits of ``a`` that ``b`` lacks: the unvisited ones, given all and visited."""
    return _merge(a, b, "left", lambda p, q: p.bitwiseAND(F.bitwise_not(q)))


def count_bits(blocks: DataFrame) -> DataFrame:
    return blocks.select("block", F.aggregate("bits", F.lit(0).cast("long"), lambda t, w: t + F.bit_count(w)).alias("bits")).where("bits > 0")


def to_rows(blocks: DataFrame) -> DataFrame:
    """Ids of the set bits."""
    lanes = blocks.select("block", F.posexplode("bits").alias("lane", "word")).where("word <> 0")
    bits = lanes.select((F.col("block") * BLOCK_BITS + F.col("lane") * 64).alias("base"), "word", F.explode(F.sequence(F.lit(0), F.lit(63))).alias("k"))
    return bits.where(F.expr("getbit(word, k) = 1")).select((F.col("base") + F.col("k")).alias("v"))


def in_blocks(rows: DataFrame, blocks: DataFrame, column: str = "v") -> DataFrame:
    """Rows whose id is set: a join on the block and a test of one bit."""
    return rows.withColumn("block", F.expr(f"{column} div {BLOCK_BITS}")).join(blocks, "block").where(F.expr(f"getbit(bits[cast({column} % {BLOCK_BITS} div 64 as int)], cast({column} % 64 as int)) = 1")).drop("block", "bits")
