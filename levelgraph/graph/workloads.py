"""Graphs built from the given tables; ids of several tables share one integer space by residue."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from levelgraph.graph.build import Graph, edges_from
from levelgraph.graph.kronecker import kronecker, kronecker_from
from levelgraph.graph.rank import global_rank
from levelgraph.runtime import materialize

# words of an item that find the texts that may hold it
SEED_WORDS = 4


def _table(spark: SparkSession, sf: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf}/{name}.parquet")


def _ids(*frames_and_expr: tuple[DataFrame, str]) -> DataFrame:
    out = None
    for df, expr in frames_and_expr:
        part = df.select(F.expr(expr).cast("long").alias("v"))
        out = part if out is None else out.union(part)
    return out


def purchase(spark: SparkSession, sf: str, where: str = "true", name: str = "purchase") -> Graph:
    lines = _table(spark, sf, "lineitem").where(where).select("l_orderkey", "l_partkey")
    joined = lines.join(_table(spark, sf, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    return Graph(edges_from(joined, "2 * o_custkey", "2 * l_partkey + 1"), _ids((_table(spark, sf, "customer"), "2 * c_custkey"), (_table(spark, sf, "part"), "2 * p_partkey + 1")), name)


def returned_purchase(spark: SparkSession, sf: str) -> Graph:
    return purchase(spark, sf, "l_returnflag = 'R'", "returned_purchase")


def supply(spark: SparkSession, sf: str) -> Graph:
    lines = _table(spark, sf, "lineitem").select("l_suppkey", "l_partkey")
    return Graph(edges_from(lines, "2 * l_suppkey", "2 * l_partkey + 1"), _ids((_table(spark, sf, "supplier"), "2 * s_suppkey"), (lines.select("l_partkey").distinct(), "2 * l_partkey + 1")), "supply")


def customer_orders(spark: SparkSession, sf: str) -> Graph:
    orders = _table(spark, sf, "orders").select("o_custkey", "o_orderkey")
    return Graph(edges_from(orders, "2 * o_custkey", "2 * o_orderkey + 1"), _ids((_table(spark, sf, "customer"), "2 * c_custkey"), (orders, "2 * o_orderkey + 1")), "customer_orders")


def bulk_returns(spark: SparkSession, sf: str) -> Graph:
    lines = _table(spark, sf, "lineitem").where("l_returnflag = 'R' and l_quantity >= 45").select("l_orderkey", "l_partkey")
    return Graph(edges_from(lines, "2 * l_orderkey", "2 * l_partkey + 1"), _ids((_table(spark, sf, "orders"), "2 * o_orderkey"), (_table(spark, sf, "part"), "2 * p_partkey + 1")), "bulk_returns")


def user_flow(spark: SparkSession, sf: str) -> Graph:
    """User of each event to the user of the next one; neighbours in time by global rank, not by one window."""
    events = global_rank(_table(spark, sf, "events").select("ts", "event_id", "user_id"), ["ts", "event_id"], "at")
    here, following = events.select("at", F.col("user_id").alias("src")), events.select((F.col("at") - 1).alias("at"), F.col("user_id").alias("dst"))
    return Graph(here.join(following, "at").select("src", "dst"), events.select(F.col("user_id").alias("v")).distinct(), "user_flow")


def geo_tree(spark: SparkSession, sf: str) -> Graph:
    region, nation, customer, supplier = (_table(spark, sf, t) for t in ("region", "nation", "customer", "supplier"))
    raw = edges_from(nation, "4 * n_nationkey + 1", "4 * n_regionkey").union(edges_from(customer, "4 * c_custkey + 2", "4 * c_nationkey + 1")).union(edges_from(supplier, "4 * s_suppkey + 3", "4 * s_nationkey + 1"))
    return Graph(raw, _ids((region, "4 * r_regionkey"), (nation, "4 * n_nationkey + 1"), (customer, "4 * c_custkey + 2"), (supplier, "4 * s_suppkey + 3")), "geo_tree")


def turn_chain(spark: SparkSession, sf: str) -> Graph:
    turns = _table(spark, sf, "conversations").select("conv_id", "turn")
    following = turns.select("conv_id", (F.col("turn") - 1).alias("turn"))
    raw = edges_from(turns.join(following, ["conv_id", "turn"]), "100 * conv_id + turn", "100 * conv_id + turn + 1")
    return Graph(raw, _ids((turns.distinct(), "100 * conv_id + turn")), "turn_chain")


def doc_copies(spark: SparkSession, sf: str) -> Graph:
    """Documents of equal text, each linked to the least id among them: a group of n copies gives n - 1 edges, not all pairs."""
    docs = _table(spark, sf, "documents").select("doc_id", F.md5(F.col("text").cast("binary")).alias("h")).where("h is not null")
    least = docs.groupBy("h").agg(F.min("doc_id").alias("src"), F.count("*").alias("n")).where("n > 1")
    raw = docs.join(least, "h").where("doc_id <> src").select("src", F.col("doc_id").alias("dst"))
    return Graph(raw, _ids((_table(spark, sf, "documents"), "doc_id")), "doc_copies")


def page_anchor(spark: SparkSession, sf: str) -> Graph:
    links = _table(spark, sf, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit(r'href="(/[^"]*)"'), F.lit(1))).alias("path"))
    paths = global_rank(links.select("path").distinct(), ["path"], "at")
    raw = edges_from(links.join(paths, "path"), "2 * page_id", "2 * at + 1")
    return Graph(raw, _ids((_table(spark, sf, "pages"), "2 * page_id"), (paths, "2 * at + 1")), "page_anchor")


def vector_sim(spark: SparkSession, sf: str, above: float = 0.45, block: int = 1024) -> Graph:
    """Pairs of vectors with a cosine above the bound: products of blocks of vectors, one pair of blocks a group.

    Only matching pairs leave a group; a group holds two blocks whatever the size of the table."""
    vectors = _table(spark, sf, "embeddings").select(F.col("vec_id").cast("long").alias("vec_id"), "embedding")
    blocks = max(1, -(-vectors.count() // block))
    b = F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int")
    other = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    dealt = vectors.withColumn("b", b).withColumn("o", other).select("vec_id", "embedding", F.col("b"), F.least("b", "o").alias("lo"), F.greatest("b", "o").alias("hi"))

    def pairs(pdf: pd.DataFrame) -> pd.DataFrame:
        x = np.stack(pdf["embedding"].to_numpy()).astype(np.float64)
        x /= np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-30)
        ids, at = pdf["vec_id"].to_numpy(), pdf["b"].to_numpy()
        lo, hi = int(pdf["lo"].iloc[0]), int(pdf["hi"].iloc[0])
        left, right = np.flatnonzero(at == lo), np.flatnonzero(at == hi)
        i, j = np.nonzero(x[left] @ x[right].T > above)
        a, c = ids[left[i]], ids[right[j]]
        keep = a < c if lo == hi else a != c
        return pd.DataFrame({"src": np.minimum(a, c)[keep], "dst": np.maximum(a, c)[keep]})

    return Graph(dealt.groupBy("lo", "hi").applyInPandas(pairs, "src long, dst long"), _ids((vectors, "vec_id")), "vector_sim")


def _windows(words: Column) -> Column:
    """Hashes of all runs of ``SEED_WORDS`` words, each once."""
    at = F.sequence(F.lit(1), F.size(words) - (SEED_WORDS - 1))
    hashes = F.array_distinct(F.transform(at, lambda i: F.xxhash64(F.array_join(F.slice(words, i, SEED_WORDS), " "))))
    return F.when(F.size(words) >= SEED_WORDS, hashes).otherwise(F.array().cast("array<bigint>"))


def containment(docs: DataFrame, items: DataFrame, pass_bytes: int = 32_000_000) -> DataFrame:
    """Pairs ``doc_id, item_id`` of rows with ``text`` containing ``item``.

    The words of an item between its first and last blank stand whole in any text that holds it, so
    the run of them that fewest items share is its seed: one scan of the texts meets all seeds in an
    equi-join on hashes, and only the pairs it finds are compared.  Items with too few words for a
    seed are compared with every text, ``pass_bytes`` of them at a time."""
    words = F.split("item", " ")
    split = items.where("item is not null").select("item_id", "item", F.slice(words, F.lit(2), F.greatest(F.size(words) - 2, F.lit(0))).alias("inner"))
    seeded = F.size("inner") >= SEED_WORDS
    seeds = split.where(seeded).select("item_id", "item", F.explode(_windows(F.col("inner"))).alias("seed"))
    shared = seeds.groupBy("seed").agg(F.count("*").alias("n"))
    rarest = seeds.select("item_id", F.md5(F.col("item").cast("binary")).alias("h"), "seed").join(shared, "seed").groupBy("item_id", "h").agg(F.min(F.struct("n", "seed")).alias("x"))
    rarest = materialize(rarest.select("item_id", F.col("x.seed").alias("seed")), "item_seeds")
    # the words are a column of their own, so they are split once and not for each run
    met = docs.select("doc_id", F.split("text", " ").alias("words")).select("doc_id", F.explode(_windows(F.col("words"))).alias("seed")).join(rarest, "seed")
    met = materialize(met.select("doc_id", "item_id").distinct(), "item_candidates")
    whole = docs.join(met, "doc_id").join(split.where(seeded).select("item_id", "item"), "item_id").where(F.col("text").contains(F.col("item")))
    found = whole.select("doc_id", "item_id")
    short = split.where(~seeded).select("item_id", "item")
    passes = -(-short.agg(F.coalesce(F.sum(F.octet_length("item") + 1), F.lit(0))).first()[0] // pass_bytes)
    for k in range(passes):
        part = F.broadcast(short.where(F.pmod(F.xxhash64("item_id"), F.lit(passes)) == k))
        found = found.union(docs.join(part, F.col("text").contains(F.col("item"))).select("doc_id", "item_id"))
    return found


def bench_overlap(spark: SparkSession, sf: str) -> Graph:
    """Documents and the benchmark items whose text they contain."""
    docs = _table(spark, sf, "documents").select("doc_id", "text")
    items = _table(spark, sf, "benchmark").select("item_id", F.col("text").alias("item"))
    return Graph(edges_from(containment(docs, items), "2 * doc_id", "2 * item_id + 1"), _ids((docs, "2 * doc_id"), (items, "2 * item_id + 1")), "bench_overlap")


GRAPHS: dict[str, Callable[[SparkSession, str], Graph]] = {
    "purchase": purchase, "returned_purchase": returned_purchase, "supply": supply, "customer_orders": customer_orders, "bulk_returns": bulk_returns,
    "user_flow": user_flow, "geo_tree": geo_tree, "turn_chain": turn_chain, "doc_copies": doc_copies, "page_anchor": page_anchor, "vector_sim": vector_sim, "bench_overlap": bench_overlap,
    "kron8": lambda spark, sf: kronecker(spark, 8), "kron10": lambda spark, sf: kronecker(spark, 10), "kron12": lambda spark, sf: kronecker(spark, 12), "kron14": lambda spark, sf: kronecker(spark, 14),
    "uniform10": lambda spark, sf: kronecker(spark, 10, probs=(0.25, 0.25, 0.25, 0.25)),
    "shuffled10": lambda spark, sf: kronecker(spark, 10, shuffle_labels=True),
    "kron_orders": lambda spark, sf: Graph(kronecker_from(_table(spark, sf, "orders"), "o_orderkey", 10).select("src", "dst"), spark.range(1024).withColumnRenamed("id", "v"), "kron_orders"),
}


def load(spark: SparkSession, sf: str, name: str) -> Graph:
    return GRAPHS[name](spark, sf)
