"""MinHash near-duplicate groups by a signature-coordinate inverted join.

Every distinct shingle set gets a signature of ``COORDINATES`` minimum hashes and is posted under
each (coordinate, value).  Two sets at the threshold similarity or above collide in ``least`` of
the coordinates at least (see :func:`least_equal`).  So

* a set with fewer than ``least`` values that some other set has too is skipped altogether;
* the others post only a prefix: with their values by length of the posting list, shortest first,
  all but the ``least - 1`` longest lists.  Two sets with ``least`` collisions meet in a list of both
  prefixes, and lists of common passages are never merged where rarer ones decide.

Collisions over the whole signature are then counted, eight coordinates to a word, inside the join
condition: a pair that cannot reach the threshold by size or has fewer than ``least`` collisions is
dropped.  The others are confirmed on their full shingle sets.

Two passes keep hot lists linear.  The first links each text to the head (least id) of each of its
lists, of single coordinates and of ``MERGED`` neighbouring ones together, which large groups of
edited copies share in many small lists.  The second looks only at merged lists that still hold
several components and pairs texts of different components there; a list of thousands of copies of
one text is by then a single component and forms no pair.  Long open lists are cut into blocks whose
pairs are dealt to different tasks.  There a finer signature tells pairs far below the threshold
from close ones before their sets are brought together.  No candidate is capped or dropped.

Texts never move between machines: what has to be looked at again is named by a bit filter of
bounded size, and each task expands the sets of its own texts that pass it.

A pair at exactly the threshold similarity 0.75 has too few of 78 equal coordinates with a
probability of about 2e-6 and meets in no merged list with one of 6e-7; both fall steeply above it.
The finer signature misses it with one of 3e-7.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from levelgraph.llm import text as tx
from levelgraph.llm.bit_filter import BitFilter, exclude
from levelgraph.reorder.components import star_contraction
from levelgraph.runtime import discard, materialize

SHINGLE_WORDS = 5
THRESHOLD_PERCENT = 75
COORDINATES = 78
MERGED = 3
LANES = 8
# members of a block of an open list: pairs of blocks are dealt to tasks
BLOCK = 4096
FINE = 1024
# a pair at the threshold falls this many standard deviations short of the expected collisions at most
DEVIATIONS = 5.0
SEED = 20240607

SIGNED = "doc_id long, n_shingles long, f1 long, f2 long, values array<int>, lanes array<long>"
FINER = "doc_id long, fine array<long>"
SETS = "doc_id long, shingles array<long>"


def shingle_sets(texts: pa.Array, size: int = SHINGLE_WORDS) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of each text; fewer words than ``size`` make one shingle."""
    w = tx.words(texts, lower=True)
    h = w.hashes()
    win, at = tx.window_hashes(h, w.first, size)
    cut = np.searchsorted(at, w.first)
    out = []
    for i, n in enumerate(w.counts):
        if n >= size:
            out.append(np.unique(win[cut[i] : cut[i + 1]]))
        elif n:
            out.append(np.array([tx.sequence_hash(h[w.first[i] : w.first[i + 1]])], dtype=np.uint64))
        else:
            out.append(np.empty(0, dtype=np.uint64))
    return out


def _parameters(coordinates: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(seed)
    return rng.integers(0, 2**31, coordinates, dtype=np.uint32) * np.uint32(2) + np.uint32(1), rng.integers(0, 2**32, coordinates, dtype=np.uint32)


def signature(shingles: np.ndarray, mult: np.ndarray, add: np.ndarray) -> np.ndarray:
    """Minimum of each coordinate's 32-bit hash over a non-empty set of well-mixed 64-bit hashes."""
    low = np.full(len(mult), np.uint32(2**32 - 1))
    short = (shingles >> np.uint64(32)).astype(np.uint32)
    with np.errstate(over="ignore"):
        for lo in range(0, len(short), 512):
            part = short[lo : lo + 512, None] * mult[None, :]
            part += add[None, :]
            np.minimum(low, part.min(axis=0), out=low)
    return low


def _long(column: str) -> F.Column:
    return F.col(column).cast("long")


def _lists(table: np.ndarray) -> pa.Array:
    n, width = table.shape
    return pa.ListArray.from_arrays(pa.array(np.arange(0, n * width + 1, width, dtype=np.int32)), pa.array(table.ravel()))


def sign(docs: DataFrame, coordinates: int = COORDINATES, seed: int = SEED, size: int = SHINGLE_WORDS) -> DataFrame:
    """Set size, set fingerprint, signature and packed signature of each document."""
    words = -(-coordinates // LANES)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        mult, add = _parameters(coordinates, seed)
        for batch in tx.slices(batches, "text"):
            sets = shingle_sets(batch.column("text"), size)
            n = np.array([len(s) for s in sets], dtype=np.int64)
            f = np.zeros((len(sets), 2), dtype=np.uint64)
            low = np.zeros((len(sets), coordinates), dtype=np.uint32)
            with np.errstate(over="ignore"):
                for i, s in enumerate(sets):
                    if len(s):
                        f[i] = s.sum(dtype=np.uint64), np.bitwise_xor.reduce(tx.mix(s))
                        low[i] = signature(s, mult, add)
                lanes = np.zeros((len(sets), words * LANES), dtype=np.uint8)
                lanes[:, :coordinates] = (low * np.uint32(0x9E3779B1)) >> np.uint32(24)
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), pa.array(n), pa.array(f[:, 0].copy().view(np.int64)), pa.array(f[:, 1].copy().view(np.int64)), _lists(low.view(np.int32)), _lists(lanes.view(np.int64))],
                names=["doc_id", "n_shingles", "f1", "f2", "values", "lanes"],
            )

    return docs.select(_long("doc_id").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, SIGNED)


def least_equal(coordinates: int, percent: int, values: int = 256) -> int:
    """Equal coordinates, of hashes with so many values, below which a pair is taken to miss the threshold."""
    p = percent / 100 + (1 - percent / 100) / values
    return max(1, int(coordinates * p - DEVIATIONS * (coordinates * p * (1 - p)) ** 0.5))


def _likely(a: str, b: str, percent: int, coordinates: int, least: int) -> F.Column:
    """Whether the sizes allow the similarity and at least ``least`` coordinates of two signatures are equal."""
    fits = F.expr(f"100 * least({a}.n, {b}.n) >= {percent} * greatest({a}.n, {b}.n)")
    unequal = F.lit(0)
    for k in range(-(-coordinates // LANES)):
        x = F.col(f"{a}.lanes")[k].bitwiseXOR(F.col(f"{b}.lanes")[k])
        for shift in (4, 2, 1):
            x = x.bitwiseOR(F.shiftrightunsigned(x, shift))
        unequal = unequal + F.bit_count(x.bitwiseAND(F.lit(0x0101010101010101)))
    return fits & (unequal <= coordinates - least)


def _finely_equal(a: str, b: str) -> F.Column:
    """How many coordinates of two finer signatures are equal."""

    def unequal(x: F.Column, y: F.Column) -> F.Column:
        z = x.bitwiseXOR(y)
        z = z.bitwiseOR(F.shiftrightunsigned(z, 2))
        z = z.bitwiseOR(F.shiftrightunsigned(z, 1))
        return F.bit_count(z.bitwiseAND(F.lit(0x1111111111111111)))

    return F.lit(FINE) - F.aggregate(F.zip_with(F.col(a), F.col(b), unequal), F.lit(0), lambda t, x: t + x)


def _expand(docs: DataFrame, ids: DataFrame, build: Callable[[list[np.ndarray]], pa.Array], size: int, schema: str) -> DataFrame:
    """``doc_id`` and what ``build`` makes of the shingle sets of the texts that ``ids`` names (perhaps of a few more)."""
    named = BitFilter(ids, "doc_id")
    names = [x.split()[0] for x in schema.split(", ")]
    target = pa.schema([(names[0], pa.int64()), (names[1], pa.list_(pa.int64()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            batch = batch.filter(pa.array(named.holds(batch.column("slot").to_numpy())))
            for part in tx.slices([batch], "text", 1_000_000):
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), build(shingle_sets(part.column("text"), size))], schema=target)

    rows = docs.select(_long("doc_id").alias("doc_id"), F.col("text").cast("string").alias("text")).where("doc_id is not null")
    return rows.withColumn("slot", named.slot("doc_id")).mapInArrow(run, schema)


def expand_sets(docs: DataFrame, ids: DataFrame, size: int = SHINGLE_WORDS) -> DataFrame:
    """Full shingle sets of the named documents."""

    def build(sets: list[np.ndarray]) -> pa.Array:
        flat = np.concatenate([*sets, np.empty(0, np.uint64)]).view(np.int64)
        return pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, sets)]).astype(np.int32)), pa.array(flat))

    return _expand(docs, ids, build, size, SETS)


def sign_finely(docs: DataFrame, ids: DataFrame, seed: int = SEED, size: int = SHINGLE_WORDS) -> DataFrame:
    """Signature of ``FINE`` coordinates of the named documents, four bits of each, sixteen to a word."""

    def build(sets: list[np.ndarray]) -> pa.Array:
        mult, add = _parameters(FINE, seed + 1)
        nibbles = np.zeros((len(sets), FINE), dtype=np.uint8)
        with np.errstate(over="ignore"):
            for i, s in enumerate(sets):
                if len(s):
                    nibbles[i] = (signature(s, mult, add) * np.uint32(0x9E3779B1)) >> np.uint32(28)
        packed = nibbles[:, 0::2] | (nibbles[:, 1::2] << np.uint8(4))
        return _lists(np.ascontiguousarray(packed).view(np.int64))

    return _expand(docs, ids, build, size, FINER)


def _confirm(pairs: DataFrame, docs: DataFrame, percent: int, size: int) -> DataFrame:
    """Pairs ``(a, b)`` whose full sets reach the similarity ``percent``/100.

    Only texts that some pair names are expanded again, each where it is read.
    """
    pairs = materialize(pairs, "pairs")
    named = pairs.select(F.col("a").alias("doc_id")).union(pairs.select("b")).distinct()
    sets = materialize(expand_sets(docs, named, size), "sets")
    left = sets.select(F.col("doc_id").alias("a"), F.col("shingles").alias("sa"))
    right = sets.select(F.col("doc_id").alias("b"), F.col("shingles").alias("sb"))
    both = pairs.join(left, "a").join(right, "b")
    shared = F.size(F.array_intersect("sa", "sb")).cast("long")
    both = both.select("a", "b", shared.alias("both"), (F.size("sa") + F.size("sb")).cast("long").alias("sizes"))
    links = materialize(both.where(F.expr(f"100 * both >= {percent} * (sizes - both)")).select("a", "b"), "links")
    discard(sets)
    discard(pairs)
    return links


def prefix_posts(firsts: DataFrame, least: int) -> DataFrame:
    """``doc, key``: the (coordinate, value) lists under which each set is posted.

    Of ``firsts`` (``rep, values``).  Only values that two sets share make lists at all; sets with
    fewer than ``least`` of them are skipped, the others leave out their ``least - 1`` longest lists."""
    posts = firsts.select(F.col("rep").alias("doc"), F.posexplode("values").alias("at", "value"))
    posts = posts.select("doc", F.shiftleft(F.col("at").cast("long"), 32).bitwiseOR(F.col("value").cast("long").bitwiseAND(F.lit(0xFFFFFFFF))).alias("key"))
    lengths = posts.groupBy("key").agg(F.count("*").alias("n")).where("n > 1")
    mine = posts.join(lengths, "key").groupBy("doc").agg(F.collect_list(F.struct("n", "key")).alias("posts"))  # one entry a coordinate
    prefix = F.slice(F.array_sort("posts"), F.lit(1), F.size("posts") - (least - 1))
    return mine.where(F.size("posts") >= least).select("doc", F.explode(prefix["key"]).alias("key"))


def near_duplicate_groups(
    docs: DataFrame,
    percent: int = THRESHOLD_PERCENT,
    coordinates: int = COORDINATES,
    size: int = SHINGLE_WORDS,
    seed: int = SEED,
    merged: int = MERGED,
    block: int = BLOCK,
) -> DataFrame:
    """Near-duplicate component of each row of ``docs`` (needs ``doc_id`` and ``text``).

    Returns ``doc_id, n_shingles, component_id, kept``: the set size, the least id reachable
    over links, and whether the row has that id.  Texts without words, and null texts, have an
    empty set and stay alone.  Rows without an id are never linked: their component is null and
    they are kept.  Rows that repeat an id count as one document.  Other columns are ignored.
    An empty table gives an empty result.
    """
    least = least_equal(coordinates, percent)
    signed = materialize(sign(docs, coordinates, seed, size), "signed")
    sets = signed.where("n_shingles > 0 and doc_id is not null")
    same = ["n_shingles", "f1", "f2"]
    firsts = sets.groupBy(*same).agg(F.min(F.struct("doc_id", "values", "lanes")).alias("x"))
    firsts = materialize(firsts.select(*same, F.col("x.doc_id").alias("rep"), "x.values", "x.lanes"), "firsts")
    posts = materialize(prefix_posts(firsts, least), "posts")
    heads = posts.groupBy("key").agg(F.min("doc").alias("head"), F.count("*").alias("n")).where("n > 1").drop("n")
    single = materialize(posts.join(heads, "key").select("doc", "head"), "single")
    discard(posts)
    bands = coordinates // merged
    keys = F.array(*[F.xxhash64(F.lit(k), *[F.col("values")[merged * k + j] for j in range(merged)]) for k in range(bands)])
    traits = firsts.join(single.select(F.col("doc").alias("rep")).distinct(), "rep", "left_semi")
    traits = materialize(traits.select(F.col("rep").alias("doc"), F.struct(F.col("n_shingles").alias("n"), "lanes", keys.alias("keys")).alias("t")), "traits")
    posts = traits.select("doc", F.posexplode("t.keys").alias("band", "key"))
    heads = posts.groupBy("key").agg(F.min("doc").alias("head"), F.count("*").alias("n")).where("n > 1").drop("n")
    shared = materialize(posts.join(heads, "key").select("key", "band", "doc", "head"), "shared")
    likely = _likely("ta", "tb", percent, coordinates, least)

    def with_traits(pairs: DataFrame, column: str, name: str) -> DataFrame:
        return pairs.join(traits.select(F.col("doc").alias(column), F.col("t").alias(name)), column)

    stars = single.union(shared.select("doc", "head")).where("doc <> head").select(F.col("doc").alias("a"), F.col("head").alias("b")).distinct()
    stars = with_traits(with_traits(stars, "a", "ta"), "b", "tb").where(likely).select("a", "b")
    links = _confirm(stars, docs, percent, size)
    comps = star_contraction(links, "a", "b")

    placed = (
        shared.join(comps.withColumnRenamed("v", "doc"), "doc", "left")
        .select("key", "band", "doc", "head", F.coalesce("comp", "doc").alias("comp"))
    )
    placed = materialize(placed, "placed")
    open_lists = placed.groupBy("key").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), F.count("*").alias("n")).where("lo <> hi")
    open_lists = open_lists.select("key", F.ceil(F.col("n") / block).cast("int").alias("blocks"))
    members = materialize(placed.join(open_lists, "key").select("key", "band", "doc", "head", "comp", "blocks"), "members")
    fine = sign_finely(docs, members.select(F.col("doc").alias("doc_id")).distinct(), seed, size)
    fine = materialize(fine.withColumnRenamed("doc_id", "doc"), "fine")
    # a member goes to every pair of blocks that has its own: a list of one block is one group, a longer one many of bounded size
    own = F.pmod(F.xxhash64("doc"), F.col("blocks")).cast("int")
    dealt = members.withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = dealt.withColumns({"lo": F.least("own", "other"), "hi": F.greatest("own", "other")})
    dealt = with_traits(dealt, "doc", "t").join(fine, "doc")
    cell = ["key", "lo", "hi"]
    a = dealt.select(*cell, "band", F.col("doc").alias("a"), F.col("comp").alias("ca"), F.col("t").alias("ta"), F.col("fine").alias("fa"), F.col("own").alias("oa"), "head")
    b = dealt.select(*[F.col(c).alias(f"{c}_b") for c in cell], F.col("doc").alias("b"), F.col("comp").alias("cb"), F.col("t").alias("tb"), F.col("fine").alias("fb"), F.col("own").alias("ob"))
    # a pair with the head of its list has been confirmed or refused already; others count in their first common list only
    new = (F.col("ca") < F.col("cb")) & (F.col("a") != F.col("head")) & (F.col("b") != F.col("head")) & ((F.col("lo") == F.col("hi")) | (F.col("oa") != F.col("ob")))
    for c in cell:
        new = (F.col(c) == F.col(f"{c}_b")) & new
    for k in range(bands - 1):
        new = new & ((F.col("band") <= k) | (F.col("ta.keys")[k] != F.col("tb.keys")[k]))
    close = _finely_equal("fa", "fb") >= least_equal(FINE, percent, 16)
    pairs = a.join(b, new & likely & close).select("a", "b")
    more = _confirm(pairs, docs, percent, size)
    comps = materialize(star_contraction(links.union(more), "a", "b"), "comps")

    reps = firsts.select(*same, "rep").join(comps.withColumnRenamed("v", "rep"), "rep", "left")
    reps = reps.select(*same, F.coalesce("comp", "rep").alias("comp"))
    out = (
        signed.drop("values", "lanes").join(reps, same, "left")
        .select(
            "doc_id", "n_shingles",
            F.when(F.col("doc_id").isNotNull(), F.when(F.col("n_shingles") > 0, F.col("comp")).otherwise(F.col("doc_id"))).alias("component_id"),
        )
        .withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))
    )
    for table in (single, traits, shared, placed, members, fine, links, more):
        discard(table)
    return out


def drop_near_duplicates(docs: DataFrame, **options) -> DataFrame:
    """Rows of ``docs`` that stay: one document of each near-duplicate group, all columns kept."""
    groups = near_duplicate_groups(docs, **options)
    return exclude(docs, groups.where(~F.col("kept")).select("doc_id").distinct(), "doc_id")


def op1_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicate_groups(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
