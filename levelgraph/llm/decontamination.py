"""Benchmark decontamination: word-pair seeds, then Smith-Waterman alignment.

Seeds are pairs of item words that are neighbours or have one word between them, looked for as
such pairs in the training texts, so one replaced, added or missing word does not break a seed.
An alignment of score ``leak_at * MATCH * n`` with an item of n words (matches cost nothing, each
other step loses 1) has at least ``leak_at * n - 1`` matched words followed by the next one over
at most one such step: two steps or more after all the others would lose too much.  So an item's
commonest pairs can be left out up to the number that must hit less the number asked for, and a
stretch of text with too few hits cannot hold a leak.  What passes is aligned with the item, and
the local alignment score tells copies, edited or paraphrased ones included, from chance.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from levelgraph.llm import text as tx
from levelgraph.llm.bit_filter import exclude

MATCH, MISMATCH, GAP = 2, -1, -1
LEAK_AT = 0.5
MIN_ITEM_WORDS = 4
# the items that one pass carries to the executors, at most
PASS_BYTES = 32_000_000
# seed hits that are sorted at once, unless one text has more
BLOCK_HITS = 2_000_000
HITS = "doc_id long, item_id long, score double, matched long, first_word long, last_word long"

_LETTER = np.zeros(256, dtype=bool)
_LETTER[[*range(48, 58), *range(65, 91), *range(97, 123), *range(0x80, 0x100)]] = True


def _unspaced(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First bytes of the characters of scripts without blanks (Han, kana, Thai, Lao, Khmer, Burmese), and the bytes after them."""
    if not (data >= 0xE0).any():
        return np.empty(0, np.int64), np.empty(0, np.int64)
    d, follow = data, np.append(data[1:], np.uint8(0))
    within = lambda x, lo, hi: (x >= lo) & (x <= hi)
    three = within(d, 0xE3, 0xE9) | (d == 0xE0) & within(follow, 0xB8, 0xBB) | (d == 0xE1) & (within(follow, 0x80, 0x82) | within(follow, 0x9E, 0x9F)) | (d == 0xEF) & within(follow, 0xA4, 0xAB)
    a, b = np.flatnonzero(three), np.flatnonzero((d == 0xF0) & within(follow, 0xA0, 0xBF))
    return np.concatenate([a, b]), np.concatenate([a + 3, b + 4])


def _read(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the lower-cased letter runs of each text, and the first run of each; characters of
    scripts without blanks are runs of their own."""
    data, offsets = tx.buffers(texts)
    data = tx.LOWER[data]
    inside = _LETTER[data]
    starts, ends, first = tx.limits(inside, offsets)
    opens, after = _unspaced(data)
    if len(opens):
        cuts = np.concatenate([opens, after[after < len(data)]])
        cuts = np.setdiff1d(cuts[inside[cuts]], starts)
        starts, ends = np.sort(np.concatenate([starts, cuts])), np.sort(np.concatenate([ends, cuts]))
        first = np.searchsorted(starts, offsets)
    return tx.span_hashes(data, starts, ends), first


@dataclass(frozen=True)
class Index:
    """Words of the items of one pass, their seeds sorted by hash, per item the hits asked for and
    the steps that an alignment can lose, and the sizes of items that are one seed."""

    item_ids: np.ndarray
    words: np.ndarray
    first: np.ndarray
    seeds: np.ndarray
    item: np.ndarray
    place: np.ndarray
    asked: np.ndarray
    slack: np.ndarray
    short: tuple[int, ...]


def _pairs(words: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the pairs of neighbours and of words with one between them, and the first word of each."""
    near, at = tx.window_hashes(words, first, 2)
    _, far = tx.window_hashes(words, first, 3)
    with np.errstate(over="ignore"):
        over = tx.mix(words[far] * tx._WINDOW_KEYS[0] + words[far + 2] * tx._WINDOW_KEYS[1]) if len(far) else np.empty(0, np.uint64)
    return np.concatenate([near, over]), np.concatenate([at, far])


def build_index(items: pa.Table, leak_at: float = LEAK_AT) -> Index:
    """Seeds of all items.  ``must`` places of an item have a hit in every leak; half of that number
    is asked for, and as many of the item's commonest places as that allows are left out.  Items of
    fewer than ``MIN_ITEM_WORDS`` words are one seed of their own size."""
    words, first = _read(items.column("text"))
    size = np.diff(first)
    must = np.maximum(np.ceil(leak_at * size - 1e-9).astype(np.int64) - 1, 1)
    asked = (must + 1) // 2
    win, at = _pairs(words, first)
    owner = (np.searchsorted(first, at, side="right") - 1).astype(np.int64)
    long = size[owner] >= MIN_ITEM_WORDS
    win, at, owner = win[long], at[long], owner[long]
    _, group, posts = np.unique(win, return_inverse=True, return_counts=True)
    load = np.zeros(len(words), dtype=np.int64)
    np.add.at(load, at, posts[group])
    places = np.unique(at)
    of = (np.searchsorted(first, places, side="right") - 1).astype(np.int64)
    order = np.lexsort((places, -load[places], of))
    rank = np.arange(len(order)) - np.searchsorted(of, of[order], side="left")
    left_out = np.zeros(len(words), dtype=bool)
    left_out[places[order][rank < (must - asked)[of[order]]]] = True
    use = ~left_out[at]
    win, owner, place = win[use], owner[use], at[use] - first[owner[use]]
    short = tuple(k for k in range(1, MIN_ITEM_WORDS) if (size == k).any())
    for k in short:
        whole = np.flatnonzero(size == k)
        own = tx.window_hashes(words, first, k)
        win, owner = np.concatenate([win, own[0][np.searchsorted(own[1], first[whole])]]), np.concatenate([owner, whole])
        place = np.concatenate([place, np.zeros(len(whole), np.int64)])
    order = np.argsort(win, kind="stable")
    slack = np.ceil(np.maximum(1 - leak_at, 0) * MATCH * size).astype(np.int64)
    slack[size < MIN_ITEM_WORDS] = 0
    return Index(items.column("item_id").to_numpy(), words, first, win[order], owner[order], place[order], asked, slack, short)


def align(item: np.ndarray, text: np.ndarray) -> tuple[int, int, int]:
    """Best local alignment score of two word sequences, and the text words where it starts and ends."""
    n = len(text)
    steps = np.arange(n + 1, dtype=np.int32) * -GAP
    row, begin = np.zeros(n + 1, np.int32), np.arange(n + 1)
    best, lo, hi = 0, 0, 0
    for w in item:
        diag = row[:-1] + np.where(text == w, MATCH, MISMATCH)
        up = row[1:] + GAP
        fresh = np.maximum(np.maximum(diag, up), 0)
        origin = np.where(fresh == 0, np.arange(1, n + 1), np.where(diag >= up, begin[:-1], begin[1:]))
        fresh = np.concatenate([[0], fresh])
        origin = np.concatenate([[0], origin])
        lifted = fresh + steps
        run = np.maximum.accumulate(lifted)
        source = np.maximum.accumulate(np.where(lifted == run, np.arange(n + 1), 0))
        row = (run - steps).astype(np.int32)
        begin = np.where(row > fresh, origin[source], origin)
        k = int(row.argmax())
        if row[k] > best:
            best, lo, hi = int(row[k]), int(begin[k]), k
    return best, lo, hi


def _windows(diagonals: np.ndarray, size: int, slack: int, n: int) -> Iterator[tuple[int, int]]:
    """Stretches of the text that hold every alignment over the seeds' diagonals, overlapping ones joined up to three items long."""
    lows = np.unique(diagonals - slack)
    lo = hi = None
    for x in lows.tolist():
        end = x + size + 2 * slack
        if hi is None:
            lo, hi = x, end
        elif x <= hi - size // 2 and end - lo <= 3 * size + 4 * slack:
            hi = end
        else:
            yield max(lo, 0), min(hi, n)
            lo, hi = x, end
    if hi is not None:
        yield max(lo, 0), min(hi, n)


def _blocks(n_hits: np.ndarray, first: np.ndarray, at: np.ndarray) -> Iterator[tuple[int, int]]:
    """Ranges of seeds (sorted by place) of whole texts that have ``BLOCK_HITS`` hits together, or of one text."""
    ends = np.searchsorted(at, first[1:])
    total = np.concatenate([[0], np.cumsum(n_hits)])
    lo = 0
    while lo < len(at):
        k = int(np.searchsorted(total[ends], total[lo] + BLOCK_HITS, side="right")) - 1
        hi = int(ends[k]) if k >= 0 and ends[k] > lo else int(ends[np.searchsorted(ends, lo, side="right")])
        yield lo, hi
        lo = hi


def _candidates(index: Index, words: np.ndarray, first: np.ndarray, mask: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Text, item and diagonal of each hit that has enough others after it in the reach of one alignment."""
    size = np.diff(index.first)
    win, at = _pairs(words, first)
    for k in index.short:
        if k != 2:  # pairs of neighbours are there
            own = tx.window_hashes(words, first, k)
            win, at = np.concatenate([win, own[0]]), np.concatenate([at, own[1]])
    maybe = mask[(win >> np.uint64(42)).astype(np.int64)]
    win, at = win[maybe], at[maybe]
    a, b = np.searchsorted(index.seeds, win, "left"), np.searchsorted(index.seeds, win, "right")
    hit = b > a
    order = np.argsort(at[hit], kind="stable")
    at, a, n = at[hit][order], a[hit][order], (b - a)[hit][order]
    for lo, hi in _blocks(n, first, at):
        m = n[lo:hi]
        where, entry = np.repeat(at[lo:hi], m), np.repeat(a[lo:hi], m) + (np.arange(m.sum()) - np.repeat(np.cumsum(m) - m, m))
        doc = np.searchsorted(first, where, side="right") - 1
        key = doc * np.int64(len(size) + 1) + index.item[entry]
        place, start = where - first[doc], index.place[entry]
        order = np.lexsort((start, place, key))
        key, place, start = key[order], place[order], start[order]
        new = np.ones(len(key), dtype=bool)
        new[1:] = (key[1:] != key[:-1]) | (place[1:] != place[:-1]) | (start[1:] != start[:-1])
        key, place, start = key[new], place[new], start[new]
        doc, item = np.divmod(key, len(size) + 1)
        last = np.arange(len(key)) + index.asked[item] - 1
        inside = last < len(key)
        last = np.where(inside, last, 0)
        keep = inside & (key[last] == key) & (place[last] - place <= size[item] + index.slack[item])
        yield doc[keep], item[keep], (place - start)[keep]


def scan(docs: DataFrame, index: Index, leak_at: float = LEAK_AT) -> DataFrame:
    size = np.diff(index.first)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        mask = np.zeros(1 << 22, dtype=bool)
        mask[(index.seeds >> np.uint64(42)).astype(np.int64)] = True
        for batch in tx.slices(batches, "text"):
            words, first = _read(batch.column("text"))
            out = []
            for doc, item, diagonal in _candidates(index, words, first, mask):
                cuts = np.flatnonzero((np.diff(doc) != 0) | (np.diff(item) != 0)) + 1 if len(doc) else np.empty(0, int)
                for lo, hi in zip([0, *cuts.tolist()], [*cuts.tolist(), len(doc)], strict=True):
                    if lo == hi:
                        continue
                    d, i = int(doc[lo]), int(item[lo])
                    n, full = int(size[i]), MATCH * int(size[i])
                    source, target = index.words[index.first[i] : index.first[i + 1]], words[first[d] : first[d + 1]]
                    best = (0, 0, 0)
                    for x, y in _windows(diagonal[lo:hi], n, int(index.slack[i]), len(target)):
                        score, s, e = align(source, target[x:y])
                        if score > best[0]:
                            best = (score, x + s, x + e - 1)
                        if score == full:
                            break
                    if best[0] >= (leak_at if n >= MIN_ITEM_WORDS else 1) * full:
                        out.append((d, i, best[0] / full, *best))
            ids = batch.column("doc_id").to_pylist()
            yield pa.RecordBatch.from_arrays(
                [pa.array([ids[o[0]] for o in out], pa.int64()), pa.array([int(index.item_ids[o[1]]) for o in out], pa.int64()), pa.array([o[2] for o in out], pa.float64()), pa.array([o[3] // MATCH for o in out], pa.int64()), pa.array([o[4] for o in out], pa.int64()), pa.array([o[5] for o in out], pa.int64())],
                names=["doc_id", "item_id", "score", "matched", "first_word", "last_word"],
            )

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.where("text is not null").mapInArrow(run, HITS)


def find_leaks(docs: DataFrame, benchmark: DataFrame, leak_at: float = LEAK_AT, pass_bytes: int = PASS_BYTES) -> DataFrame:
    """Leaked test items: ``doc_id, item_id, score, matched, first_word, last_word``.

    One row for each text row and item whose best alignment reaches ``leak_at`` of the item's full
    score; word places count lower-cased runs of letters and digits, and single characters of
    scripts without blanks.  Items with fewer than ``MIN_ITEM_WORDS`` words leak where they stand
    whole; items without a word, null items and null texts give nothing.  A benchmark beyond
    ``pass_bytes`` is scanned for in several passes, so what an executor holds is bounded.
    """
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text")).where("item_id is not null and text is not null")
    total = items.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0)).alias("n")).first()["n"]
    passes = max(1, -(-total // pass_bytes))
    found = None
    for k in range(passes):
        part = items.where(F.pmod(F.xxhash64("item_id"), F.lit(passes)) == k) if passes > 1 else items
        index = build_index(part.toArrow().sort_by("item_id"), leak_at)
        hits = scan(docs, index, leak_at)
        found = hits if found is None else found.union(hits)
    return found


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """Rows of ``docs`` in which no test item leaks; all columns kept, rows without an id stay."""
    return exclude(docs, find_leaks(docs, benchmark, **options).select("doc_id").distinct(), "doc_id")


def op9_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return find_leaks(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
