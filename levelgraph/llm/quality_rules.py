"""Quality rules and a calibrated hashed n-gram classifier, scored in Arrow batches.

The rules count symbols, repeated lines and repeated word windows.  The classifier is a logistic
regression on hashed words and hashed 4-grams of characters inside words, word ends included (means
over a text, so length does not matter), fitted on labelled quality rows and calibrated on rows it has not seen.  A text is kept
if no rule fails and its calibrated probability reaches a fixed threshold.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from levelgraph.llm import learning as ln
from levelgraph.llm import text as tx

BITS = 16
SCALE = 8.0
KEEP_AT = 0.5
MIN_WORDS = 50
REPEAT_PERCENT = 50
RULES = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, score double, kept boolean"
ROWS = "label int, at int, columns array<int>, values array<float>"

SYMBOL = np.zeros(256, dtype=bool)
SYMBOL[[ord(c) for c in "#*$%&|<>"]] = True
LEAD = np.ones(256, dtype=bool)
LEAD[0x80:0xC0] = False


@dataclass(frozen=True)
class Model:
    words: np.ndarray
    grams: np.ndarray
    bias: float
    slope: float
    shift: float

    def score(self, w: tx.Words, h: np.ndarray) -> np.ndarray:
        z = self.bias + _mean(self.words[_word_slot(h)], w.first, w.counts)
        grams, first = _grams(w)
        z = z + _mean(self.grams[grams], first, np.diff(first))
        return ln.sigmoid(self.slope * z + self.shift)


def _word_slot(h: np.ndarray) -> np.ndarray:
    return (h >> np.uint64(64 - BITS)).astype(np.int64)


def _grams(w: tx.Words) -> tuple[np.ndarray, np.ndarray]:
    """Hashed slots of the 4-grams of characters of each text in order, and where each text's begin.

    A gram lies in one word with the blanks on either side of it, so words of two characters or more
    have grams; other white space counts as a blank."""
    data = np.where(tx.SPACE[w.data], np.uint8(0x20), w.data)
    cuts = w.offsets[1:-1]
    # a blank between texts, so that the ends of a text's words are seen too
    data = np.insert(data, np.concatenate([[0], cuts, [len(data)]]).astype(np.int64), 0x20) if len(w.offsets) > 1 else data
    points = np.frombuffer(data.tobytes().decode("utf-8", "replace").encode("utf-32-le"), dtype=np.uint32)
    before = np.concatenate([[0], np.cumsum(LEAD[data], dtype=np.int64)])
    edges = before[w.offsets + np.arange(len(w.offsets))]  # the blank before each text, and the one after the last
    if len(points) < 4:
        return np.empty(0, np.uint32), np.zeros(len(w.offsets), np.int64)
    blank = points == 0x20
    inside = ~(blank[1:-2] | blank[2:-1])
    with np.errstate(over="ignore"):
        g = points[:-3] * np.uint32(0x9E3779B1)
        for k in (1, 2, 3):
            g = (g ^ points[k : len(points) - 3 + k]) * np.uint32(0x85EBCA6B)
            g ^= g >> np.uint32(15)
        g = g * np.uint32(0x9E3779B1)
    at = np.flatnonzero(inside)
    return (g[at] >> np.uint32(32 - BITS)), np.searchsorted(at, edges)


def _sums(values: np.ndarray, first: np.ndarray) -> np.ndarray:
    total = np.concatenate([[0.0], np.cumsum(values, dtype=np.float64)])
    return total[first[1:]] - total[first[:-1]]


def _mean(values: np.ndarray, first: np.ndarray, n: np.ndarray) -> np.ndarray:
    return np.divide(_sums(values, first), n, out=np.zeros(len(n)), where=n > 0) * SCALE


def _features(batch: pa.RecordBatch) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    w = tx.words(batch.column("text"))
    slots = _word_slot(w.hashes())
    grams, first = _grams(w)
    for i in range(batch.num_rows):
        a, na = np.unique(slots[w.first[i] : w.first[i + 1]], return_counts=True)
        b, nb = np.unique(grams[first[i] : first[i + 1]], return_counts=True)
        yield np.concatenate([a, b.astype(np.int64) + (1 << BITS)]), np.concatenate([na / max(na.sum(), 1), nb / max(nb.sum(), 1)]) * SCALE


def fit(docs: DataFrame, labels: DataFrame, per_class: int = 1500, allowed: Column | None = None) -> Model:
    """Fit on at most ``per_class`` labelled rows of each class; a fifth of them only calibrates.

    ``allowed`` (over ``doc_id``) keeps rows out of the fit, to measure on."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in tx.slices(batches, "text"):
            rows = list(_features(batch))
            yield pa.RecordBatch.from_arrays(
                [batch.column("label"), pa.array((batch.column("doc_id").to_numpy() % 2147483647).astype(np.int32)), pa.array([c.astype(np.int32) for c, _ in rows], pa.list_(pa.int32())), pa.array([v.astype(np.float32) for _, v in rows], pa.list_(pa.float32()))],
                names=["label", "at", "columns", "values"],
            )

    sample = ln.labelled_sample(docs, labels, "quality", F.lit(True) if allowed is None else allowed, per_class)
    table = sample.mapInArrow(run, ROWS).toArrow()
    size = 2 << BITS
    y = table.column("label").to_numpy().astype(float) if table.num_rows else np.empty(0)
    if not len(y) or y.min() == y.max():
        return Model(np.zeros(1 << BITS), np.zeros(1 << BITS), 0.0, 1.0, 2.0)
    rows = [(np.array(c, np.int64), np.array(v)) for c, v in zip((x.values.to_numpy() for x in table.column("columns")), (x.values.to_numpy() for x in table.column("values")), strict=True)]
    order = np.argsort(table.column("at").to_numpy(), kind="stable")
    held = np.zeros(len(y), dtype=bool)
    held[order[::5]] = True
    if len({*y[held]}) < 2 or len({*y[~held]}) < 2:
        held[:] = False
    w, b = ln.fit_logistic(ln.Sparse([r for r, h in zip(rows, held, strict=True) if not h], size), y[~held], l2=1e-6, steps=120, rate=0.3)
    seen = held if held.any() else ~held
    z = ln.Sparse([r for r, h in zip(rows, seen, strict=True) if h], size).dot(w) + b
    slope, shift = ln.fit_platt(z, y[seen])
    return Model(w[: 1 << BITS], w[1 << BITS :], b, slope, shift)


def measure(batch: pa.RecordBatch, model: Model | None, keep_at: float = KEEP_AT) -> pa.RecordBatch:
    """Counts, rules and verdict of a batch of ``doc_id, text``."""
    w = tx.words(batch.column("text"))
    data, offsets, n = w.data, w.offsets, w.counts
    h = w.hashes()
    inside = ~tx.SPACE[data]
    chars = _sums(inside & LEAD[data], offsets)
    symbols = _sums(SYMBOL[data], offsets)

    owner = tx.mix(np.arange(1, len(n) + 1, dtype=np.uint64))
    starts, ends, lines = tx.limits(data != 10, offsets)
    holds = np.searchsorted(w.starts, ends) > np.searchsorted(w.starts, starts)
    starts, ends = starts[holds], ends[holds]
    lines = np.searchsorted(starts, offsets)
    of = np.repeat(np.arange(len(n)), np.diff(lines))
    key = tx.mix(tx.span_hashes(data, starts, ends) ^ owner[of])
    _, at = np.unique(key, return_index=True)
    again = np.ones(len(key), dtype=bool)
    again[at] = False
    dup_lines = np.bincount(of[again], minlength=len(n))

    win, at = tx.window_hashes(h, w.first, 3)
    owners = w.owners()
    _, back, count = np.unique(tx.mix(win ^ owner[owners[at]]) if len(win) else win, return_inverse=True, return_counts=True)
    hit = at[count[back] > 1]
    cover = np.zeros(len(h) + 4, dtype=np.int64)
    for k in range(3):
        cover[hit + k] = 1
    repeat = _sums(cover[: len(h)], w.first).astype(np.int64)

    failed = (n < MIN_WORDS) | (100 * repeat > REPEAT_PERCENT * n)
    score = model.score(w, h) if model is not None else np.ones(len(n))
    columns = {
        "doc_id": batch.column("doc_id"), "n_words": pa.array(n.astype(np.int64)), "word_chars": pa.array(chars.astype(np.int64)), "n_symbols": pa.array(symbols.astype(np.int64)),
        "n_dup_lines": pa.array(dup_lines.astype(np.int64)), "n_repeat_words": pa.array(repeat), "base_failed": pa.array(failed), "score": pa.array(score.astype(np.float64)), "kept": pa.array(~failed & (score >= keep_at)),
    }
    return pa.RecordBatch.from_pydict(columns)


def apply_rules(docs: DataFrame, model: Model | None = None, keep_at: float = KEEP_AT) -> DataFrame:
    """Counts and verdict of each row of ``docs`` (``doc_id``, ``text``).

    Null and empty texts have no words, so the base rule fails and they are not kept.  Without a
    model only the base rules decide.  Repeated rows are measured each; other columns are ignored.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in tx.slices(batches, "text"):
            yield measure(batch, model, keep_at)

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(run, RULES)


def op6_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return apply_rules(docs, fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))
