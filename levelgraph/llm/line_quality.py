"""Document quality from a linear-chain conditional random field over lines.

Every line gets a good or bad label from features of its own and of the lines next to it.  The
posterior of each line comes from forward-backward sums over the whole document; weighted by line
length they aggregate into one number, which a logistic fit turns into the document's score.

Lines carry no labels of their own: fitting starts from the document's label and then relabels
lines of bad documents that the chain itself is sure are good.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from levelgraph.llm import learning as ln
from levelgraph.llm import text as tx

PREDICT_AT = 0.3
FOLDS, HELD = 5, 0
SAMPLE_ROWS = 1500
# text whose lines are turned into features at once: about a hundred bytes of features a byte of very short lines
SLICE_BYTES = 400_000
SCORES = "doc_id long, n_lines long, bad_share double, score double"
ROWS = "label int, lengths array<int>, features array<float>"

_CLASSES = np.zeros((6, 256), dtype=bool)
_CLASSES[0, [ord(c) for c in "#*$%&|<>{}[]\\^~@=_+/"]] = True
_CLASSES[1, 65:91] = True
_CLASSES[2, [ord("!"), ord("?")]] = True
_CLASSES[3, 48:58] = True
_CLASSES[4, [*range(97, 123), *range(0x80, 0x100)]] = True
_CLASSES[5, ord("|")] = True
# bins of each share or count; a feature is one bin of one measure
_EDGES = (
    (0.005, 0.03, 0.08), (0.06, 0.15, 0.4), (0.005, 0.03, 0.08), (0.02, 0.1, 0.3), (0.5, 0.65, 0.75), (0.005, 0.03, 0.08),
    (3.5, 4.5, 6.5), (2.5, 6.5, 20.5), (0.05, 0.3, 0.6), (0.05, 0.3, 0.6), (0.5,), (0.5,),
)
N_OWN = sum(len(e) + 1 for e in _EDGES)
N_FEATURES = 3 * N_OWN + 2


@dataclass
class Lines:
    first: np.ndarray  # index of the first line of each text
    length: np.ndarray
    own: np.ndarray  # one-hot bins, lines by N_OWN


def _between(flags: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    total = np.concatenate([[0], np.cumsum(flags, dtype=np.int64)])
    return (total[ends] - total[starts]).astype(np.float64)


def read_lines(texts: pa.Array) -> Lines:
    """Lines with at least one word, their lengths in bytes and their binned measures."""
    w = tx.words(texts)
    h = w.hashes()
    starts, ends, _ = tx.limits(w.data != 10, w.offsets)
    lo, hi = np.searchsorted(w.starts, starts), np.searchsorted(w.starts, ends)
    keep = hi > lo
    starts, ends, lo, hi = starts[keep], ends[keep], lo[keep], hi[keep]
    first = np.searchsorted(starts, w.offsets)
    size = (ends - starts).astype(np.float64)
    n_words = (hi - lo).astype(np.float64)
    doc = np.repeat(np.arange(len(first) - 1), np.diff(first))
    line = np.repeat(np.arange(len(starts)), hi - lo)
    of = tx.mix(np.arange(1, max(len(first), len(starts)) + 1, dtype=np.uint64))

    def repeated(keys: np.ndarray) -> np.ndarray:
        _, at = np.unique(keys, return_index=True)
        again = np.ones(len(keys), dtype=bool)
        again[at] = False
        return again

    # words in lines, in order: every word lies in exactly one kept line
    again_line = np.bincount(line[repeated(tx.mix(h ^ of[line]))], minlength=len(starts)) / np.maximum(n_words, 1)
    pair = tx.mix(h[:-1] * np.uint64(3) ^ h[1:]) if len(h) else h
    if len(h):
        same = line[:-1] == line[1:]
        pairs = repeated(tx.mix(pair[same] ^ of[doc[line[:-1][same]]]))
        again_pair = np.bincount(line[:-1][same][pairs], minlength=len(starts)) / np.maximum(n_words, 1)
    else:
        again_pair = np.zeros(len(starts))
    copy = repeated(tx.mix(tx.span_hashes(w.data, starts, ends) ^ of[doc])).astype(float)
    shares = [_between(c[w.data], starts, ends) / size for c in _CLASSES]
    letters = np.maximum(_between((_CLASSES[1] | _CLASSES[4])[w.data], starts, ends), 1)
    shares[1] = _between(_CLASSES[1][w.data], starts, ends) / letters
    lone = (np.diff(first) == 1).astype(float)[doc]
    measures = [*shares, size / np.maximum(n_words, 1), n_words, again_line, again_pair, copy, lone]
    own = np.zeros((len(starts), N_OWN), dtype=np.float32)
    at, rows = 0, np.arange(len(starts))
    for x, edges in zip(measures, _EDGES, strict=True):
        own[rows, at + np.searchsorted(edges, x)] = 1
        at += len(edges) + 1
    return Lines(first, size, own)


def with_neighbours(own: np.ndarray, first: np.ndarray) -> np.ndarray:
    """A line's own bins, those of the lines before and after it, and flags for either end."""
    n = len(own)
    out = np.zeros((n, N_FEATURES), dtype=np.float32)
    if not n:
        return out
    out[:, :N_OWN] = own
    head, tail = np.zeros(n, dtype=bool), np.zeros(n, dtype=bool)
    filled = np.diff(first) > 0
    head[first[:-1][filled]] = True
    tail[first[1:][filled] - 1] = True
    out[1:, N_OWN : 2 * N_OWN] = own[:-1]
    out[head, N_OWN : 2 * N_OWN] = 0
    out[:-1, 2 * N_OWN : 3 * N_OWN] = own[1:]
    out[tail, 2 * N_OWN : 3 * N_OWN] = 0
    out[head, -2] = 1
    out[tail, -1] = 1
    return out


def marginals(unary: np.ndarray, stay: tuple[float, float, float], first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Posterior that each line is bad, and expected good-to-bad statistics, by forward-backward.

    ``unary`` is the bad-over-good log odds of each line from its features; ``stay`` holds the
    transition scores good-good, bad-bad and the score of either change.  All texts advance
    together, one line a step, longest texts first, so a step is a few array operations.
    Returns the posteriors and, for each of the three transitions, its expected count.
    """
    n = len(unary)
    lengths = np.diff(first)
    order = np.argsort(-lengths, kind="stable")
    starts, lengths = first[:-1][order], lengths[order]
    gg, bb, gb = stay
    f = np.zeros((n, 2))  # log forward sums of good, bad
    b = np.zeros((n, 2))
    longest = int(lengths[0]) if len(lengths) else 0
    alive = [int(np.searchsorted(-lengths, -t, side="left")) for t in range(longest + 1)]  # texts with more than t lines
    for t in range(longest):
        at = starts[: alive[t]] + t
        if t:
            p = f[at - 1]
            f[at, 0] = np.logaddexp(p[:, 0] + gg, p[:, 1] + gb)
            f[at, 1] = np.logaddexp(p[:, 0] + gb, p[:, 1] + bb) + unary[at]
        else:
            f[at, 1] = unary[at]
    for t in range(longest - 2, -1, -1):
        at = starts[: alive[t + 1]] + t
        q0, q1 = b[at + 1, 0], b[at + 1, 1] + unary[at + 1]
        b[at, 0] = np.logaddexp(q0 + gg, q1 + gb)
        b[at, 1] = np.logaddexp(q0 + gb, q1 + bb)
    z = np.logaddexp(f[:, 0] + b[:, 0], f[:, 1] + b[:, 1])
    bad = np.exp(f[:, 1] + b[:, 1] - z)
    inner = np.ones(n, dtype=bool)
    inner[first[:-1][np.diff(first) > 0]] = False
    at = np.flatnonzero(inner)
    if len(at):
        u, zz = unary[at], z[at]
        e = [np.exp(f[at - 1, 0] + gg + b[at, 0] - zz).sum(), np.exp(f[at - 1, 1] + bb + u + b[at, 1] - zz).sum()]
        e.append(len(at) - e[0] - e[1])
    else:
        e = [0.0, 0.0, 0.0]
    return bad, np.array(e)


@dataclass(frozen=True)
class Model:
    weights: np.ndarray
    stay: tuple[float, float, float]
    slope: float
    shift: float

    def bad_share(self, lines: Lines) -> np.ndarray:
        unary = with_neighbours(lines.own, lines.first) @ self.weights.astype(np.float32)
        bad, _ = marginals(unary.astype(np.float64), self.stay, lines.first)
        doc = np.repeat(np.arange(len(lines.first) - 1), np.diff(lines.first))
        n = len(lines.first) - 1
        total = np.bincount(doc, lines.length, minlength=n)
        return np.divide(np.bincount(doc, lines.length * bad, minlength=n), total, out=np.ones(n), where=total > 0)

    def score(self, share: np.ndarray) -> np.ndarray:
        return ln.sigmoid(self.slope * share + self.shift)


def _fit_chain(x: np.ndarray, y: np.ndarray, first: np.ndarray, weight: np.ndarray, steps: int, l2: float = 1e-3) -> tuple[np.ndarray, np.ndarray]:
    """Weights and transitions that raise the conditional likelihood of line labels ``y`` (1 bad)."""
    w, stay = np.zeros(x.shape[1]), np.zeros(3)
    inner = np.ones(len(y), dtype=bool)
    inner[first[:-1][np.diff(first) > 0]] = False
    at = np.flatnonzero(inner)
    seen = np.array([((y[at] == 0) & (y[at - 1] == 0)).sum(), ((y[at] == 1) & (y[at - 1] == 1)).sum(), (y[at] != y[at - 1]).sum()], dtype=float)
    m, v = np.zeros(len(w) + 3), np.zeros(len(w) + 3)
    scale = 1.0 / max(weight.sum(), 1)
    for t in range(1, steps + 1):
        bad, expected = marginals(x @ w, tuple(stay), first)
        g = np.concatenate([x.T @ ((bad - y) * weight) * scale + l2 * w, (expected - seen) / max(len(y), 1) + l2 * stay])
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        move = 0.15 * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
        w, stay = w - move[:-3], stay - move[-3:]
    return w, stay


def fit(docs: DataFrame, labels: DataFrame, per_class: int = SAMPLE_ROWS, steps: int = 80) -> Model:
    """Fit on at most ``per_class`` labelled documents of each class outside the held-out fold."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in tx.slices(batches, "text", SLICE_BYTES):
            lines = read_lines(batch.column("text"))
            cuts = lines.first.astype(np.int32)
            bins = lines.own.astype(np.float32)
            flat = pa.array(bins.ravel())
            yield pa.RecordBatch.from_arrays(
                [batch.column("label"), pa.ListArray.from_arrays(pa.array(cuts), pa.array(lines.length.astype(np.int32))), pa.ListArray.from_arrays(pa.array(cuts * N_OWN), flat)],
                names=["label", "lengths", "features"],
            )

    allowed = ln.fold("doc_id", FOLDS) != HELD
    table = ln.labelled_sample(docs, labels, "quality", allowed, per_class).mapInArrow(run, ROWS).toArrow()
    quality = table.column("label").to_numpy() if table.num_rows else np.empty(0)
    if not len(quality) or quality.min() == quality.max():
        return Model(np.zeros(N_FEATURES), (0.0, 0.0, 0.0), 0.0, 2.0)
    sizes = [np.asarray(v.values) for v in table.column("lengths")]
    first = np.concatenate([[0], np.cumsum([len(v) for v in sizes])])
    own = np.concatenate([np.asarray(v.values, dtype=np.float32) for v in table.column("features")]).reshape(-1, N_OWN)
    lines = Lines(first, np.concatenate(sizes).astype(float), own)
    x = with_neighbours(own, first).astype(np.float64)
    doc = np.repeat(np.arange(len(quality)), np.diff(first))
    y = (quality[doc] == 0).astype(float)
    # each document counts alike inside its class, each class alike
    weight = (ln.class_weights((quality == 0).astype(float)) / np.maximum(np.diff(first), 1))[doc]
    weight *= len(weight) / weight.sum()
    w, stay = _fit_chain(x, y, first, weight, steps)
    bad, _ = marginals(x @ w, tuple(stay), first)
    # in a bad document, lines well below its worst line and sure to be good are relabelled
    worst = np.zeros(len(quality))
    np.maximum.at(worst, doc, bad)
    y = np.where((y == 1) & (bad < 0.3) & (worst[doc] > 0.6), 0.0, y)
    w, stay = _fit_chain(x, y, first, weight, steps)
    model = Model(w, tuple(stay), 1.0, 0.0)
    slope, shift = ln.fit_platt(model.bad_share(lines), (quality > 0).astype(float))
    return Model(w, tuple(stay), slope, shift)


def score_quality(docs: DataFrame, model: Model) -> DataFrame:
    """``doc_id, n_lines, bad_share, score`` of each row of ``docs`` (``doc_id``, ``text``).

    A document without lines has a bad share of 1 and the score that goes with it.  Repeated rows
    are scored each; other columns are ignored.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in tx.slices(batches, "text", SLICE_BYTES):
            lines = read_lines(batch.column("text"))
            share = model.bad_share(lines)
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), pa.array(np.diff(lines.first).astype(np.int64)), pa.array(share), pa.array(model.score(share))],
                names=["doc_id", "n_lines", "bad_share", "score"],
            )

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(run, SCORES)


def drop_low_quality(docs: DataFrame, model: Model, at: float = PREDICT_AT) -> DataFrame:
    """Rows of ``docs`` whose score reaches ``at``; all columns kept, whatever their names, texts scored whole.

    Null and empty texts have the score of a text without lines; repeated rows are judged each and
    an empty table gives an empty result."""
    names = docs.columns
    rows = docs.toDF(*[f"c{k}" for k in range(len(names))])
    text = f"c{names.index('text')}"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in tx.slices(batches, text, SLICE_BYTES):
            good = model.score(model.bad_share(read_lines(batch.column(text)))) >= at
            yield batch.filter(pa.array(good))

    return rows.mapInArrow(run, rows.schema).toDF(*names)


def op7_line_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    scored = score_quality(docs, fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))
    return scored.select(
        "doc_id", (ln.fold("doc_id", FOLDS) == HELD).alias("held_out"), "score",
        (F.col("score") >= PREDICT_AT).cast("int").alias("predicted"), "n_lines", "bad_share",
    )
