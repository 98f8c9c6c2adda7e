"""Small pieces shared by the classifiers: labelled samples, logistic fits, calibration."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SAMPLE_ROWS = 3000


def fold(column: str, folds: int) -> Column:
    """Remainder of the crc32 of an id as text; null ids fall in fold 0."""
    return F.coalesce(F.crc32(F.col(column).cast("long").cast("string")) % folds, F.lit(0).cast("long"))


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, allowed: Column, per_class: int = SAMPLE_ROWS) -> DataFrame:
    """At most ``per_class`` labelled documents of each class as ``doc_id, text, label``.

    The rows are the first by a hash of their id among those that ``allowed`` (over ``doc_id``)
    lets in, so the sample does not depend on the order or the layout of the tables.
    """
    rows = labels.select(F.col("doc_id").cast("long").alias("doc_id"), (F.col(label) > 0).cast("int").alias("label")).where("doc_id is not null and label is not null")
    rows = rows.where(allowed).groupBy("doc_id").agg(F.max("label").alias("label"))
    picked = [rows.where(F.col("label") == k).orderBy(F.xxhash64(F.lit(5), "doc_id"), "doc_id").limit(per_class) for k in (0, 1)]
    body = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).where("text is not null")
    # at most 2 * per_class ids and classes
    return body.join(F.broadcast(picked[0].union(picked[1])), "doc_id")


def sigmoid(z: np.ndarray) -> np.ndarray:
    return 1.0 / (1.0 + np.exp(-np.clip(z, -35, 35)))


def class_weights(y: np.ndarray) -> np.ndarray:
    """Weights that give both classes the same total."""
    n1 = max(int(y.sum()), 1)
    n0 = max(len(y) - n1, 1)
    return np.where(y > 0, len(y) / (2.0 * n1), len(y) / (2.0 * n0))


class Sparse:
    """Rows of (column, value) pairs with the two products that a fit needs."""

    def __init__(self, rows: list[tuple[np.ndarray, np.ndarray]], n_columns: int):
        self.n_columns = n_columns
        self.row = np.repeat(np.arange(len(rows)), [len(c) for c, _ in rows])
        self.column = np.concatenate([np.empty(0, np.int64), *(c for c, _ in rows)]).astype(np.int64)
        self.value = np.concatenate([np.empty(0), *(v for _, v in rows)]).astype(np.float64)
        self.n_rows = len(rows)

    def dot(self, w: np.ndarray) -> np.ndarray:
        return np.bincount(self.row, w[self.column] * self.value, minlength=self.n_rows)

    def dot_t(self, g: np.ndarray) -> np.ndarray:
        return np.bincount(self.column, g[self.row] * self.value, minlength=self.n_columns)


def fit_logistic(x: Sparse, y: np.ndarray, l2: float = 1e-4, steps: int = 200, rate: float = 0.2, pairs: Sparse | None = None, pair_penalty: float = 0.0, sample_weight: np.ndarray | None = None) -> tuple[np.ndarray, float]:
    """Weights and intercept by full-batch Adam on the class-balanced loss.

    ``sample_weight`` scales single rows inside their class.  ``pairs`` holds differences of feature rows whose scores should not change; their mean squared
    score change times ``pair_penalty`` is added to the loss.
    """
    w, b = np.zeros(x.n_columns), 0.0
    m, v, mb, vb = np.zeros_like(w), np.zeros_like(w), 0.0, 0.0
    weight = class_weights(y) / max(len(y), 1)
    if sample_weight is not None:
        of = y > 0
        total = np.where(of, sample_weight[of].sum() / max(of.sum(), 1), sample_weight[~of].sum() / max((~of).sum(), 1))
        weight = weight * sample_weight / np.maximum(total, 1e-12)
    for t in range(1, steps + 1):
        err = (sigmoid(x.dot(w) + b) - y) * weight
        g, gb = x.dot_t(err) + l2 * w, float(err.sum())
        if pairs is not None and pairs.n_rows:
            g = g + pairs.dot_t(pairs.dot(w)) * (2.0 * pair_penalty / pairs.n_rows)
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        mb, vb = 0.9 * mb + 0.1 * gb, 0.999 * vb + 0.001 * gb * gb
        c1, c2 = 1 - 0.9**t, 1 - 0.999**t
        w -= rate * (m / c1) / (np.sqrt(v / c2) + 1e-8)
        b -= rate * (mb / c1) / (np.sqrt(vb / c2) + 1e-8)
    return w, b


def fit_platt(z: np.ndarray, y: np.ndarray, steps: int = 60) -> tuple[float, float]:
    """Slope and intercept that turn a raw score into a probability (Newton steps, smoothed targets)."""
    n1, n0 = float(y.sum()), float(len(y) - y.sum())
    if not n1 or not n0:
        return 1.0, 0.0
    target = np.where(y > 0, (n1 + 1) / (n1 + 2), 1 / (n0 + 2))
    mid, spread = float(z.mean()), float(z.std()) or 1.0
    x = (z - mid) / spread

    def loss(a: float, b: float) -> float:
        t = a * x + b
        return float((np.logaddexp(0, t) - target * t).sum()) + 5e-4 * a * a

    a, b = 1.0, 0.0
    for _ in range(steps):
        p = sigmoid(a * x + b)
        d, r = p - target, np.maximum(p * (1 - p), 1e-9)
        ga, gb = float((d * x).sum()) + 1e-3 * a, float(d.sum())
        haa, hab, hbb = float((r * x * x).sum()) + 1e-3, float((r * x).sum()), float(r.sum()) + 1e-9
        det = haa * hbb - hab * hab
        if det <= 1e-12:
            break
        da, db, scale, now = (hbb * ga - hab * gb) / det, (haa * gb - hab * ga) / det, 1.0, loss(a, b)
        while scale > 1e-4 and loss(a - scale * da, b - scale * db) > now:
            scale /= 2
        a, b = a - scale * da, b - scale * db
        if scale <= 1e-4 or max(abs(da), abs(db)) < 1e-7:
            break
    return a / spread, b - a * mid / spread
