"""Toxicity by a counterfactually regularised classifier.

Features are lower-cased words and their first bytes, each at three levels: present, there twice or
more, and there at least once in a hundred words.  A logistic regression on the telling ones is
fitted to labelled documents and, beside them, to labelled sentences in which groups of people are
named: a sentence that names one is taken as it is, others get a name put in.  A penalty on pairs
(a sentence and the same with its name swapped for another one, or taken out) keeps their scores
together, so that naming a group does not make a text toxic.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from levelgraph.llm import learning as ln
from levelgraph.llm import text as tx
from levelgraph.runtime import discard, materialize

PREDICT_AT = 0.7
FOLDS, HELD = 3, 1
SAMPLE_ROWS = 3000
MAX_FEATURES = 20000
PREFIXES = (3, 4, 5, 6, 7)
PAIR_PENALTY = 5.0
MENTION_WEIGHT = 0.25
# likelihood ratio from which a feature is used; a third of it where a class has less than a hundred rows
LEAST_RATIO = 20.0
CALIBRATION_FOLDS = 5
BEND = 3.0
LEVELS = 3
# sentences of a sampled document that may be shown with a group's name, and their characters at most
SENTENCES, SENTENCE_CHARS = 4, 400

# Terms that name groups of people; a term is swapped for others of its line.
IDENTITY_TERMS = (
    ("women", "men", "girls", "boys", "lesbians", "transgender"),
    ("woman", "man", "girl", "boy"),
    ("muslims", "christians", "jews", "hindus", "buddhists", "atheists"),
    ("black", "white", "asian", "african", "american", "european", "mexican"),
    ("gay", "straight", "disabled", "elderly", "young"),
    ("immigrants", "refugees"),
    ("frauen", "männer", "muslime", "juden"),
    ("femmes", "hommes", "musulmans", "juifs"),
    ("mujeres", "hombres", "musulmanes", "judíos"),
)
_TERM_LINE = {t: line for line in IDENTITY_TERMS for t in line}
_TERM = re.compile(r"(?i)\b(?:" + "|".join(_TERM_LINE) + r")\b")
_SENTENCE = re.compile(r"[^.!?\n]*\w[^.!?\n]*")

_LETTER = np.zeros(256, dtype=bool)
_LETTER[[*range(48, 58), *range(65, 91), *range(97, 123), *range(0x80, 0x100)]] = True
ROWS = "doc_id long, label int, m1 long, m2 long, features array<long>, counts array<int>, n_words int, sentences array<string>"
SCORES = "doc_id long, score double"


def word_features(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Feature hash of every word and word prefix, with the text it stands in (unsorted, repeated), and each text's words."""
    data, offsets = tx.buffers(texts)
    data = tx.LOWER[data]
    starts, ends, first = tx.limits(_LETTER[data], offsets)
    doc = np.repeat(np.arange(len(offsets) - 1), np.diff(first))
    out, of = [tx.span_hashes(data, starts, ends)], [doc]
    for k in PREFIXES:
        long = np.flatnonzero(ends - starts > k)
        out.append(tx.mix(tx.span_hashes(data, starts[long], starts[long] + k) + np.uint64(k)))
        of.append(doc[long])
    return np.concatenate(out), np.concatenate(of), np.diff(first)


def _counted(h: np.ndarray, doc: np.ndarray, n: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """Distinct feature hashes of each of ``n`` texts, sorted, with how often they occur."""
    order = np.argsort(doc, kind="stable")
    cuts = np.searchsorted(doc[order], np.arange(n + 1))
    h = h[order]
    return [np.unique(h[cuts[i] : cuts[i + 1]], return_counts=True) for i in range(n)]


def _levels(count: np.ndarray, n_words: np.ndarray | int) -> tuple[np.ndarray, np.ndarray]:
    """Which features are there twice or more, and which of those in one of a hundred words."""
    twice = count >= 2
    return twice, twice & (100 * count >= n_words)


def columns_of(features: np.ndarray, h: np.ndarray, count: np.ndarray, n_words: int) -> np.ndarray:
    """Model columns of one text: ``LEVELS`` for each known feature."""
    if not len(features):
        return np.empty(0, np.int64)
    at = np.minimum(np.searchsorted(features, h), len(features) - 1)
    known = features[at] == h
    at, count = at[known].astype(np.int64), count[known]
    twice, dense = _levels(count, n_words)
    return np.sort(np.concatenate([at * LEVELS, at[twice] * LEVELS + 1, at[dense] * LEVELS + 2]))


@dataclass(frozen=True)
class Model:
    features: np.ndarray  # sorted hashes
    weights: np.ndarray  # LEVELS for each feature
    bias: float
    slope: float
    shift: float

    def score(self, texts: pa.Array) -> np.ndarray:
        z = np.full(len(texts), self.bias)
        if len(self.features):
            h, doc, n_words = word_features(texts)
            mask = np.zeros(1 << 20, dtype=bool)
            mask[(self.features >> np.uint64(44)).astype(np.int64)] = True
            maybe = mask[(h >> np.uint64(44)).astype(np.int64)]
            h, doc = h[maybe], doc[maybe]
            at = np.minimum(np.searchsorted(self.features, h), len(self.features) - 1)
            hit = self.features[at] == h
            both, count = np.unique(doc[hit] * np.int64(len(self.features)) + at[hit], return_counts=True)
            doc, at = np.divmod(both, len(self.features))
            twice, dense = _levels(count, n_words[doc])
            w = self.weights.reshape(-1, LEVELS)[at]
            np.add.at(z, doc, w[:, 0] + twice * w[:, 1] + dense * w[:, 2])
        return ln.sigmoid(self.slope * _bent(z) + self.shift)


def _sentences(text: str, doc_id: int) -> list[str]:
    """At most ``SENTENCES`` of the sentences of a text, chosen by a hash; long ones are left out."""
    found = [s.strip() for s in dict.fromkeys(_SENTENCE.findall(text)) if len(s) <= SENTENCE_CHARS]
    return sorted(found, key=lambda s: (zlib.crc32(f"{doc_id}:{s}".encode("utf-8", "surrogatepass")), s))[:SENTENCES]


def _sample(docs: DataFrame, labels: DataFrame, per_class: int) -> DataFrame:
    """Features of the labelled sample; of texts that are near copies of one another the first by id stays."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in tx.slices(batches, "text"):
            h, doc, n_words = word_features(batch.column("text"))
            sets = _counted(h, doc, batch.num_rows)
            w = tx.words(batch.column("text"), lower=True)
            win, at = tx.window_hashes(w.hashes(), w.first, 3)
            cut = np.searchsorted(at, w.first)
            low = np.zeros((batch.num_rows, 2), dtype=np.uint64)
            for i in range(batch.num_rows):
                part, own = win[cut[i] : cut[i + 1]], sets[i][0]
                part = part if len(part) else np.array([np.bitwise_xor.reduce(own) if len(own) else 0], dtype=np.uint64)
                low[i] = part.min(), tx.mix(part).min()
            said = [_sentences(t, i) for t, i in zip(batch.column("text").to_pylist(), batch.column("doc_id").to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column("doc_id"), batch.column("label"), pa.array(low[:, 0].copy().view(np.int64)), pa.array(low[:, 1].copy().view(np.int64)),
                    pa.array([s.view(np.int64) for s, _ in sets], pa.list_(pa.int64())), pa.array([c.astype(np.int32) for _, c in sets], pa.list_(pa.int32())),
                    pa.array(n_words.astype(np.int32)), pa.array(said, pa.list_(pa.string())),
                ],
                names=["doc_id", "label", "m1", "m2", "features", "counts", "n_words", "sentences"],
            )

    sample = ln.labelled_sample(docs, labels, "toxic", ln.fold("doc_id", FOLDS) != HELD, per_class)
    rows = sample.select("doc_id", "text", "label").mapInArrow(run, ROWS)
    row = F.struct("doc_id", "m1", "m2", "n_words", "features", "counts", "sentences")
    for key in ("m1", "m2"):
        rows = rows.groupBy("label", F.col(key).alias("_key")).agg(F.min(row).alias("r")).select("label", "r.*")
    return materialize(rows, "toxic_sample")


def fit(
    docs: DataFrame, labels: DataFrame, per_class: int = SAMPLE_ROWS, max_features: int = MAX_FEATURES, pair_penalty: float = PAIR_PENALTY, mention_weight: float = MENTION_WEIGHT,
) -> Model:
    """Fit on at most ``per_class`` labelled documents of each class outside the held-out fold.

    ``mention_weight`` is what a sentence that names a group weighs beside a document (0 leaves
    them out); ``pair_penalty`` is the weight of the squared score changes under swaps.  The same
    rows give the same model however they are laid out.
    """
    sample = _sample(docs, labels, per_class)
    n = {r["label"]: r["n"] for r in sample.groupBy("label").agg(F.count("*").alias("n")).collect()}
    if len(n) < 2:
        discard(sample)
        return Model(np.empty(0, np.uint64), np.empty(0), 0.0, 1.0, -2.0 if n.get(0) or not n else 2.0)
    counts = sample.select("label", F.explode("features").alias("f")).groupBy("f").agg(F.sum("label").alias("t"), F.count("*").alias("n"))
    lift = F.log((F.col("t") + 0.5) / (n[1] + 1.0)) - F.log((F.col("n") - F.col("t") + 0.5) / (n[0] + 1.0))
    # likelihood ratio of the feature's classes against those of the sample
    part = lambda seen, share: F.when(seen > 0, seen * F.log(seen / (F.col("n") * share))).otherwise(0.0)
    ratio = 2 * (part(F.col("t"), n[1] / (n[0] + n[1])) + part(F.col("n") - F.col("t"), n[0] / (n[0] + n[1])))
    told = counts.withColumns({"lift": lift, "ratio": F.round(ratio, 9)}).where(F.col("ratio") >= (LEAST_RATIO if min(n.values()) >= 100 else LEAST_RATIO / 3))
    told = told.orderBy(F.desc("ratio"), "f").limit(max_features)
    told = {r["f"]: r["lift"] for r in told.select("f", "lift").collect()}
    terms = np.unique(word_features(pa.array(list(_TERM_LINE)))[0])
    features = np.unique(np.concatenate([np.array(list(told), dtype=np.int64).view(np.uint64), terms]))
    toxic_signs = np.sort(np.array([f for f, x in told.items() if x > 0], dtype=np.int64).view(np.uint64))
    chosen = sample.mapInArrow(_restrict(features), "doc_id long, label int, columns array<int>, sentences array<string>").toArrow()
    discard(sample)
    every = sorted(zip(*(chosen.column(c).to_pylist() for c in ("doc_id", "label", "columns", "sentences")), strict=True))
    y = np.array([label for _, label, _, _ in every], dtype=float)
    rows = [np.array(c, dtype=np.int64) for _, _, c, _ in every]
    said = counterfactuals([(i, int(label), s) for i, label, _, s in every], features, toxic_signs)

    def trained(rows_in: np.ndarray) -> tuple[np.ndarray, float]:
        named = [x for x in said if rows_in[x[0]]]
        pairs = [p for _, _, ps in named for p in ps]
        named = named if mention_weight > 0 else []
        x = [_one(r) for r, ok in zip(rows, rows_in, strict=True) if ok] + [_one(c) for _, c, _ in named]
        weight = np.concatenate([np.ones(int(rows_in.sum())), np.full(len(named), mention_weight)])
        size = len(features) * LEVELS
        return ln.fit_logistic(
            ln.Sparse(x, size), np.concatenate([y[rows_in], y[[i for i, _, _ in named]]]), l2=5e-5, steps=300, rate=0.1,
            pairs=ln.Sparse(pairs, size), pair_penalty=pair_penalty, sample_weight=weight,
        )

    w, b = trained(np.ones(len(y), dtype=bool))
    # raw scores of rows that a model has not seen, to calibrate with
    z, fold = np.zeros(len(y)), np.arange(len(y)) % CALIBRATION_FOLDS
    for k in range(CALIBRATION_FOLDS):
        seen = fold != k
        wk, bk = trained(seen) if len(y) >= 300 and len({*y[seen]}) == 2 else (w, b)
        z[~seen] = ln.Sparse([_one(r) for r, ok in zip(rows, ~seen, strict=True) if ok], len(features) * LEVELS).dot(wk) + bk
    slope, shift = ln.fit_platt(_bent(z), y)
    return Model(features, w, b, slope, shift)


def _one(columns: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    return columns, np.ones(len(columns))


def _bent(z: np.ndarray) -> np.ndarray:
    """Raw scores in (-BEND, BEND): far ones all say the same, and must not flatten the calibration."""
    return z / (1 + np.abs(z) / BEND)


def _restrict(features: np.ndarray):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            h, count, n_words = batch.column("features"), batch.column("counts"), batch.column("n_words").to_pylist()
            out = [columns_of(features, np.asarray(h[k].values).view(np.uint64), np.asarray(count[k].values), n_words[k]).astype(np.int32) for k in range(batch.num_rows)]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("label"), pa.array(out, pa.list_(pa.int32())), batch.column("sentences")], names=["doc_id", "label", "columns", "sentences"])

    return run


def swapped(sentence: str, turn: int) -> list[tuple[str, str]]:
    """Pairs of texts that differ in a group's name only; the first text of the first pair names one.

    A sentence that names a group is paired with itself under another name of the same line; one
    that names none gets a name at a place given by ``turn``, and is paired with that too."""
    named = _TERM.search(sentence)
    if named:
        line = _TERM_LINE[named.group().lower()]
        other = line[(line.index(named.group().lower()) + 1 + turn % (len(line) - 1)) % len(line)]
        return [(sentence, sentence[: named.start()] + other + sentence[named.end() :])]
    words, line = sentence.split(), IDENTITY_TERMS[turn % len(IDENTITY_TERMS)]
    at, k = (turn >> 8) % (len(words) + 1), (turn >> 16) % len(line)
    put = lambda term: " ".join([*words[:at], term, *words[at:]])
    return [(put(line[k]), put(line[(k + 1) % len(line)])), (put(line[k]), sentence)]


def counterfactuals(every: list[tuple[int, int, list[str]]], features: np.ndarray, toxic_signs: np.ndarray) -> list[tuple[int, np.ndarray, list[tuple[np.ndarray, np.ndarray]]]]:
    """Of each document ``(id, label, sentences)`` a sentence that names a group, and pairs that should score alike.

    Any sentence of a clean document will do; of a toxic one the one with most signs of toxicity is
    taken, which its label then fits, and none where no sentence has a sign.  Returns the place in
    ``every``, the columns of the sentence, and feature differences of its pairs."""
    flat = [s for _, _, sentences in every for s in sentences]
    h, doc, _ = word_features(pa.array(flat, pa.string()))
    signs = np.bincount(doc[np.isin(h, toxic_signs)], minlength=len(flat))
    texts, places, at = [], [], 0
    for k, (doc_id, label, sentences) in enumerate(every):
        here, at = signs[at : at + len(sentences)], at + len(sentences)
        if not sentences or (label and not here.max()):
            continue
        sentence = sentences[int(here.argmax()) if label else 0]
        pairs = swapped(sentence, zlib.crc32(f"{doc_id}:{sentence}".encode("utf-8", "surrogatepass")))
        places.append((k, len(texts), len(pairs)))
        texts += [t for pair in pairs for t in pair]
    h, doc, n_words = word_features(pa.array(texts, pa.string()))
    columns = [columns_of(features, *x, n) for x, n in zip(_counted(h, doc, len(texts)), n_words, strict=True)]
    out = []
    for k, start, n in places:
        pairs = []
        for j in range(start, start + 2 * n, 2):
            came, gone = np.setdiff1d(columns[j], columns[j + 1]), np.setdiff1d(columns[j + 1], columns[j])
            pairs.append((np.concatenate([came, gone]), np.concatenate([np.ones(len(came)), -np.ones(len(gone))])))
        out.append((k, columns[start], pairs))
    return out


def score_toxicity(docs: DataFrame, model: Model) -> DataFrame:
    """``doc_id, score`` of each row of ``docs``; null and empty texts get the score of no words.

    Repeated rows are scored each; other columns are ignored.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in tx.slices(batches, "text"):
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(model.score(batch.column("text")))], names=["doc_id", "score"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(run, SCORES)


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    scored = score_toxicity(docs, fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))
    return scored.select(
        "doc_id", (ln.fold("doc_id", FOLDS) == HELD).alias("held_out"), "score",
        (F.col("score") >= PREDICT_AT).cast("int").alias("predicted"),
    )
