"""Token counts by trie-shared dynamic programming over a unigram vocabulary.

The distinct pre-tokens of a batch are put into a trie; the best unigram score of every prefix is
computed once at its node, from its ancestors, whatever number of pre-tokens share it.  Terminal
nodes hold the number of pieces of the best segmentation, and a text's count is the sum over its
pre-tokens.
"""

from __future__ import annotations

import re
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from levelgraph.llm import text as tx

MARK = "▁"
CACHE_WORDS = 500_000
COUNTS = "doc_id long, n_pretokens long, n_tokens long"
_SPLIT = re.compile(r"[^\x20\x09-\x0D]+")


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def load_vocabulary(path: str) -> dict[str, float]:
    """Pieces with unigram log scores: a piece at rank r of the file weighs like 1 / (r + 2)."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    out: dict[str, float] = {}
    for i in range(model.get_piece_size()):
        if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i)):
            out[model.id_to_piece(i)] = -float(np.log(i + 2.0))
    return out


class TrieCounter:
    """Counts pieces of pre-tokens; keeps the counts of a bounded number of them."""

    def __init__(self, vocabulary: dict[str, float], limit: int = CACHE_WORDS):
        self.vocabulary, self.limit = vocabulary, limit
        self.longest = max(map(len, vocabulary), default=1)
        # a character outside the vocabulary falls back to its bytes, each scored below every piece
        self.byte = min(vocabulary.values(), default=0.0) - 10.0
        self.cache: dict[str, int] = {}

    def _extend(self, text: str, k: int, score: list[float], count: list[int]) -> None:
        """Forward score and piece count of the prefix of ``k + 1`` characters, from shorter ones."""
        get, end = self.vocabulary.get, k + 1
        n = len(text[k].encode("utf-8", "surrogatepass"))
        best, pieces = score[k] + n * self.byte, count[k] + n
        for begin in range(max(0, end - self.longest), end):
            value = get(text[begin:end])
            if value is not None:
                total = score[begin] + value
                if total > best or (total == best and count[begin] + 1 < pieces):
                    best, pieces = total, count[begin] + 1
        score.append(best)
        count.append(pieces)

    def insert(self, words: Iterable[str]) -> None:
        """Walk the trie of ``words``, each with the space mark before it, depth first.

        In sorted order only the branch to the last node has to be held; a node that two words
        share is on both branches and is scored once.
        """
        score, count, last = [0.0], [0], ""
        for word in sorted(words):
            marked = MARK + word
            shared, most = 0, min(len(last), len(marked))
            while shared < most and last[shared] == marked[shared]:
                shared += 1
            del score[shared + 1 :], count[shared + 1 :]
            for k in range(shared, len(marked)):
                self._extend(marked, k, score, count)
            self.cache[word] = count[-1]
            last = marked

    def counts(self, texts: Iterable[str | None]) -> tuple[list[int], list[int]]:
        split = [_SPLIT.findall(t) if t else [] for t in texts]
        fresh = {w for ws in split for w in ws if w not in self.cache}
        if len(self.cache) + len(fresh) > self.limit:
            self.cache.clear()
            fresh = {w for ws in split for w in ws}
        self.insert(fresh)
        get = self.cache.__getitem__
        return [len(ws) for ws in split], [sum(map(get, ws)) for ws in split]


def count_tokens(docs: DataFrame, vocabulary_path: str | None = None) -> DataFrame:
    """``doc_id, n_pretokens, n_tokens`` of each row of ``docs``; null and empty texts count 0.

    Repeated rows are counted each; other columns are ignored.
    """
    path = vocabulary_path or default_vocabulary()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = _counter(path)
        for batch in tx.slices(batches, "text"):
            words, pieces = counter.counts(batch.column("text").to_pylist())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(words, pa.int64()), pa.array(pieces, pa.int64())], names=["doc_id", "n_pretokens", "n_tokens"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(run, COUNTS)


_counters: dict[str, TrieCounter] = {}


def _counter(path: str) -> TrieCounter:
    if path not in _counters:
        _counters[path] = TrieCounter(load_vocabulary(path))
    return _counters[path]


def op4_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return count_tokens(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
