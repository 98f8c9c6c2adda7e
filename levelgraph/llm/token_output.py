"""Token ids of whole texts, written as seekable zstandard shards in ascending id order.

The tokenizer works word by word: text without white space inside is encoded once per process
and kept, as the tokenizer's own rules never join text across white space.  Texts outside the
range where that is certain are encoded whole.
"""

from __future__ import annotations

import os
import re
import uuid
import zlib
from array import array
from collections.abc import Iterator
from pathlib import PurePosixPath

import numpy as np
import pyarrow as pa
import regex
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from levelgraph.llm.token_file import ShardReader, ShardWriter
from levelgraph.runtime import materialize, new_path

END_ID = 2
CACHE_WORDS = 400_000
MANIFEST = "shard int, path string, n_docs long, n_ids long"
TOKENS = "shard int, pos long, doc_id long, n_tokens long, ids_crc32 long"


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


class WordEncoder:
    """Ids of whole texts as little-endian 32-bit bytes, with a bounded store of encoded words.

    Texts inside Latin-1 are cut at white space and each new word into the pre-tokens of the
    tokenizer's own rule, whose ids come from its model; a probe at the start holds this against
    the whole tokenizer.  The store has two halves: when the newer one is full it becomes the
    older one, and words that are met again move over, so common words are never encoded twice.
    """

    ODD = re.compile("[\x1c-\x1f]")
    PIECES = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+")
    PROBE = "It's a PROBE, 12 times: we'll, don't! (é ÀÉß) x--y\t½²ª µ×÷ «q» \xa0a\x85b\n"

    def __init__(self, path: str, cache_words: int = CACHE_WORDS):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.model = self.tokenizer.model
        self.half = max(1, cache_words // 2)
        self.cache: dict[str, bytes] = {}
        self.older: dict[str, bytes] = {}
        # characters that stand for bytes in a byte-level vocabulary: printable ones for themselves, the others from 256 on
        plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
        self.bytes = dict(zip((b for b in range(256) if b not in plain), range(256, 512), strict=False))
        self.by_words = True
        self.by_words = self._by_words(self.PROBE) == self._pack(self.PROBE)
        self.cache.clear()

    def _pack(self, text: str) -> bytes:
        return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, dtype="<u4").tobytes()

    def _piece(self, piece: str) -> bytes:
        if not (piece.isascii() and piece.isprintable()):
            piece = piece.encode().decode("latin-1").translate(self.bytes)
        return array("I", [t.id for t in self.model.tokenize(piece)]).tobytes()

    def _word(self, word: str) -> bytes:
        if word.isalpha():
            return self._piece(word)
        cache, out, body = self.cache, [], word[:-1]
        for p in (body, word[-1]) if body.isalpha() and word[-1] in ".,!?" else self.PIECES.findall(word):
            ids = cache.get(p)
            if ids is None:
                ids = self.older.get(p)
                cache[p] = ids = self._piece(p) if ids is None else ids
            out.append(ids)
        return b"".join(out)

    def _by_words(self, text: str) -> bytes:
        words = text.lower().split()
        cache, older = self.cache, self.older
        for w in set(words).difference(cache):
            known = older.get(w)
            cache[w] = self._word(w) if known is None else known
        out = b"".join(map(cache.__getitem__, words))
        if len(cache) > self.half:
            self.older, self.cache = cache, {}
        return out

    def encode(self, text: str) -> bytes:
        if not text.isascii():
            try:
                text.encode("latin-1")
            except UnicodeEncodeError:
                return self._pack(text)
        if not self.by_words or "<|" in text or self.ODD.search(text):
            return self._pack(text)
        return self._by_words(text)


_encoders: dict[str, WordEncoder] = {}


def encoder(path: str) -> WordEncoder:
    if path not in _encoders:
        _encoders[path] = WordEncoder(path)
    return _encoders[path]


def open_folder(uri: str) -> tuple[fs.FileSystem, str]:
    """File system and path of a folder in shared storage."""
    return fs.FileSystem.from_uri(uri)


def write_tokens(docs: DataFrame, folder: str, tokenizer_path: str | None = None, end_id: int = END_ID, frame_bytes: int | None = None) -> DataFrame:
    """Encode ``docs`` and write shards below ``folder``; returns the manifest.

    Documents are range-partitioned on their id, so shards and the documents in them ascend;
    null ids come first, repeated ids stay next to each other, null texts count as empty.
    An attempt writes under a name of its own and only the rows of successful attempts reach
    the manifest, so lost executors and retried tasks leave no half-written shard in it.
    """
    path = tokenizer_path or default_tokenizer()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        shard = TaskContext.get().partitionId()
        code, end = encoder(path), np.array([end_id], dtype="<u4").tobytes()
        system, base = open_folder(folder)
        writer = sink = None
        n_docs = n_ids = 0
        for batch in batches:
            for doc_id, text in zip(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist(), strict=True):
                if writer is None:
                    system.create_dir(base, recursive=True)
                    name = str(PurePosixPath(base, f"shard-{shard:06d}-{uuid.uuid4().hex}.ids.zst"))
                    sink = system.open_output_stream(name, compression=None)
                    writer = ShardWriter(sink, **({"frame_bytes": frame_bytes} if frame_bytes else {}))
                ids = code.encode(text or "") + end
                writer.add(doc_id, ids)
                n_docs += 1
                n_ids += len(ids) // 4
        if writer is not None:
            writer.close()
            sink.close()
            yield pa.RecordBatch.from_pydict(
                {"shard": pa.array([shard], pa.int32()), "path": [name], "n_docs": [n_docs], "n_ids": [n_ids]}
            )

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    dealt = rows.repartitionByRange("doc_id", F.xxhash64("text")).sortWithinPartitions("doc_id", F.xxhash64("text"))
    return materialize(dealt.mapInArrow(run, MANIFEST), "token_manifest")


def read_tokens(manifest: DataFrame, folder: str) -> DataFrame:
    """Read every shard of a manifest back: number, checksum and global start of each document's ids."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        system, _ = open_folder(folder)
        for batch in batches:
            for shard, path in zip(batch.column("shard").to_pylist(), batch.column("path").to_pylist(), strict=True):
                with system.open_input_file(path) as source:
                    ids, counts, crcs = [], [], []
                    for doc_id, tokens in ShardReader(source).scan():
                        ids.append(doc_id)
                        counts.append(len(tokens))
                        crcs.append(zlib.crc32(tokens.tobytes()))
                start = np.cumsum(counts) - counts
                yield pa.RecordBatch.from_arrays(
                    [pa.array(np.full(len(ids), shard, np.int32)), pa.array(start, pa.int64()), pa.array(ids, pa.int64()), pa.array(counts, pa.int64()), pa.array(crcs, pa.int64())],
                    names=["shard", "pos", "doc_id", "n_tokens", "ids_crc32"],
                )

    before = Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    bases = manifest.select("shard", F.coalesce(F.sum("n_ids").over(before), F.lit(0)).alias("base"))  # a row for each shard
    shards = max(1, manifest.count())
    rows = manifest.select("shard", "path").repartition(shards).mapInArrow(run, TOKENS)
    return rows.join(F.broadcast(bases), "shard").select(
        "doc_id", (F.col("base") + F.col("pos")).alias("start"), "n_tokens", "ids_crc32"
    )


def token_table(docs: DataFrame, folder: str | None = None, **options) -> DataFrame:
    """Write the shards of ``docs`` and return what reading them back gives."""
    folder = folder or new_path(docs.sparkSession, "token_ids")
    return read_tokens(write_tokens(docs, folder, **options), folder)


def op3_token_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_table(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
