"""Token-id shards: independent zstandard frames with a trailing seek table.

Layout of a shard, every integer little-endian:

* zstandard frames, each the 32-bit ids of some whole consecutive documents;
* a skippable frame with the directory: for each document its id, whether that id is null,
  the frame it lies in and its number of ids;
* a skippable frame with the seek table of the public seekable format: compressed size,
  plain size and checksum (low half of XXH64 of the plain bytes) of each frame, then a footer.

Any zstandard decoder reads the frames in order and skips the rest.  A reader that wants some
documents reads both tables and decompresses the frames that hold them, nothing else.
"""

from __future__ import annotations

import struct
from collections.abc import Iterable, Iterator

import numpy as np
import xxhash
import zstandard

# fixed values of the public seekable format
SKIPPABLE_DIRECTORY = 0x184D2A50
SKIPPABLE_SEEK = 0x184D2A5E
SEEKABLE_MAGIC = 0x8F92EAB1
CHECKSUM_FLAG = 0x80

FRAME_BYTES = 1 << 18
_ENTRY = np.dtype([("packed", "<u4"), ("plain", "<u4"), ("check", "<u4")])
_DOCUMENT = np.dtype([("doc_id", "<i8"), ("null", "u1"), ("frame", "<u4"), ("n_ids", "<u4")])


class ShardWriter:
    """Appends documents to a shard; holds one frame in memory."""

    def __init__(self, sink, level: int = 1, frame_bytes: int = FRAME_BYTES):
        self.sink, self.frame_bytes = sink, frame_bytes
        self.codec = zstandard.ZstdCompressor(level=level, write_checksum=True, write_content_size=True)
        self.parts: list[bytes] = []
        self.size = 0
        self.entries: list[tuple[int, int, int]] = []
        self.documents: list[tuple[int, int, int, int]] = []

    def add(self, doc_id: int | None, ids: bytes) -> None:
        if self.size and self.size + len(ids) > self.frame_bytes:
            self._flush()
        self.documents.append((doc_id or 0, doc_id is None, len(self.entries), len(ids) // 4))
        self.parts.append(ids)
        self.size += len(ids)

    def _flush(self) -> None:
        plain = b"".join(self.parts)
        packed = self.codec.compress(plain)
        self.sink.write(packed)
        self.entries.append((len(packed), len(plain), xxhash.xxh64_intdigest(plain) & 0xFFFFFFFF))
        self.parts, self.size = [], 0

    def close(self) -> None:
        if self.parts:
            self._flush()
        table = zstandard.ZstdCompressor(level=3).compress(np.array(self.documents, dtype=_DOCUMENT).tobytes())
        self.sink.write(struct.pack("<II", SKIPPABLE_DIRECTORY, len(table)) + table)
        seek = np.array(self.entries, dtype=_ENTRY).tobytes()
        self.sink.write(struct.pack("<II", SKIPPABLE_SEEK, len(seek) + 9) + seek + struct.pack("<IBI", len(self.entries), CHECKSUM_FLAG, SEEKABLE_MAGIC))


class ShardReader:
    """Random access to a shard given a seekable file."""

    def __init__(self, source):
        self.source = source
        end = source.seek(0, 2)
        source.seek(end - 9)
        n, flag, magic = struct.unpack("<IBI", source.read(9))
        if magic != SEEKABLE_MAGIC or not flag & CHECKSUM_FLAG:
            raise ValueError("no seek table with checksums at the end of this file")
        at = end - 17 - n * _ENTRY.itemsize
        source.seek(at)
        kind, size = struct.unpack("<II", source.read(8))
        if kind != SKIPPABLE_SEEK or size != n * _ENTRY.itemsize + 9:
            raise ValueError("damaged seek table")
        self.entries = np.frombuffer(source.read(n * _ENTRY.itemsize), dtype=_ENTRY)
        self.at = np.concatenate([[0], np.cumsum(self.entries["packed"].astype(np.int64))])
        source.seek(int(self.at[-1]))
        kind, size = struct.unpack("<II", source.read(8))
        if kind != SKIPPABLE_DIRECTORY:
            raise ValueError("no directory after the last frame")
        self.documents = np.frombuffer(zstandard.ZstdDecompressor().decompress(source.read(size)), dtype=_DOCUMENT)
        self.codec = zstandard.ZstdDecompressor()

    def frame(self, k: int) -> bytes:
        self.source.seek(int(self.at[k]))
        plain = self.codec.decompress(self.source.read(int(self.entries["packed"][k])), max_output_size=int(self.entries["plain"][k]))
        if xxhash.xxh64_intdigest(plain) & 0xFFFFFFFF != int(self.entries["check"][k]):
            raise ValueError(f"frame {k} fails its checksum")
        return plain

    def scan(self, wanted: Iterable[int] | None = None) -> Iterator[tuple[int | None, np.ndarray]]:
        """Documents in file order, or only those whose id is in ``wanted``."""
        docs = self.documents
        start = np.cumsum(docs["n_ids"].astype(np.int64)) - docs["n_ids"]
        base = np.zeros(len(self.entries) + 1, dtype=np.int64)
        base[1:] = np.cumsum(self.entries["plain"].astype(np.int64) // 4)
        pick = np.arange(len(docs)) if wanted is None else np.flatnonzero(np.isin(docs["doc_id"], list(wanted)) & (docs["null"] == 0))
        held, plain = -1, b""
        for i in pick:
            k = int(docs["frame"][i])
            if k != held:
                held, plain = k, np.frombuffer(self.frame(k), dtype="<u4")
            lo = int(start[i] - base[k])
            yield None if docs["null"][i] else int(docs["doc_id"][i]), plain[lo : lo + int(docs["n_ids"][i])]
