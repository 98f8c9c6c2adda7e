"""Vectorised work on whole texts: words, hashes and windows over Arrow string buffers.

A batch of texts is one byte buffer with offsets.  Word limits come from a byte table, and
word hashes from prefix sums of a polynomial modulo 2**64, so no Python loop runs over words.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

U64 = np.uint64
_BASE = 0x9E3779B97F4A7C15 | 1
_MASK = (1 << 64) - 1
_BLOCK = 1 << 16

SPACE = np.zeros(256, dtype=bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def _powers(base: int, n: int) -> np.ndarray:
    out = np.empty(n, dtype=U64)
    out[0] = 1
    done = 1
    with np.errstate(over="ignore"):
        while done < n:
            step = min(done, n - done)
            out[done : done + step] = out[:step] * U64(pow(base, done, 1 << 64))
            done += step
    return out


_INVERSE = pow(_BASE, -1, 1 << 64)
_POW = _powers(_BASE, _BLOCK + 1)
_INV = _powers(_INVERSE, _BLOCK + 1)


def mix(h: np.ndarray) -> np.ndarray:
    """Finalising 64-bit mixer (a bijection)."""
    h = h ^ (h >> U64(33))
    h = h * U64(0xFF51AFD7ED558CCD)
    h ^= h >> U64(33)
    h = h * U64(0xC4CEB9FE1A85EC53)
    h ^= h >> U64(33)
    return h


@dataclass
class Words:
    """Words of a batch: byte limits, owners and, per text, the index of its first word."""

    data: np.ndarray
    offsets: np.ndarray
    starts: np.ndarray
    ends: np.ndarray
    first: np.ndarray

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    def owners(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.first) - 1), self.counts)

    def hashes(self) -> np.ndarray:
        return span_hashes(self.data, self.starts, self.ends)


def buffers(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and 64-bit offsets of a string column; nulls become empty texts."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
        if isinstance(texts, pa.ChunkedArray):
            texts = pa.concat_arrays(texts.chunks) if texts.num_chunks else pa.array([], pa.large_string())
    texts = texts.cast(pa.large_string())
    if texts.null_count:
        texts = texts.fill_null("")
    raw = texts.buffers()
    offsets = np.frombuffer(raw[1], dtype=np.int64)[texts.offset : texts.offset + len(texts) + 1] if len(texts) else np.zeros(1, np.int64)
    data = np.frombuffer(raw[2], dtype=np.uint8) if raw[2] is not None and raw[2].size else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def limits(inside: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Runs of ``inside`` bytes that never cross a text's limits; starts, ends, first run of each text."""
    n = len(inside)
    opens = np.empty(n, dtype=bool)
    closes = np.empty(n, dtype=bool)
    if n:
        opens[0] = True
        np.logical_not(inside[:-1], out=opens[1:])
        closes[-1] = True
        np.logical_not(inside[1:], out=closes[:-1])
        cuts = offsets[(offsets > 0) & (offsets < n)]
        opens[cuts] = True
        closes[cuts - 1] = True
        opens &= inside
        closes &= inside
    starts = np.flatnonzero(opens)
    ends = np.flatnonzero(closes) + 1
    return starts, ends, np.searchsorted(starts, offsets)


def words(texts: pa.Array, lower: bool = False) -> Words:
    """Maximal runs of bytes other than ASCII white space."""
    data, offsets = buffers(texts)
    if lower:
        data = LOWER[data]
    starts, ends, first = limits(~SPACE[data], offsets)
    return Words(data, offsets, starts, ends, first)


def span_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hash of each byte span (spans sorted and disjoint), by blocks of bounded memory."""
    h0, h1 = np.empty(len(starts), dtype=U64), np.empty(len(ends), dtype=U64)
    shift = np.empty(len(starts), dtype=U64)
    carry = U64(0)
    with np.errstate(over="ignore"):
        for lo in range(0, max(len(data), 1), _BLOCK):
            part = data[lo : lo + _BLOCK]
            n = len(part)
            cum = np.zeros(n + 1, dtype=U64)
            np.cumsum((part.astype(U64) + U64(1)) * _POW[:n], out=cum[1:])
            cum = cum * U64(pow(_BASE, lo, 1 << 64)) + carry
            a, b = np.searchsorted(starts, (lo, lo + _BLOCK))
            h0[a:b] = cum[starts[a:b] - lo]
            shift[a:b] = _INV[starts[a:b] - lo] * U64(pow(_INVERSE, lo, 1 << 64))
            c, d = np.searchsorted(ends, (lo + 1, lo + _BLOCK + 1))
            h1[c:d] = cum[ends[c:d] - lo]
            carry = cum[n]
        out = (h1 - h0) * shift
        return mix(out ^ ((ends - starts).astype(U64) << U64(48)))


_WINDOW_KEYS = [U64(pow(0xD6E8FEB86659FD93, k + 1, 1 << 64) | 1) for k in range(64)]


def window_hashes(h: np.ndarray, first: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all windows of ``size`` words inside a text, and the index of their first word."""
    total = len(h)
    if total < size:
        return np.empty(0, dtype=U64), np.empty(0, dtype=np.int64)
    with np.errstate(over="ignore"):
        acc = h[: total - size + 1] * _WINDOW_KEYS[0]
        for k in range(1, size):
            acc = acc + h[k : total - size + 1 + k] * _WINDOW_KEYS[k]
    last_start = np.repeat(first[1:] - size, np.diff(first))[: total - size + 1]
    at = np.flatnonzero(np.arange(total - size + 1) <= last_start)
    return mix(acc[at]), at


def sequence_hash(h: np.ndarray) -> int:
    """Hash of a short whole sequence of word hashes (at most 63 words)."""
    with np.errstate(over="ignore"):
        acc = U64(len(h) * 0x2545F4914F6CDD1D & _MASK)
        for k, x in enumerate(h):
            acc = acc + x * _WINDOW_KEYS[k + 1]
        return int(mix(np.array([acc], dtype=U64))[0])


def slices(batches: Iterator[pa.RecordBatch], column: str, max_bytes: int = 1_000_000) -> Iterator[pa.RecordBatch]:
    """Cut record batches so that a piece holds about ``max_bytes`` of text, or one text."""
    for batch in batches:
        n = batch.num_rows
        if not n:
            continue
        _, offsets = buffers(batch.column(batch.schema.get_field_index(column)))
        lo = 0
        while lo < n:
            hi = int(np.searchsorted(offsets, offsets[lo] + max_bytes, side="right")) - 1
            hi = min(max(hi, lo + 1), n)
            yield batch.slice(lo, hi - lo)
            lo = hi
