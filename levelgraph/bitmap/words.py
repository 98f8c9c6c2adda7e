"""Vertex sets as packed 64-bit words on the driver and in Arrow kernels.

A set over n labels takes n / 8 bytes, so it is built, merged and sent around only below a bound
on the labels (``MAX_LABELS``); beyond it sets stay tables (see :mod:`levelgraph.bitmap.blocks`).
Words are grouped in lines of 512 bits, the unit in which ranges are cut, so a range owns its
lines alone and no two tasks of a step ever write the same one.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

LINE_WORDS = 8
# labels of a set that is broadcast at most (32 MB)
MAX_LABELS = 1 << 28
_FULL = np.uint64(0xFFFFFFFFFFFFFFFF)


def empty(n_labels: int) -> np.ndarray:
    lines = -(-max(n_labels, 1) // (64 * LINE_WORDS))
    return np.zeros(lines * LINE_WORDS, dtype=np.uint64)


def holds(words: np.ndarray, labels: np.ndarray) -> np.ndarray:
    """Which labels are set."""
    return (words[labels >> 6] >> (labels & 63).astype(np.uint64) & np.uint64(1)).astype(bool)


def pack(labels: np.ndarray, n_labels: int) -> np.ndarray:
    out = empty(n_labels)
    np.bitwise_or.at(out, labels >> 6, np.uint64(1) << (labels & 63).astype(np.uint64))
    return out


def unpack(words: np.ndarray) -> np.ndarray:
    """Labels that are set, in order; only words with a bit are looked into."""
    at = np.flatnonzero(words)
    bits = np.unpackbits(words[at].view(np.uint8), bitorder="little").reshape(-1, 64)
    row, bit = np.nonzero(bits)
    return at[row] * 64 + bit


def merge_one_by_one(words: np.ndarray, more: np.ndarray) -> np.ndarray:
    """The union, vertex by vertex: what :func:`merge` does a line at a time (the baseline of the block form)."""
    out = words.copy()
    for v in unpack(more).tolist():
        out[v >> 6] |= np.uint64(1 << (v & 63))
    return out


def merge(words: np.ndarray, more: np.ndarray) -> np.ndarray:
    """The union of two sets, whole words at a time."""
    return words | more


def count(words: np.ndarray) -> int:
    return int(np.bitwise_count(words).sum())


def cells(rows: DataFrame, column: str = "v", *more) -> DataFrame:
    """``bucket, bits`` (4 KB for 32,768 labels) of a column of labels, with other aggregates beside them."""
    at = F.col(column) + 1  # the built-in buckets start at 1
    return rows.groupBy(F.bitmap_bucket_number(at).alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(at)).alias("bits"), *more)


def from_cells(rows: list, n_labels: int) -> np.ndarray:
    """Words of collected ``bucket, bits`` rows, copied line by line."""
    out = empty(n_labels)
    raw = out.view(np.uint8)
    for r in rows:
        part = np.frombuffer(r["bits"], dtype=np.uint8)
        lo = (r["bucket"] - 1) * len(part)
        n = min(len(part), len(raw) - lo)
        raw[lo : lo + n] |= part[:n]
    return out


def live_stretches(visited: np.ndarray, ranges: list[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
    """``(rid, first, last)`` label of each range that is not in ``visited``; ranges without one are left out.

    Ranges are cut at word limits unless a block of less than a word is asked for."""
    out = []
    for rid, lo, hi in ranges:
        a, b = lo >> 6, (hi + 63) >> 6
        free = ~visited[a:b]
        if lo & 63:
            free[0] &= _FULL << np.uint64(lo & 63)
        if hi & 63:
            free[-1] &= _FULL >> np.uint64(64 - (hi & 63))
        at = np.flatnonzero(free)
        if len(at):
            first, last = int(free[at[0]]), int(free[at[-1]])
            out.append((rid, (a + int(at[0])) * 64 + (first & -first).bit_length() - 1, (a + int(at[-1])) * 64 + last.bit_length() - 1))
    return out
