"""Vectorised words, word hashes and windows over the bytes of an Arrow string column.

Words are runs of bytes other than 0x20 and 0x09-0x0D; every separator is ASCII, so bytes and
code points agree on them. All kernels work on whole batches: no Python loop over words.
"""

from __future__ import annotations

import ctypes

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

SEPARATORS = np.zeros(256, bool)
SEPARATORS[[0x20, *range(0x09, 0x0E)]] = True
NEWLINE = np.zeros(256, bool)
NEWLINE[0x0A] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
U = np.uint64
_A, _B, _C = U(0x9E3779B97F4A7C15), U(0xC2B2AE3D27D4EB4F), U(0xD6E8FEB86659FD93)  # odd multipliers
_MASKS = np.array([(1 << (8 * k)) - 1 for k in range(8)] + [(1 << 64) - 1], dtype=np.uint64)


def column_bytes(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets from 0) of a string or binary column; null is empty."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    col = pc.fill_null(col.cast(pa.large_binary()), b"")
    if not len(col):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    off = np.frombuffer(col.buffers()[1], np.int64)[col.offset : col.offset + len(col) + 1]
    data = np.frombuffer(col.buffers()[2], np.uint8)[off[0] : off[-1]] if col.buffers()[2] is not None else np.zeros(0, np.uint8)
    return data, off - off[0]


def trimmed(run):
    """``run`` (batches -> batches), which gives freed memory back to the system when a partition ends: workers live on between tasks."""

    def wrapped(batches):
        try:
            yield from run(batches)
        finally:
            pa.default_memory_pool().release_unused()
            try:
                ctypes.CDLL(None).malloc_trim(0)
            except (AttributeError, OSError):  # another C library
                pass

    return wrapped


def bites(batch: pa.RecordBatch, column: int, most_bytes: int = 2 << 20, most_rows: int = 2000):
    """Slices of the batch of at most so many bytes of text (or one row), so that a kernel's arrays stay small."""
    off = column_bytes(batch.column(column))[1]
    i = 0
    while i < batch.num_rows:
        j = min(max(i + 1, int(np.searchsorted(off, off[i] + most_bytes, "right")) - 1), i + most_rows)
        yield batch.slice(i, j - i)
        i = j


def spans(data: np.ndarray, off: np.ndarray, separators: np.ndarray = SEPARATORS) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(starts, ends, first word of each document and the total) of the words."""
    n = len(data)
    inside = ~separators[data]
    first = np.zeros(n + 1, bool)
    first[off] = True
    starts = inside.copy()
    starts[1:] &= ~inside[:-1] | first[1:n]
    ends = inside.copy()
    ends[:-1] &= ~inside[1:] | first[1:n]
    s, e = np.flatnonzero(starts), np.flatnonzero(ends) + 1
    return s, e, np.searchsorted(s, off)


def mix(h: np.ndarray) -> np.ndarray:
    h = h ^ (h >> U(32))
    h *= _A
    h ^= h >> U(29)
    h *= _C
    h ^= h >> U(32)
    return h


def span_hashes(data: np.ndarray, s: np.ndarray, e: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each span's bytes, eight bytes a step."""
    padded = np.zeros(len(data) + 8, np.uint8)
    padded[: len(data)] = data
    word = np.ndarray((len(data) + 1,), "<u8", padded, strides=(1,))
    left = e - s
    h = left.astype(np.uint64) * _B + _C
    live, at, k = None, s, 0
    while True:
        v = word[at] & _MASKS[np.minimum(left, 8)]
        if live is None:
            h = mix((h ^ v) * _B)
        else:
            h[live] = mix((h[live] ^ v) * _B)
        more = np.flatnonzero(left > 8)
        if not len(more):
            return h
        live = more if live is None else live[more]
        at, left, k = at[more] + 8, left[more] - 8, k + 1


def joined(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    return mix(x * _A + (y ^ _C) * _B)


def windows(h: np.ndarray, k: int) -> np.ndarray:
    """Hash of each run of k hashes, by doubling; the last k-1 entries are left out."""
    power, have, done, out = h, 1, 0, None
    n = len(h) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    while True:
        if k & have:
            out = power[done : done + n] if out is None else joined(out, power[done : done + n])
            done += have
        if done == k:
            return mix(out + U(k)) if out is power else out
        power = joined(power[:-have], power[have:])
        have *= 2


def inside_one(first: np.ndarray, k: int) -> np.ndarray:
    """Which of the windows of k words that ``windows`` returns lie within one document."""
    n = int(first[-1]) - k + 1
    if n <= 0:
        return np.zeros(0, bool)
    doc_end = np.repeat(first[1:], np.diff(first))
    return np.arange(n) + k <= doc_end[:n]


def document_of(first: np.ndarray) -> np.ndarray:
    return np.repeat(np.arange(len(first) - 1), np.diff(first))


def per_document(values: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Sum of the values of each document's words."""
    total = np.zeros(len(values) + 1, np.int64)
    np.cumsum(values, out=total[1:])
    return total[first[1:]] - total[first[:-1]]


def repeated(keys: np.ndarray) -> np.ndarray:
    """Which keys occur more than once."""
    if not len(keys):
        return np.zeros(0, bool)
    order = np.argsort(keys)
    k = keys[order]
    same = np.zeros(len(k), bool)
    eq = k[1:] == k[:-1]
    same[1:] |= eq
    same[:-1] |= eq
    out = np.empty(len(k), bool)
    out[order] = same
    return out
