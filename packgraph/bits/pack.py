"""Bit kernels on NumPy arrays: fixed-width fields, variable-length integers, rank and select.

All work on whole batches of lists: ``begin`` has the first entry of each list and the total.
"""

from __future__ import annotations

import numpy as np


def _places(width: np.ndarray, begin: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(bit of each entry's field, first byte of each list and the total); lists start at whole bytes."""
    count = np.diff(begin)
    size = (count * width + 7) // 8
    byte = np.concatenate([[0], np.cumsum(size)])
    k = np.arange(begin[-1]) - np.repeat(begin[:-1], count)
    return np.repeat(byte[:-1] * 8, count) + k * np.repeat(width, count), byte


def pack(values: np.ndarray, width: np.ndarray, begin: np.ndarray) -> list[bytes]:
    """Fields of width[i] bits for list i, least significant bit first. Values are non-negative and fit."""
    at, byte = _places(width, begin)
    bits = np.zeros(int(byte[-1]) * 8, np.uint8)
    w = np.repeat(width, np.diff(begin))
    v = values.astype(np.uint64)
    for b in range(int(width.max(initial=0))):
        live = np.flatnonzero(w > b)
        bits[at[live] + b] = (v[live] >> np.uint64(b)) & np.uint64(1)
    raw = np.packbits(bits, bitorder="little").tobytes()
    return [raw[i:j] for i, j in zip(byte[:-1].tolist(), byte[1:].tolist())]


def unpack(payloads: list[bytes], width: np.ndarray, begin: np.ndarray) -> np.ndarray:
    at, _ = _places(width, begin)
    bits = np.unpackbits(np.frombuffer(b"".join(payloads), np.uint8), bitorder="little")
    w = np.repeat(width, np.diff(begin))
    out = np.zeros(int(begin[-1]), np.uint64)
    for b in range(int(width.max(initial=0))):
        live = np.flatnonzero(w > b)
        out[live] |= bits[at[live] + b].astype(np.uint64) << np.uint64(b)
    return out.astype(np.int64)


def field(payload: bytes, width: int, i: int) -> int:
    """One field by position: one 64-bit word, or two beyond 57 bits."""
    if not width:
        return 0
    bit = i * width
    word = int.from_bytes(payload[bit >> 3 : (bit >> 3) + (8 if width <= 57 else 16)], "little")
    return (word >> (bit & 7)) & ((1 << width) - 1)


def varint(values: np.ndarray, begin: np.ndarray) -> list[bytes]:
    """Seven bits a byte, low first, the top bit set on all but the last byte."""
    v = values.astype(np.uint64)
    size = np.ones(len(v), np.int64)
    for k in range(1, 10):
        size += v >= np.uint64(1 << (7 * k))
    end = np.cumsum(size)
    at = end - size
    out = np.zeros(int(end[-1]) if len(end) else 0, np.uint8)
    for k in range(int(size.max(initial=0))):
        live = np.flatnonzero(size > k)
        more = (size[live] > k + 1).astype(np.uint8) << 7
        out[at[live] + k] = ((v[live] >> np.uint64(7 * k)) & np.uint64(0x7F)).astype(np.uint8) | more
    cut = np.concatenate([[0], end])[begin]
    raw = out.tobytes()
    return [raw[i:j] for i, j in zip(cut[:-1].tolist(), cut[1:].tolist())]


def unvarint(payloads: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(values, begin)."""
    raw = np.frombuffer(b"".join(payloads), np.uint8)
    last = raw < 0x80
    ends = np.flatnonzero(last) + 1
    starts = np.concatenate([[0], ends[:-1]]) if len(ends) else np.zeros(0, np.int64)
    k = np.arange(len(raw)) - np.repeat(starts, ends - starts)
    values = np.add.reduceat((raw & 0x7F).astype(np.uint64) << (7 * k).astype(np.uint64), starts) if len(starts) else np.zeros(0, np.uint64)
    byte = np.concatenate([[0], np.cumsum([len(p) for p in payloads])])
    return values.astype(np.int64), np.searchsorted(ends, byte, "right")


def zigzag(x: np.ndarray) -> np.ndarray:
    return np.where(x >= 0, 2 * x, -2 * x - 1)


def unzigzag(z: np.ndarray) -> np.ndarray:
    return np.where(z & 1, -(z >> 1) - 1, z >> 1)


def gaps(nbrs: np.ndarray, begin: np.ndarray, origin: np.ndarray) -> np.ndarray:
    """Zig-zagged first difference to ``origin`` of each list, plain differences after it."""
    d = np.diff(nbrs, prepend=0)
    first = begin[:-1][np.diff(begin) > 0]
    d[first] = zigzag(nbrs[first] - origin[np.diff(begin) > 0])
    return d


def ungaps(d: np.ndarray, begin: np.ndarray, origin: np.ndarray) -> np.ndarray:
    full = np.diff(begin) > 0
    first = begin[:-1][full]
    d = d.copy()
    d[first] = unzigzag(d[first]) + origin[full]
    total = np.cumsum(d)
    count = np.diff(begin)[full]
    return total - np.repeat(total[first] - d[first], count)
