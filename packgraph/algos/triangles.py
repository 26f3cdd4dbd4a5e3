"""Triangles of one part of a graph, as NumPy kernels over whole batches."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

#: Entries of the table of marked ends, and wedges looked up at once.
MARKS = 1 << 25
WEDGES = 1 << 20


def colour(v: np.ndarray, p: int) -> np.ndarray:
    """One of p colours of each id, by its hash."""
    return ((v.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(40)).astype(np.int64) % p


def pack_edges(held: list[tuple[np.ndarray, np.ndarray]], p: int) -> Iterator[pa.RecordBatch]:
    """(x, y, n, payload) of the edges between each two colours: sorted, first ends as differences, bytes of one rank together."""
    v, u = (np.concatenate([h[k] for h in held]) for k in (0, 1))
    x, y = np.sort([colour(v, p), colour(u, p)], axis=0)
    pair = x * p + y
    order = np.lexsort((u, v, pair))
    v, u, pair = v[order], u[order], pair[order]
    begin = np.flatnonzero(np.concatenate([[True], pair[1:] != pair[:-1]])) if len(v) else np.zeros(0, np.int64)
    codec = pa.Codec("zstd")
    for i, j in zip(begin.tolist(), [*begin[1:].tolist(), len(v)]):
        both = np.concatenate([np.diff(v[i:j], prepend=0), u[i:j]]).astype("<i8")
        raw = codec.compress(both.view(np.uint8).reshape(-1, 8).T.tobytes(), asbytes=True)
        values = [[int(pair[i]) // p], [int(pair[i]) % p], [j - i], [raw]]
        yield pa.RecordBatch.from_arrays([pa.array(k, t) for k, t in zip(values, (pa.int32(), pa.int32(), pa.int64(), pa.binary()))], names=["x", "y", "n", "payload"])


def unpack_edges(table: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    codec, vs, us = pa.Codec("zstd"), [], []
    for n, raw in zip(table["n"].to_pylist(), table["payload"].to_pylist()):
        both = np.frombuffer(codec.decompress(raw, 16 * n, asbytes=True), np.uint8).reshape(8, -1).T.copy().view("<i8").ravel()
        vs.append(np.cumsum(both[:n])), us.append(both[n:])
    return np.concatenate(vs), np.concatenate(us)


def closed(v: np.ndarray, u: np.ndarray, p: int, part: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """The triangles of the edges of ``part``, each once. If its colours differ, those of a single colour are left out: another part has them.

    An edge goes from its end of lower degree, so no list is longer than sqrt(2 m). Lists of some vertices are marked in a table, and
    the lists of their neighbours looked up in it.
    """
    ids, ends = np.unique(np.concatenate([v, u]), return_inverse=True)
    n, m = len(ids), len(v)
    by_degree = np.argsort(np.bincount(ends, minlength=n), kind="stable")
    rank = np.empty(n, np.int64)
    rank[by_degree] = np.arange(n)
    ends, ids = rank[ends], ids[by_degree]
    a, b = np.minimum(ends[:m], ends[m:]), np.maximum(ends[:m], ends[m:])
    order = np.argsort(a * n + b)
    a, b = a[order], b[order].astype(np.int32)
    d = np.bincount(a, minlength=n)
    begin = np.cumsum(d) - d
    shade = colour(ids, p)
    mixed = not part // (p * p) == part // p % p == part % p

    wedges = d[b]  # of each edge: the lists of its far end
    rows = np.flatnonzero((d > 1) & (np.bincount(a, weights=wedges, minlength=n) > 0))
    work = np.cumsum(np.bincount(a, weights=wedges, minlength=n)[rows])
    at, most = 0, max(1, MARKS // max(n, 1))
    mark = np.zeros(most * n, bool)
    while at < len(rows):
        done = work[at - 1] if at else 0
        to = min(max(at + 1, int(np.searchsorted(work, done + WEDGES))), at + most, len(rows))
        some = rows[at:to]
        k = _spans(begin[some], d[some])
        base = np.repeat(np.arange(len(some)) * n, d[some])
        mark[base + b[k]] = True
        far = d[b[k]]
        c = b[_spans(begin[b[k]], far)]
        hit = np.flatnonzero(mark[np.repeat(base, far) + c])
        mark[base + b[k]] = False
        if len(hit):
            edge = k[np.searchsorted(np.cumsum(far), hit, side="right")]
            found = a[edge], b[edge], c[hit]
            if mixed:
                x, y, z = (shade[f] for f in found)
                one = ~((x == y) & (y == z))
                found = tuple(f[one] for f in found)
            yield tuple(ids[f] for f in found)
        at = to


def _spans(begin: np.ndarray, count: np.ndarray) -> np.ndarray:
    """begin, begin + 1, .. of each span, one after another."""
    end = np.cumsum(count)
    return np.arange(end[-1] if len(end) else 0) + np.repeat(begin - (end - count), count)
