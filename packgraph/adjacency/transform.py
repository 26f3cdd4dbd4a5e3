"""Transformers: a sorted list of labels to bytes and back, whole batches at a time.

Each has ``encode(lists, begin, origin, n) -> (payloads, width, first)`` and ``decode(payloads, width, first, d, origin, n)
-> flat labels``. ``width`` and ``first`` are columns next to the payload.
"""

from __future__ import annotations

import numpy as np

from ..bits.pack import gaps, pack, ungaps, unpack, unvarint, unzigzag, varint, zigzag


class Transformer:
    """What all share. ``fitted``: the transformer with what it takes from the whole graph; ``side_bits``: of a row's width and first label, as stored."""

    def fitted(self, g):
        return self

    def side_bits(self, n: int) -> tuple[int, int]:
        return 0, 0


def _begin(d: np.ndarray) -> np.ndarray:
    return np.concatenate([[0], np.cumsum(d)])


def _bits(x: np.ndarray) -> np.ndarray:
    """Bit lengths of non-negative integers."""
    out = np.zeros(len(x), np.int64)
    for b in range(63):
        out += x >> b > 0
    return out


class FixedWidth(Transformer):
    """Labels less one in fields of one width: the graph's (``local=False``) or each list's; or, with ``gap``, gaps after the first.

    ``top`` is the width of the graph's widest gap, which ``fitted`` finds; without it a batch's widest serves.
    """

    def __init__(self, local: bool = True, gap: bool = False, top: int | None = None):
        self.local, self.gap, self.top = local, gap, top
        self.name = ("local" if local else "global") + ("_gap" if gap else "")

    def fitted(self, g):
        if self.local or not self.gap:
            return self
        from pyspark.sql import functions as F

        lists = g.adjacency().select("nbrs")  # chunks: a gap between two chunks is a first label
        gap = F.transform(F.sequence(F.lit(1), F.size("nbrs") - 1), lambda i: F.get("nbrs", i) - F.get("nbrs", i - 1))
        widest = lists.where(F.size("nbrs") > 1).agg(F.max(F.array_max(gap)).alias("g")).first()["g"] or 0
        return FixedWidth(False, True, int(widest).bit_length())

    def side_bits(self, n: int) -> tuple[int, int]:
        label = max(n - 1, 0).bit_length()
        return (label.bit_length() if self.local else 0), (label if self.gap else 0)

    def encode(self, x, begin, origin, n):
        d = np.diff(begin)
        full = d > 0
        first = np.zeros(len(d), np.int64)
        first[full] = x[begin[:-1][full]]
        if self.gap:
            inner = np.ones(len(x), bool)
            inner[begin[:-1][full]] = False
            values, cut = np.diff(x, prepend=0)[inner], _begin(np.maximum(d - 1, 0))
        else:
            values, cut = x - 1, begin
        top = np.zeros(len(d), np.int64)
        some = np.diff(cut) > 0
        if some.any():
            top[some] = np.maximum.reduceat(values, cut[:-1][some])
        width = _bits(top) if self.local or self.gap else np.full(len(d), max(n - 1, 0).bit_length())
        if self.gap and not self.local:
            width = np.full(len(d), width.max(initial=0) if self.top is None else self.top)
        return pack(values, width, cut), width, first

    def decode(self, payloads, width, first, d, origin, n):
        if not self.gap:
            return unpack(payloads, width, _begin(d)) + 1
        inner = unpack(payloads, width, _begin(np.maximum(d - 1, 0)))
        begin = _begin(d)
        out = np.zeros(begin[-1], np.int64)
        lead = np.zeros(begin[-1], bool)
        lead[begin[:-1][d > 0]] = True
        out[~lead] = inner
        total = np.cumsum(out)
        base = total[begin[:-1][d > 0]]
        return total - np.repeat(base, d[d > 0]) + np.repeat(first[d > 0], d[d > 0])


class FullVarint(Transformer):
    name = "full_varint"

    def encode(self, x, begin, origin, n):
        return varint(x, begin), np.zeros(len(begin) - 1, np.int64), np.zeros(len(begin) - 1, np.int64)

    def decode(self, payloads, width, first, d, origin, n):
        return unvarint(payloads)[0]


class GapVarint(Transformer):
    """Zig-zagged difference of the first neighbour to the vertex, then gaps, as variable-length integers."""

    name = "gap_varint"

    def encode(self, x, begin, origin, n):
        return varint(gaps(x, begin, origin), begin), np.zeros(len(begin) - 1, np.int64), np.zeros(len(begin) - 1, np.int64)

    def decode(self, payloads, width, first, d, origin, n):
        return ungaps(unvarint(payloads)[0], _begin(d), origin)


class PrefixGroups(Transformer):
    """Neighbours grouped by their leading bits: prefix, count, then the stripped suffixes.

    Labels less one have ``bits`` bits, of which ``levels`` lead (those of the cluster). Groups are written
    as variable-length prefix and count and ``bits - levels`` wide suffixes. With ``near`` a prefix is stored as its exclusive or with the
    vertex's own, so that shared leading bits are zeros.
    """

    def __init__(self, levels: int, bits: int, near: bool = False):
        self.levels, self.bits, self.near = levels, bits, near
        self.name = f"prefix_{levels}" + ("_near" if near else "")

    def encode(self, x, begin, origin, n):
        low = max(self.bits - self.levels, 0)
        prefix, suffix = (x - 1) >> low, (x - 1) & ((1 << low) - 1)
        out = []
        for k, (i, j) in enumerate(zip(begin[:-1].tolist(), begin[1:].tolist())):
            p = prefix[i:j]
            at = np.flatnonzero(np.concatenate([[True], p[1:] != p[:-1]])) if j > i else np.zeros(0, np.int64)
            key = p[at] ^ ((int(origin[k]) - 1) >> low) if self.near else p[at]
            head = np.stack([key, np.diff(np.append(at, j - i))], axis=1).ravel()
            out.append(varint(np.concatenate([[len(at)], head]), np.array([0, 1 + len(head)]))[0] + pack(suffix[i:j], np.array([low]), np.array([0, j - i]))[0])
        return out, np.full(len(out), low), np.zeros(len(out), np.int64)

    def decode(self, payloads, width, first, d, origin, n):
        low, out = max(self.bits - self.levels, 0), []
        for k, raw in enumerate(payloads):
            tail = -(-int(d[k]) * low // 8)
            head, _ = unvarint([raw[: len(raw) - tail]])
            key, count = head[1::2], head[2::2]
            if self.near:
                key = key ^ ((int(origin[k]) - 1) >> low)
            out.append(((np.repeat(key, count) << low) | unpack([raw[len(raw) - tail :]], np.array([low]), np.array([0, int(d[k])]))) + 1)
        return np.concatenate(out) if out else np.zeros(0, np.int64)


_MORE_BYTES = 1 << np.arange(7, 63, 7)


def _varint_bytes(numbers: np.ndarray) -> int:
    """How many bytes ``varint`` takes for them."""
    return len(numbers) + int(np.searchsorted(_MORE_BYTES, numbers, side="right").sum())


class RefInterval(Transformer):
    """Reference and interval coding of lists: copies from an earlier list of the block, runs of consecutive labels, gaps.

    Parameters have the published defaults: a window of 7 earlier lists, chains of at most 3, runs of 4 or more. All
    numbers are variable-length integers here (the published zeta code is finer for residuals; see ``zeta_bits``).
    A list only refers to lists encoded in the same call, which are stored, and decoded, together as a block.
    """

    name = "ref_interval"
    blocked = True

    def __init__(self, window: int = 7, max_chain: int = 3, min_interval: int = 4):
        self.window, self.max_chain, self.min_interval = window, max_chain, min_interval

    def _rest(self, x: np.ndarray, v: int) -> list[int]:
        """Numbers for labels that are not copied: runs, then residual gaps."""
        gaps = x[1:] - x[:-1]
        if np.count_nonzero(gaps == 1) < self.min_interval - 1:
            return [0, int(zigzag(x[:1] - v)[0]), *gaps.tolist()] if len(x) else [0]
        cut = np.flatnonzero(gaps != 1) + 1
        runs = [r for r in np.split(x, cut) if len(r) >= self.min_interval]
        left = x[~np.isin(x, np.concatenate(runs))] if runs else x
        out, last = [len(runs)], 0
        for r in runs:
            out += [int(r[0]) - last, len(r) - self.min_interval]
            last = int(r[0])
        if len(left):
            out += [int(zigzag(left[:1] - v)[0]), *np.diff(left).tolist()]
        return out

    def encode(self, x, begin, origin, n):
        lists = [x[i:j] for i, j in zip(begin[:-1].tolist(), begin[1:].tolist())]
        inside = np.ones(max(len(x) - 1, 0), bool)
        inside[[i - 1 for i in begin[1:-1].tolist() if 0 < i < len(x)]] = False
        rising = not np.any((np.diff(x) <= 0) & inside)  # else a label may be there twice
        chain, out = [0] * len(lists), []
        for k, a in enumerate(lists):
            numbers = np.array([0, *self._rest(a, int(origin[k]))])
            best, chosen, size = None, numbers, _varint_bytes(numbers)
            for r in range(1, min(self.window, k) + 1):
                b = lists[k - r]
                if chain[k - r] >= self.max_chain or not len(b) or not len(a):
                    continue
                if rising:
                    at = np.searchsorted(a, b)
                    at[at == len(a)] = 0
                    hit = a[at] == b
                    alone = np.ones(len(a), bool)
                    alone[at[hit]] = False
                else:
                    hit, alone = np.isin(b, a), ~np.isin(a, b)
                if not hit.any():
                    continue
                edge = np.flatnonzero(hit[1:] != hit[:-1]) + 1
                blocks = np.diff(edge, prepend=0, append=len(b)).tolist()
                if not hit[0]:
                    blocks = [0, *blocks]
                numbers = np.array([r, len(blocks), *blocks, *self._rest(a[alone], int(origin[k]))])
                took = _varint_bytes(numbers)
                if took < size:
                    best, chosen, size = k - r, numbers, took
            chain[k] = chain[best] + 1 if best is not None else 0
            out.append(varint(chosen, np.array([0, len(chosen)]))[0])
        return out, np.zeros(len(out), np.int64), np.zeros(len(out), np.int64)

    def decode(self, payloads, width, first, d, origin, n):
        lists = []
        numbers, begin = unvarint(payloads)
        for k, (i, j) in enumerate(zip(begin[:-1].tolist(), begin[1:].tolist())):
            v = numbers[i:j].tolist()
            at, copied = 1, np.zeros(0, np.int64)
            if v[0]:
                blocks = v[2 : 2 + v[1]]
                at = 2 + v[1]
                keep = np.repeat(np.arange(len(blocks)) % 2 == 0, blocks)
                copied = lists[k - v[0]][keep]
            runs, last, more = v[at], 0, []
            at += 1
            for _ in range(runs):
                last += v[at]
                more.append(np.arange(last, last + v[at + 1] + self.min_interval))
                at += 2
            if at < len(v):
                left = np.array(v[at:])
                left[0] = unzigzag(left[:1])[0] + int(origin[k])
                more.append(np.cumsum(left))
            lists.append(np.sort(np.concatenate([copied, *more]).astype(np.int64)))
        return np.concatenate(lists) if lists else np.zeros(0, np.int64)


def zeta_bits(x: np.ndarray, k: int = 3) -> np.ndarray:
    """Bits of positive integers in the zeta code of shrinking parameter k."""
    h = np.floor(np.log2(np.maximum(x, 1)) / k).astype(np.int64)
    low = np.left_shift(1, h * k)
    span = np.left_shift(1, (h + 1) * k) - low
    full = np.ceil(np.log2(span)).astype(np.int64)
    short = (1 << full) - span
    return h + 1 + np.where(x - low < short, full - 1, full)
