"""Offset structures over one vertex range: bytes built from positions of ones, and select on those bytes.

Every kind is made by ``Kind(ones, size)`` and opened again by ``Kind.load(raw)``; ``raw`` is all there is of it, header and directories
too. ``payload_bits`` are what its codes count as, ``index_bits`` what speeds select. ``select(j)`` takes an array of ranks from 0 and gives
positions; ranks of a range are vertices in order.
"""

from __future__ import annotations

import functools
import math
import zlib

import numpy as np

from ..bits.pack import pack

HEADER = 4  # 64-bit numbers: ones, size, and two of the kind's own


class Stored:
    """A header and sections, each padded to whole words."""

    raw: bytes

    def _store(self, header: tuple[int, ...], *sections: bytes) -> None:
        head = np.array([*header, *[0] * (HEADER - len(header))], "<i8").tobytes()
        self._open(head + b"".join(x + b"\0" * (-len(x) % 8) for x in sections))

    @classmethod
    def load(cls, raw: bytes):
        """The structure in ``raw``, as written."""
        x = cls.__new__(cls)
        x._open(raw)
        return x

    def _open(self, raw: bytes) -> None:
        self.raw = raw
        self.n, self.size, self.a, self.b = np.frombuffer(raw, "<i8", HEADER).tolist()
        self.at = 8 * HEADER
        self._parse()

    def _take(self, size: int, kind: str = "u1") -> np.ndarray:
        """The next section, of ``size`` bytes."""
        x = np.frombuffer(self.raw, kind, size // np.dtype(kind).itemsize, self.at)
        self.at += size + -size % 8
        return x

    def _parse(self) -> None:
        raise NotImplementedError


def _fields(raw: np.ndarray, bit: np.ndarray, width) -> np.ndarray:
    """Fields of ``width`` bits (57 at most) that begin at the given bits."""
    padded = np.zeros(len(raw) + 8, np.uint8)
    padded[: len(raw)] = raw
    word = np.ndarray((len(raw) + 1,), "<u8", padded, strides=(1,))
    mask = (np.uint64(1) << np.asarray(width, np.uint64)) - np.uint64(1)
    return ((word[bit >> 3] >> (bit & 7).astype(np.uint64)) & mask).astype(np.int64)


def _words(ones: np.ndarray, size: int, step: int = 64) -> np.ndarray:
    bits = np.zeros(-(-max(size, 1) // step) * step, np.uint8)
    bits[ones] = 1
    return np.packbits(bits, bitorder="little").view("<u8")


def _in_rows(rows: np.ndarray, k: np.ndarray) -> np.ndarray:
    """Place of the k-th one (from 0) in each row of words."""
    total = np.cumsum(np.bitwise_count(rows), axis=1, dtype=np.int64)
    at = (total <= k[:, None]).sum(axis=1)
    each = np.arange(len(k))
    before = np.where(at > 0, total[each, np.maximum(at - 1, 0)], 0)
    bits = np.unpackbits(np.ascontiguousarray(rows[each, at]).view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    return 64 * at + np.argmax(np.cumsum(bits, axis=1) == (k - before + 1)[:, None], axis=1)


class Pointers(Stored):
    """An integer of ``bits`` (32 or 64) for each list and the end."""

    def __init__(self, ones: np.ndarray, size: int, bits: int = 64):
        self._store((len(ones), size, bits), np.append(ones, size).astype(f"<u{bits // 8}").tobytes())

    def _parse(self) -> None:
        self.values = self._take((self.n + 1) * self.a // 8, f"<u{self.a // 8}")
        self.payload_bits, self.index_bits = self.a * (self.n + 1), 0

    def select(self, j: np.ndarray) -> np.ndarray:
        return self.values[j].astype(np.int64)


class PackedPointers(Stored):
    """Integers of ceil(log2 size) bits."""

    def __init__(self, ones: np.ndarray, size: int):
        width = max(size - 1, 0).bit_length()
        self._store((len(ones), size, width), pack(ones, np.array([width]), np.array([0, len(ones)]))[0])

    def _parse(self) -> None:
        self.fields = self._take((self.n * self.a + 7) // 8)
        self.payload_bits, self.index_bits = self.n * self.a, 0

    def select(self, j: np.ndarray) -> np.ndarray:
        return _fields(self.fields, np.asarray(j, np.int64) * self.a, self.a)


class Plain(Stored):
    """The bit vector, and the number of ones before each run of ``step`` bits."""

    def __init__(self, ones: np.ndarray, size: int, step: int = 4096):
        words = _words(ones, size, step)
        each = np.bitwise_count(words).reshape(-1, step // 64).sum(axis=1, dtype=np.int64)
        self._store((len(ones), size, step), (np.cumsum(each) - each).astype("<i8").tobytes(), words.tobytes())

    def _parse(self) -> None:
        runs = -(-max(self.size, 1) // self.a)
        self.before = self._take(8 * runs, "<i8")
        self.words = self._take(runs * self.a // 8, "<u8").reshape(runs, -1)
        self.payload_bits, self.index_bits = self.size, 64 * runs

    def select(self, j: np.ndarray) -> np.ndarray:
        run = np.searchsorted(self.before, j, "right") - 1
        return run * self.a + _in_rows(self.words[run], np.asarray(j) - self.before[run])


class Interleaved(Stored):
    """Each run of ``step`` bits follows a 64-bit count of the ones before it."""

    def __init__(self, ones: np.ndarray, size: int, step: int = 512):
        words = _words(ones, size, step).reshape(-1, step // 64)
        each = np.bitwise_count(words).sum(axis=1, dtype=np.int64)
        rows = np.concatenate([(np.cumsum(each) - each).astype("<u8")[:, None], words], axis=1)
        self._store((len(ones), size, step), rows.tobytes())

    def _parse(self) -> None:
        runs = -(-max(self.size, 1) // self.a)
        self.rows = self._take(runs * (8 + self.a // 8), "<u8").reshape(runs, -1)
        self.payload_bits, self.index_bits = self.size, 64 * runs

    def select(self, j: np.ndarray) -> np.ndarray:
        before = self.rows[:, 0].astype(np.int64)
        run = np.searchsorted(before, j, "right") - 1
        return run * self.a + _in_rows(self.rows[run, 1:], np.asarray(j) - before[run])


@functools.cache
def _patterns(block: int):
    """Blocks ordered by their ones: (where each class begins, pattern of each place, place of each pattern in its class, index bits of each class)."""
    pattern = np.arange(1 << block)
    ones = np.bitwise_count(pattern).astype(np.int64)
    order = np.lexsort((pattern, ones))
    begin = np.searchsorted(ones[order], np.arange(block + 2))
    rank = np.empty(len(pattern), np.int64)
    rank[order] = np.arange(len(pattern)) - begin[ones[order]]
    return begin, order, rank, np.array([(math.comb(block, c) - 1).bit_length() for c in range(block + 1)])


class Entropy(Stored):
    """Blocks of 15 bits as class (ones in the block, 4 bits) and index among the class's blocks.

    The ones and the index bits before each run of ``sample`` blocks stand beside them.
    """

    BLOCK = 15

    def __init__(self, ones: np.ndarray, size: int, sample: int = 32):
        count = -(-max(size, 1) // self.BLOCK)
        value = np.zeros(count, np.int64)
        np.add.at(value, ones // self.BLOCK, 1 << (ones % self.BLOCK))
        _, _, rank, width = _patterns(self.BLOCK)
        classes = np.bitwise_count(value).astype(np.int64)
        bits = width[classes]
        at = np.cumsum(bits) - bits
        raw = np.zeros(int(bits.sum()), np.uint8)
        for b in range(int(bits.max(initial=0))):
            live = np.flatnonzero(bits > b)
            raw[at[live] + b] = rank[value[live]] >> b & 1
        runs = np.stack([(np.cumsum(classes) - classes)[::sample], at[::sample]], axis=1).astype("<i8")
        packed = pack(classes, np.array([4]), np.array([0, count]))[0]
        self._store((len(ones), size, sample, len(raw)), runs.tobytes(), packed, np.packbits(raw, bitorder="little").tobytes())

    def _parse(self) -> None:
        self.count = -(-max(self.size, 1) // self.BLOCK)
        runs = -(-self.count // self.a)
        self.runs = self._take(16 * runs, "<i8").reshape(runs, 2)
        self.classes = self._take((4 * self.count + 7) // 8)
        self.indices = self._take((self.b + 7) // 8)
        self.payload_bits, self.index_bits = 4 * self.count + self.b, 128 * runs

    def select(self, j: np.ndarray) -> np.ndarray:
        begin, patterns, _, width = _patterns(self.BLOCK)
        j = np.asarray(j, np.int64)
        run = np.searchsorted(self.runs[:, 0], j, "right") - 1
        blocks = run[:, None] * self.a + np.arange(self.a)
        some = np.minimum(blocks, self.count - 1)
        classes = np.where(blocks < self.count, self.classes[some >> 1] >> (some & 1) * 4 & 15, 0).astype(np.int64)
        total = np.cumsum(classes, axis=1)
        k = j - self.runs[run, 0]
        at = (total <= k[:, None]).sum(axis=1)
        each = np.arange(len(j))
        mine = classes[each, at]
        bits = width[classes]
        index = _fields(self.indices, self.runs[run, 1] + np.cumsum(bits, axis=1)[each, at] - bits[each, at], bits[each, at])
        value = patterns[begin[mine] + index]
        within = value[:, None] >> np.arange(self.BLOCK) & 1
        return blocks[each, at] * self.BLOCK + np.argmax(np.cumsum(within, axis=1) == (k - total[each, at] + mine + 1)[:, None], axis=1)


class Sparse(Stored):
    """Low bits packed, high bits in unary: about n (2 + log2(size / n)) bits."""

    def __init__(self, ones: np.ndarray, size: int):
        n = len(ones)
        low = max(0, (size // n).bit_length() - 1) if n else 0
        high = Plain((ones >> low) + np.arange(n), n + (size >> low) + 1, 1024)
        self._store((n, size, low), pack(ones & ((1 << low) - 1), np.array([low]), np.array([0, n]))[0], high.raw)

    def _parse(self) -> None:
        self.lows = self._take((self.n * self.a + 7) // 8)
        self.high = Plain.load(self.raw[self.at :])
        self.payload_bits, self.index_bits = self.n * self.a + self.high.size, self.high.index_bits

    def select(self, j: np.ndarray) -> np.ndarray:
        j = np.asarray(j, np.int64)
        return ((self.high.select(j) - j) << self.a) | _fields(self.lows, j * self.a, self.a)


class BTree(Stored):
    """Leaves of raw bits under inner counts (bits and ones up to each leaf's end); bits can be inserted."""

    def __init__(self, ones: np.ndarray, size: int, leaf: int = 4096):
        bits = np.zeros(max(size, 1), np.uint8)
        bits[ones] = 1
        self.leaf = leaf
        self._count([bits[i : i + leaf] for i in range(0, len(bits), leaf)])

    def _count(self, leaves: list[np.ndarray]) -> None:
        self.leaves = dict(enumerate(leaves))
        self.ends = np.cumsum([len(x) for x in leaves])
        self.ones = np.cumsum([int(x.sum()) for x in leaves])
        self.n, self.size = int(self.ones[-1]), int(self.ends[-1])
        self.payload_bits, self.index_bits = self.size, 128 * len(leaves)
        self.__dict__.pop("raw", None)

    @functools.cached_property
    def raw(self) -> bytes:
        leaves = [self._leaf(k) for k in range(len(self.ends))]
        head = np.array([int(self.ones[-1]), int(self.ends[-1]), self.leaf, len(leaves)], "<i8").tobytes()
        return head + self.ends.astype("<i8").tobytes() + self.ones.astype("<i8").tobytes() + b"".join(np.packbits(x, bitorder="little").tobytes() for x in leaves)

    def _open(self, raw: bytes) -> None:
        self.__dict__["raw"] = raw
        self.n, self.size, self.leaf, count = np.frombuffer(raw, "<i8", HEADER).tolist()
        self.at = 8 * HEADER
        self.ends, self.ones = self._take(8 * count, "<i8").copy(), self._take(8 * count, "<i8").copy()
        self.byte = self.at + np.concatenate([[0], np.cumsum(-(-np.diff(self.ends, prepend=0) // 8))])
        self.leaves: dict[int, np.ndarray] = {}
        self.payload_bits, self.index_bits = self.size, 128 * count

    def _leaf(self, k: int) -> np.ndarray:
        """A leaf's bits; stored leaves are unpacked when they are asked for."""
        if k not in self.leaves:
            length = int(self.ends[k] - (self.ends[k - 1] if k else 0))
            self.leaves[k] = np.unpackbits(np.frombuffer(self.raw, np.uint8, int(self.byte[k + 1] - self.byte[k]), int(self.byte[k])), count=length, bitorder="little")
        return self.leaves[k]

    def insert(self, position: int, bit: int = 1) -> None:
        """Puts a bit at ``position``; what stood there and after moves up. A leaf twice as long as others is split."""
        if len(self.leaves) < len(self.ends):
            for k in range(len(self.ends)):
                self._leaf(k)
        k = min(int(np.searchsorted(self.ends, position, "right")), len(self.ends) - 1)
        at = position - (int(self.ends[k - 1]) if k else 0)
        new = np.insert(self.leaves[k], at, bit)
        if len(new) < 2 * self.leaf:
            self.__dict__.pop("raw", None)
            self.leaves[k] = new
            self.ends[k:] += 1
            self.ones[k:] += bit
            self.n, self.size, self.payload_bits = self.n + bit, self.size + 1, self.payload_bits + 1
            return
        half = len(new) // 2
        leaves = [self.leaves[i] for i in range(len(self.ends))]
        leaves[k : k + 1] = [new[:half], new[half:]]
        self._count(leaves)

    def select(self, j: np.ndarray) -> np.ndarray:
        j = np.asarray(j, np.int64)
        k = np.searchsorted(self.ones, j, "right")
        out = np.zeros(len(j), np.int64)
        for leaf in np.unique(k).tolist():
            mine = np.flatnonzero(k == leaf)
            place = np.flatnonzero(self._leaf(leaf))
            out[mine] = place[j[mine] - (self.ones[leaf - 1] if leaf else 0)] + (self.ends[leaf - 1] if leaf else 0)
        return out


def delta_code(x: np.ndarray) -> str:
    """Elias delta codes of positive integers, as characters: the length's length in zeros, the length, the rest."""
    out = []
    for v in x.tolist():
        length = bin(v.bit_length())[2:]
        out.append("0" * (len(length) - 1) + length + bin(v)[3:])
    return "".join(out)


def delta_decode(bits: str, n: int) -> np.ndarray:
    out, at = [], 0
    for _ in range(n):
        one = bits.index("1", at)
        end = 2 * one - at + 1
        length = int(bits[one:end], 2)
        out.append(int("1" + bits[end : end + length - 1], 2))
        at = end + length - 1
    return np.array(out, np.int64)


class GapTree(Stored):
    """Leaves of zero-run lengths in Elias delta code under inner counts (ones, and places, before each leaf); ones can be inserted."""

    def __init__(self, ones: np.ndarray, size: int, leaf: int = 512):
        leaves = [ones[i : i + leaf] for i in range(0, len(ones), leaf)]
        codes = [delta_code(np.diff(x, prepend=ones[i * leaf - 1] if i else -1)) for i, x in enumerate(leaves)]
        bits = np.frombuffer("".join(codes).encode(), np.uint8) - 48
        heads = [[i * leaf, ones[i * leaf - 1] if i else -1, at] for i, at in enumerate(np.cumsum([0, *map(len, codes)])[:-1].tolist())] if leaves else []
        self._store((len(ones), size, leaf, len(bits)), np.array(heads, "<i8").tobytes(), np.packbits(bits).tobytes())

    def _parse(self) -> None:
        count = -(-self.n // self.a)
        self.heads = self._take(24 * count, "<i8").reshape(count, 3)
        self.codes = self._take((self.b + 7) // 8)
        self.payload_bits, self.index_bits = self.b, 192 * count

    def _leaf(self, k: int) -> np.ndarray:
        """Places of a leaf's ones."""
        first, before, lo = self.heads[k].tolist()
        hi = int(self.heads[k + 1, 2]) if k + 1 < len(self.heads) else self.b
        bits = np.unpackbits(self.codes[lo >> 3 : (hi + 7) >> 3])[lo & 7 : (lo & 7) + hi - lo]
        return before + np.cumsum(delta_decode((bits + 48).tobytes().decode(), min(self.a, self.n - first)))

    def insert(self, position: int) -> None:
        """Puts a one at ``position``; later ones move up."""
        ones = np.concatenate([self._leaf(k) for k in range(len(self.heads))]) if self.n else np.zeros(0, np.int64)
        cut = int(np.searchsorted(ones, position))
        self.__init__(np.concatenate([ones[:cut], [position], ones[cut:] + 1]), self.size + 1, self.a)

    def select(self, j: np.ndarray) -> np.ndarray:
        j = np.asarray(j, np.int64)
        out = np.zeros(len(j), np.int64)
        for k in np.unique(j // self.a).tolist():
            mine = np.flatnonzero(j // self.a == k)
            out[mine] = self._leaf(k)[j[mine] % self.a]
        return out


class Deflated(Stored):
    """Another kind's bytes under zlib, whole or in blocks of ``block`` bytes with a directory; only blocks that are asked are inflated."""

    inner: type = Pointers

    def __init__(self, ones: np.ndarray, size: int, block: int | None = None):
        raw = self.inner(ones, size).raw
        body = raw[8 * HEADER :] if block else raw
        step = block or len(body)
        parts = [zlib.compress(body[i : i + step], 6) for i in range(0, len(body), step)]
        self._store((len(ones), size, step if block else 0, len(parts)), np.cumsum([0, *map(len, parts)]).astype("<i8").tobytes(), b"".join(parts))

    def _parse(self) -> None:
        self.cuts = self._take(8 * (self.b + 1), "<i8")
        self.parts = self._take(int(self.cuts[-1]))
        self.payload_bits, self.index_bits = 8 * int(self.cuts[-1]), 64 * self.b if self.a else 0

    def _part(self, k: int) -> bytes:
        return zlib.decompress(self.parts[self.cuts[k] : self.cuts[k + 1]].tobytes())

    def select(self, j: np.ndarray) -> np.ndarray:
        if not self.a:
            return self.inner.load(self._part(0)).select(j)
        j = np.asarray(j, np.int64)  # blocks hold whole 64-bit pointers
        each, out = self.a // 8, np.zeros(len(j), np.int64)
        for k in np.unique(j // each).tolist():
            mine = np.flatnonzero(j // each == k)
            out[mine] = np.frombuffer(self._part(k), "<u8")[j[mine] % each]
        return out


class DeflatedPlain(Deflated):
    inner = Plain


class _Kind:
    """A kind with its options: called to build, ``load`` to open."""

    def __init__(self, of: type, *options):
        self.of, self.options, self.load = of, options, of.load

    def __call__(self, ones: np.ndarray, size: int):
        return self.of(np.asarray(ones, np.int64), size, *self.options)


KINDS = {
    "ptr64": _Kind(Pointers), "ptr32": _Kind(Pointers, 32), "ptrlog": _Kind(PackedPointers), "plain": _Kind(Plain), "interleaved": _Kind(Interleaved), "entropy": _Kind(Entropy),
    "sparse": _Kind(Sparse), "btree": _Kind(BTree), "gap": _Kind(GapTree), "zlib": _Kind(Deflated), "zlib_plain": _Kind(DeflatedPlain), "zlib_blocked": _Kind(Deflated, 4096),
}
