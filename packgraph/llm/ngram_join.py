"""Exact n-gram Jaccard join by signature trees.

1. Texts with the same words are one class (128-bit key of the word sequence); everything below works on
   one representative a class.
2. A count sketch over all documents orders shingles, the common ones last, so that prefixes (a set
   of n needs n - ceil(t n) + 1 of its first shingles: two linked sets share one) avoid what
   many documents hold. The order only moves cost: any total order gives the same links.
3. Sets that share one of their first three shingles with a group's smallest id are compared at once;
   components of those links take whole groups of near copies out of the search.
4. All prefixes go to hash buckets as packed bytes; a shingle needs a search only where it is in the
   prefixes of two components whose sizes allow a link. One bit a shingle comes back, and only such documents are sent on.
5. In each such group signature trees (nodes hold the OR of token bitmaps and the range of sizes) are
   traversed against each other; a pair of nodes is left as soon as the sizes or the largest possible overlap
   rule out a link, or both lie in one component. Groups are cut by size band (only neighbouring bands can link)
   and large bands into chunks, each pair of chunks a unit of its own.
6. The sets of those documents that are in a pair which the bounds leave come to the task once each. Pairs that the bounds leave are compared exactly there, each
   document's best pair first; pairs whose ends are joined by then are passed over. A task gives the links that join
   something new, a forest; components of all links give the result.

Defined results: a text without words has the empty set and no link; with fewer words than a
shingle the whole sequence is one shingle; repeated rows link; null text is empty; extra columns are ignored;
a row with a null id gets its copies' component, or null; rows of one id must have one text; no rows give no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import words as W
from .common import components, drop, exchange_flags, text_bytes, to_blocks, unpack, written
from .substring_dedup import deal, flags_of, n_buckets

SKETCH_PARTS = 64
EARLY = 3
KEY_BYTES = 6  # of a shingle in a set or bucket: bucket and 48 bits tell shingles apart
CHUNK = 4096
SMALL = CHUNK
BROADCAST_IDS = 1_000_000  # 8 MB of ids; beyond it the texts are joined by a shuffle


def need(a, b, percent: int):
    """Least overlap of linked sets of sizes a and b: 100 i >= percent (a + b - i)."""
    return -(-percent * (a + b) // (100 + percent))


def shingles(col: pa.Array, k: int) -> tuple[list[np.ndarray], np.ndarray, np.ndarray]:
    """Each text's distinct shingle hashes (ascending), and two hashes of its word sequence."""
    data, off = W.column_bytes(col)
    data = W.LOWER[data]
    s, e, first = W.spans(data, off)
    h = W.span_hashes(data, s, e)
    g = W.windows(h, k)
    n = np.diff(first)
    key1, key2 = np.zeros(len(n), np.uint64), np.zeros(len(n), np.uint64)
    # the sequence's key: sums over words of mixes of word and place
    place = (np.arange(len(h)) - np.repeat(first[:-1], n)).astype(np.uint64)
    for key, salt in ((key1, W.U(1)), (key2, W.U(0x632BE59BD9B4E019))):
        total = np.zeros(len(h) + 1, np.uint64)
        np.cumsum(W.joined(h + salt, W.mix(place + salt)), out=total[1:])
        key[:] = W.mix(total[first[1:]] - total[first[:-1]] + n.astype(np.uint64))
    sets = []
    for i, j in zip(first[:-1].tolist(), first[1:].tolist()):
        if j - i >= k:
            sets.append(np.unique(g[i : j - k + 1]))
        elif j > i:
            x = h[i : i + 1]
            for w in range(i + 1, j):
                x = W.joined(x, h[w : w + 1])
            sets.append(W.mix(x + W.U(j - i)))
        else:
            sets.append(np.zeros(0, np.uint64))
    return sets, key1, key2


def sketch_cells(size: int) -> int:
    """About one cell for 32 shingles of ``size`` bytes of text, 2**16 to 2**24 (16 MB of classes)."""
    return 1 << min(max(16, int(size / 200).bit_length()), 24)


def cell(h: np.ndarray, cells: int) -> np.ndarray:
    return (h >> W.U(20)).astype(np.int64) & (cells - 1)


def sketched(docs: DataFrame, k: int, cells: int) -> np.ndarray:
    """A class for each cell of a count sketch over all documents: 0 for usual cells, more the more sets meet it."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, held = np.zeros(cells, np.uint32), []
        for b in batches:
            for rows in W.bites(b, 0):
                held.append(np.concatenate(shingles(rows.column(0), k)[0]))
                if sum(map(len, held)) > 1 << 21:
                    at, n = np.unique(cell(np.concatenate(held), cells), return_counts=True)
                    total[at] += n.astype(np.uint32)
                    held = []
        if held:
            at, n = np.unique(cell(np.concatenate(held), cells), return_counts=True)
            total[at] += n.astype(np.uint32)
        squeeze = zstandard.ZstdCompressor().compress
        parts = [squeeze(np.ascontiguousarray(x.view(np.uint8).reshape(-1, 4).T).tobytes()) for x in total.reshape(SKETCH_PARTS, -1)]
        yield pa.RecordBatch.from_arrays([pa.array(range(SKETCH_PARTS), pa.int32()), pa.array(parts, pa.binary())], names=["part", "counts"])

    def counts(raw: bytes) -> np.ndarray:
        return np.ascontiguousarray(np.frombuffer(zstandard.ZstdDecompressor().decompress(raw), np.uint8).reshape(4, -1).T).view("<u4").ravel()

    def add(t: pa.Table) -> pa.Table:
        total = np.zeros(cells // SKETCH_PARTS, np.int64)
        for x in t["counts"].to_pylist():
            total += counts(x)
        level = np.round(8 * np.log2(total + 1)).astype(np.uint8)
        return pa.table({"part": t["part"].slice(0, 1), "level": pa.array([level.tobytes()], pa.binary())})

    got = docs.select("text").mapInArrow(W.trimmed(count), "part int, counts binary").groupBy("part").applyInArrow(add, "part int, level binary").collect()  # a byte a cell
    level = np.zeros((SKETCH_PARTS, cells // SKETCH_PARTS), np.uint8)
    for r in got:
        level[r["part"]] = np.frombuffer(r["level"], np.uint8)
    level = level.ravel()
    usual = int(np.median(level)) + 8  # twice the median
    return np.where(level > usual, level - usual, 0).astype(np.uint8)


def bitmap(h: np.ndarray) -> bytes:
    """One bit a shingle in a power of two of bits, at least as many as shingles (64 to 16384)."""
    bits = 1 << min(max(6, int(len(h) - 1).bit_length()), 14)
    x = np.zeros(bits, np.uint8)
    x[(h >> W.U(8)).astype(np.int64) & (bits - 1)] = 1
    return np.packbits(x, bitorder="little").tobytes()


def signed(docs: DataFrame, k: int, percent: int, classes: np.ndarray) -> DataFrame:
    """doc_id, k1, k2, n, prefix (8 bytes a shingle, in the common order), bits."""
    names = ["doc_id", "k1", "k2", "n", "prefix", "bits"]
    shared = docs.sparkSession.sparkContext.broadcast(classes)  # a byte a cell

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rarity = shared.value
        for b in batches:
            for rows in W.bites(b, 1):
                sets, k1, k2 = shingles(rows.column(1), k)
                prefix = []
                for x in sets:
                    take = len(x) - -(-percent * len(x) // 100) + 1 if len(x) else 0
                    prefix.append(x[np.argsort(rarity[cell(x, len(rarity))], kind="stable")[:take]].tobytes())
                yield pa.RecordBatch.from_arrays([rows.column(0), pa.array(k1.view(np.int64)), pa.array(k2.view(np.int64)), pa.array([len(x) for x in sets], pa.int64()), pa.array(prefix, pa.binary()), pa.array([bitmap(x) for x in sets], pa.binary())], names=names)

    return docs.mapInArrow(W.trimmed(run), "doc_id long, k1 long, k2 long, n long, prefix binary, bits binary")


# --- exact comparison ---------------------------------------------------------------------------


def low(h: np.ndarray) -> bytes:
    return np.unique(h & W.U((1 << 8 * KEY_BYTES) - 1)).view(np.uint8).reshape(-1, 8)[:, :KEY_BYTES].tobytes()


def raised(x: bytes) -> np.ndarray:
    raw = np.zeros((len(x) // KEY_BYTES, 8), np.uint8)
    raw[:, :KEY_BYTES] = np.frombuffer(x, np.uint8).reshape(-1, KEY_BYTES)
    return raw.view("<u8").ravel()


def sets_of(docs: DataFrame, ids: DataFrame, k: int) -> DataFrame:
    """doc_id, h (the set, ``KEY_BYTES`` a shingle) of the ids in the written table ``ids``, written; a row an id."""
    wanted = docs.join(F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids, "doc_id", "left_semi")

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for rows in W.bites(b, 1):
                yield pa.RecordBatch.from_arrays([rows.column(0), pa.array([low(x) for x in shingles(rows.column(1), k)[0]], pa.binary())], names=["doc_id", "h"])

    return written(wanted.select("doc_id", "text").mapInArrow(W.trimmed(make), "doc_id long, h binary").groupBy("doc_id").agg(F.max("h").alias("h")), "sets")


def verified(docs: DataFrame, pairs: DataFrame, k: int, percent: int) -> DataFrame:
    """Those pairs (a, b) of doc_ids whose sets link. Sets move once for each b, grouped under a."""
    sets = sets_of(docs, written(pairs.select(F.col("a").alias("doc_id")).union(pairs.select("b")).distinct(), "ids"), k)
    with_b = pairs.join(sets.select(F.col("doc_id").alias("b"), F.col("h").alias("hb")), "b")
    both = with_b.join(sets.select(F.col("doc_id").alias("a"), F.col("h").alias("ha")), "a").select("a", "b", "ha", "hb")

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in batches:
            ok = np.zeros(t.num_rows, bool)
            a = t.column(0).to_pylist()
            was, x = None, None
            for r in range(t.num_rows):
                if a[r] != was:
                    was, x = a[r], raised(t.column(2)[r].as_py())
                ok[r] = linked(x, raised(t.column(3)[r].as_py()), percent)
            yield t.select(["a", "b"]).filter(pa.array(ok))

    return both.mapInArrow(W.trimmed(compare), "a long, b long")


def linked(x: np.ndarray, y: np.ndarray, percent: int) -> bool:
    """Whether two sets (ascending) link."""
    if 100 * min(len(x), len(y)) < percent * max(len(x), len(y)):
        return False
    z = np.concatenate([x, y])
    z.sort()
    both = int((z[1:] == z[:-1]).sum())
    return 100 * both >= percent * (len(x) + len(y) - both)


# --- signature trees ----------------------------------------------------------------------------


class SignatureTree:
    """Nodes over sets sorted by size: level 0 are the sets, each level above ORs ``fan`` neighbours.

    Bitmaps are folded to one width. A node holds the OR of its bitmaps, the least and greatest
    size, the greatest number of shingles that share a bit with another (slack), and the component
    if all below are in one (else -1).
    """

    def __init__(self, n: np.ndarray, bits: np.ndarray, comp: np.ndarray, fan: int = 8):
        ones = np.bitwise_count(bits).sum(axis=1).astype(np.int64)
        self.levels = [(bits, n, n, n - ones, comp)]
        while len(self.levels[-1][1]) > fan:
            b, lo, hi, slack, c = self.levels[-1]
            at = np.arange(0, len(lo), fan)
            same = np.minimum.reduceat(c, at)
            same = np.where(same == np.maximum.reduceat(c, at), same, -1)
            self.levels.append((np.bitwise_or.reduceat(b, at, axis=0), np.minimum.reduceat(lo, at), np.maximum.reduceat(hi, at), np.maximum.reduceat(slack, at), same))
        self.fan = fan


def traverse(x: SignatureTree, y: SignatureTree, percent: int, same: bool) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs of sets of x and y (indices; i < j if ``same``) that the bounds cannot rule out, some at a time.

    Both trees are entered at the lower root's level, so that node pairs are of one level. Node pairs wait in a stack, the
    lowest first, so that memory stays bounded however many pairs there are.
    """
    level = min(len(x.levels), len(y.levels)) - 1
    i, j = np.divmod(np.arange(len(x.levels[level][1]) * len(y.levels[level][1])), len(y.levels[level][1]))
    if same:
        i, j = i[i <= j], j[i <= j]
    step = np.arange(x.fan)
    stack = [(level, i, j)]
    while stack:
        level, i, j = stack.pop()
        if len(i) > MOST_PAIRS:
            stack.append((level, i[MOST_PAIRS:], j[MOST_PAIRS:]))
            i, j = i[:MOST_PAIRS], j[:MOST_PAIRS]
        xb, xlo, xhi, xs, xc = x.levels[level]
        yb, ylo, yhi, ys, yc = y.levels[level]
        ok = (100 * xhi[i] >= percent * ylo[j]) & (100 * yhi[j] >= percent * xlo[i]) & ((xc[i] != yc[j]) | (xc[i] < 0))
        if same and level == 0:
            ok &= i < j
        i, j = i[ok], j[ok]
        # |a & b| <= common bits + shingles hidden by a shared bit, on either side
        most = np.bitwise_count(xb[i] & yb[j]).sum(axis=1).astype(np.int64) + np.minimum(xs[i], ys[j])
        ok = most >= need(xlo[i], ylo[j], percent)
        i, j = i[ok], j[ok]
        if level == 0:
            if len(i):
                yield i, j
            continue
        level -= 1
        a = (i[:, None, None] * x.fan + step[None, :, None] + 0 * step[None, None, :]).ravel()
        b = (j[:, None, None] * y.fan + step[None, None, :] + 0 * step[None, :, None]).ravel()
        ok = (a < len(x.levels[level][1])) & (b < len(y.levels[level][1]))
        if same:
            ok &= a <= b
        if ok.any():
            stack.append((level, a[ok], b[ok]))


def folded(bits: list[bytes], width: int) -> np.ndarray:
    """Bitmaps of ``width`` bytes: wider ones are folded by OR (bits are low bits of one hash)."""
    out = np.zeros((len(bits), width), np.uint8)
    for k, b in enumerate(bits):
        x = np.frombuffer(b, np.uint8)
        out[k] = np.bitwise_or.reduce(x.reshape(-1, width)) if len(x) >= width else np.tile(x, width // len(x))
    return out.view(np.uint64)


class Forest:
    """Exact comparison of pairs of documents whose ends are in different components; keeps the links that joined two."""

    def __init__(self, comp: np.ndarray, sets: list[bytes], percent: int):
        self.names, self.node = np.unique(comp, return_inverse=True)
        self.up = list(range(len(self.names)))
        self.sets, self.percent = sets, percent
        self.size = np.array([len(x) // KEY_BYTES for x in sets], np.int64)
        self.mark = np.zeros(1 << 20, bool)
        self.links: list[tuple[int, int]] = []
        self._roots = 0, self.node
        self.bad = np.zeros(0, np.int64)  # pairs that don't link, so that other units don't ask again

    def find(self, x: int) -> int:
        up = self.up
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    def roots(self) -> np.ndarray:
        """Each document's component."""
        if self._roots[0] != len(self.links):
            up = np.array(self.up)
            while not (up[up] == up).all():
                up = up[up]
            self._roots = len(self.links), up[self.node]
        return self._roots[1]

    def apart(self, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        r = self.roots()
        return r[i] != r[j]

    def compare(self, i: np.ndarray, j: np.ndarray, most: np.ndarray) -> None:
        """Documents i and j, which may share ``most`` shingles."""
        i, j = np.minimum(i, j), np.maximum(i, j)
        key, first = np.unique(i * len(self.sets) + j, return_index=True)
        first = first[~np.isin(key, self.bad)]
        i, j, most = i[first], j[first], most[first]
        ratio = most * 1000 // (self.size[i] + self.size[j] + 1)
        # the best pair of each first, then all by document
        order = np.lexsort((-ratio, i))
        lead = order[np.flatnonzero(np.concatenate([[True], i[order][1:] != i[order][:-1]]))] if len(i) else order
        failed = [self.bad]
        for some in (lead, order):
            some = some[self.apart(i[some], j[some])]
            failed.append(self._each(i[some], j[some]))
        self.bad = np.unique(np.concatenate(failed))

    def _each(self, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        bad, was, x, at = [], -1, None, None
        mask = W.U(len(self.mark) - 1)
        for a, b in zip(i.tolist(), j.tolist()):
            u, v = self.find(int(self.node[a])), self.find(int(self.node[b]))
            if u == v:
                continue
            if a != was:
                if at is not None:
                    self.mark[at] = False
                was, x = a, raised(self.sets[a])
                at = (x & mask).astype(np.int64)
                self.mark[at] = True
            y = raised(self.sets[b])
            most = int(np.count_nonzero(self.mark[(y & mask).astype(np.int64)]))  # not below the overlap
            if 100 * most >= self.percent * (len(x) + len(y) - most) and linked(x, y, self.percent):
                self.up[max(u, v)] = min(u, v)
                self.links.append((a, b))
            else:
                bad.append(a * len(self.sets) + b)
        if at is not None:
            self.mark[at] = False
        return np.array(bad, np.int64)


MOST_PAIRS = 200_000


UNIT = "task long, group long, chunk int, own int, rep long, n long, comp long, bits binary"


def _units(t: pa.Table):
    """The table sorted by unit, and each unit's rows (from, to)."""
    t = t.sort_by([("group", "ascending"), ("chunk", "ascending"), ("n", "ascending"), ("rep", "ascending")])
    g, chunk = t["group"].to_numpy(), t["chunk"].to_numpy()
    cuts = np.flatnonzero(np.concatenate([[True], (g[1:] != g[:-1]) | (chunk[1:] != chunk[:-1]), [True]])) if t.num_rows else np.zeros(1, np.int64)
    return t, list(zip(cuts[:-1].tolist(), cuts[1:].tolist()))


def _search(chunk: int, own: np.ndarray, n: np.ndarray, comp: np.ndarray, bits: list[bytes], percent: int):
    """Pairs of a unit's rows that the trees cannot rule out, some at a time: (i, j, common bits)."""
    b = folded(bits, min(map(len, bits)))  # folding keeps the bound: a fold only adds common bits and slack
    i, j = np.flatnonzero(own == 1), np.flatnonzero(own == 0)
    x = SignatureTree(n[i], b[i], comp[i]) if len(i) else None
    y = SignatureTree(n[j], b[j], comp[j]) if len(j) else None
    searches = []
    if x and chunk == 0:  # the host's own
        searches.append((i, i, traverse(x, x, percent, True)))
    if x and y:
        searches.append((i, j, traverse(x, y, percent, False)))
    for left, right, found in searches:
        for p, q in found:
            p, q = left[p], right[q]
            yield p, q, np.bitwise_count(b[p] & b[q]).sum(axis=1).astype(np.int64)


def surviving_rows(percent: int):
    """A grouped function: signature trees for all units of a task; the rows that are in some pair which the bounds leave."""

    def run(t: pa.Table) -> pa.Table:
        t, units = _units(t)
        chunk, own, rep, n, comp = (t[c].to_numpy() for c in ("chunk", "own", "rep", "n", "comp"))
        bits = t["bits"].combine_chunks()
        keep = np.zeros(t.num_rows, bool)
        for lo, hi in units:
            if comp[lo:hi].min() == comp[lo:hi].max():
                continue
            for p, q, _ in _search(chunk[lo], own[lo:hi], n[lo:hi], comp[lo:hi], [x.as_py() for x in bits[lo:hi]], percent):
                ok = rep[lo + p] != rep[lo + q]
                keep[lo + p[ok]] = True
                keep[lo + q[ok]] = True
        return t.select([x.split()[0] for x in UNIT.split(", ")]).filter(pa.array(keep))

    return run


def forest_links(percent: int):
    """A cogrouped function: the trees again for what survived, exact comparison, and the links that join components."""

    def run(t: pa.Table, s: pa.Table) -> pa.Table:
        none = pa.table({"a": pa.array([], pa.int64()), "b": pa.array([], pa.int64())})
        if not t.num_rows:
            return none
        t, units = _units(t)
        chunk, own, rep, n, comp = (t[c].to_numpy() for c in ("chunk", "own", "rep", "n", "comp"))
        bits = t["bits"].combine_chunks()
        order = pa.compute.sort_indices(s["rep"])
        known = s["rep"].take(order).to_numpy()
        doc = np.searchsorted(known, rep)  # of each row
        names = np.zeros(len(known), np.int64)
        names[doc] = comp
        forest = Forest(names, s["h"].take(order).to_pylist(), percent)
        held: list[np.ndarray] = []

        def settle() -> None:
            if held:
                x = np.concatenate(held)
                held.clear()
                forest.compare(x[:, 0], x[:, 1], x[:, 2])

        for lo, hi in units:
            root = forest.roots()[doc[lo:hi]]
            if root.min() == root.max():
                continue
            for p, q, most in _search(chunk[lo], own[lo:hi], n[lo:hi], root, [x.as_py() for x in bits[lo:hi]], percent):
                u, v = doc[lo + p], doc[lo + q]
                held.append(np.stack([u, v, most], axis=1)[forest.apart(u, v)])
                if sum(map(len, held)) > MOST_PAIRS:
                    settle()
        settle()
        if not forest.links:
            return none
        at = np.array(forest.links)
        return pa.table({"a": pa.array(known[at].min(axis=1), pa.int64()), "b": pa.array(known[at].max(axis=1), pa.int64())})

    return run


def search_units(found: DataFrame) -> DataFrame:
    """group, chunk, own, rep, n, comp, bits, key: what is searched together.

    A unit is a band of a shingle's group with, as guests, the next band. Only units with two components are made. Where a band has
    more than ``CHUNK`` sets, it is cut into chunks by a hash and each pair of chunks is a unit. Units of one key go to one
    task: small units share the key of their smallest id, so that sets which share many shingles are told apart once.
    """
    row = ["rep", "n", "comp", "bits"]
    per = written(found.groupBy("h", "band").agg(F.count("*").alias("c"), F.min("comp").alias("lo"), F.max("comp").alias("hi"), F.min("rep").alias("first")), "bands")
    per = per.withColumn("chunks", F.ceil(F.col("c") / CHUNK).cast("long"))
    # (h, at): a band as the host; (band): whose rows come, the host's own or a guest's
    host = per.select("h", F.col("band").alias("at"), F.col("lo").alias("hlo"), F.col("hi").alias("hhi"), F.col("chunks").alias("hc"), F.when(F.col("c") <= SMALL, F.xxhash64("first")).otherwise(F.xxhash64("h", "band")).alias("key"))
    meets = per.withColumn("at", F.explode(F.array(F.col("band"), F.col("band") - 1))).join(host, ["h", "at"])
    # a meeting is searched if it holds two components; guests alone are no reason
    meets = meets.where("least(lo, hlo) != greatest(hi, hhi)").select("h", "band", "at", "chunks", "hc", "key")
    plain = meets.where("chunks = 1 AND hc = 1")
    large = meets.where("chunks > 1 OR hc > 1")
    # plain: guests' hosts must be there too, so own rows are sent once for each host that searches at all
    hosts = plain.select("h", "at", "key").distinct()
    own = found.join(hosts.select("h", F.col("at").alias("band"), "key"), ["h", "band"]).select(F.xxhash64("h", "band").alias("group"), F.lit(0).alias("chunk"), F.lit(1).alias("own"), *row, "key")
    guests = found.join(plain.where("band != at").select("h", "band", "at", "key"), ["h", "band"]).select(F.xxhash64("h", "at").alias("group"), F.lit(0).alias("chunk"), F.lit(0).alias("own"), *row, "key")
    mine = F.pmod(F.xxhash64("rep"), F.col("chunks"))
    # large: host chunk x against guest chunk y
    host_side = found.join(large.select("h", F.col("at").alias("band"), F.col("band").alias("other"), F.col("hc").alias("chunks"), F.col("chunks").alias("theirs")), ["h", "band"]).withColumn("x", mine)
    host_side = host_side.select("h", F.col("band").alias("at"), "other", "x", F.explode(F.expr("sequence(0L, theirs - 1)")).alias("y"), F.lit(1).alias("own"), *row)
    guest_side = found.join(large.select("h", "band", "at", "chunks", F.col("hc").alias("theirs")), ["h", "band"]).withColumn("y", mine)
    guest_side = guest_side.select("h", "at", F.col("band").alias("other"), F.explode(F.expr("sequence(0L, theirs - 1)")).alias("x"), "y", F.lit(0).alias("own"), *row)
    pairs = host_side.unionByName(guest_side).where("at != other OR x <= y")
    chunked = pairs.withColumn("group", F.xxhash64("h", "at", "other", "x", "y", F.lit(11))).select("group", F.lit(1).alias("chunk"), "own", *row, F.col("group").alias("key"))
    return own.union(guests).union(chunked)


# --- the join -----------------------------------------------------------------------------------


def size_band(n: np.ndarray, percent: int) -> np.ndarray:
    """Sizes of linked sets are in one band or in neighbouring ones (a band is a little wider than the ratio allowed)."""
    return np.floor(np.log(n) / (1.0001 * np.log(100 / percent))).astype(np.int64)


KEY_SIZE = KEY_BYTES + 10


def mixed(blobs: list[bytes]) -> list[bytes]:
    """A judge: shingles that two components hold in one size band or two neighbouring ones.

    A key is the shingle's low bytes, then its component (8 bytes) and size band (2).
    """
    raw = np.frombuffer(b"".join(blobs), np.uint8).reshape(-1, KEY_SIZE)
    key = np.zeros((len(raw), 8), np.uint8)
    key[:, :KEY_BYTES] = raw[:, :KEY_BYTES]
    key = key.view("<u8").ravel()
    comp = np.ascontiguousarray(raw[:, KEY_BYTES : KEY_BYTES + 8]).view("<i8").ravel()
    band = np.ascontiguousarray(raw[:, KEY_BYTES + 8 :]).view("<u2").ravel().astype(np.int64)
    flag = np.zeros(len(raw), bool)
    if len(raw):
        order = np.lexsort((band, key))
        k, c, d = key[order], comp[order], band[order]
        begin = np.flatnonzero(np.concatenate([[True], (k[1:] != k[:-1]) | (d[1:] != d[:-1])]))
        lo, hi = np.minimum.reduceat(c, begin), np.maximum.reduceat(c, begin)
        hit = lo != hi
        near = (k[begin][1:] == k[begin][:-1]) & (d[begin][1:] == d[begin][:-1] + 1)
        near &= np.minimum(lo[1:], lo[:-1]) != np.maximum(hi[1:], hi[:-1])
        hit[1:] |= near
        hit[:-1] |= near
        flag[order] = np.repeat(hit, np.diff(np.append(begin, len(k))))
    cuts = np.cumsum([0, *(len(x) // KEY_SIZE for x in blobs)])
    return [np.packbits(flag[i:j]).tobytes() for i, j in zip(cuts[:-1], cuts[1:])]


def _postings(rows: pa.RecordBatch, percent: int):
    """(shingle, row, number of its key) of each prefix entry; (shingle, component, band) of each distinct key."""
    blobs = rows.column("prefix").to_pylist()
    h = np.frombuffer(b"".join(blobs), "<u8")
    row = np.repeat(np.arange(len(blobs)), [len(x) // 8 for x in blobs])
    comp = rows.column("comp").to_numpy()[row]
    band = size_band(rows.column("n").to_numpy(), percent)[row]
    order = np.lexsort((band, comp, h))
    a, c, d = h[order], comp[order], band[order]
    new = np.concatenate([[True], (a[1:] != a[:-1]) | (c[1:] != c[:-1]) | (d[1:] != d[:-1])]) if len(a) else np.zeros(0, bool)
    number = np.empty(len(h), np.int64)
    number[order] = np.cumsum(new) - 1
    return h, row, number, a[new], c[new], d[new]


def jaccard_components(docs: DataFrame, k: int = 4, percent: int = 85) -> DataFrame:
    """doc_id, n_shingles, component_id, rep (smallest doc_id of the same words); ids are long and not null."""
    docs = docs.select(F.col("doc_id").cast("long"), "text")
    size = text_bytes(docs)
    buckets = n_buckets(size, 40)
    sigs = written(signed(docs, k, percent, sketched(docs, k, sketch_cells(size))), "signatures")
    classes = sigs.groupBy("k1", "k2").agg(F.min("doc_id").alias("rep"), F.min_by(F.struct("n", "prefix", "bits"), "doc_id").alias("s"))
    classes = written(classes.select("k1", "k2", "rep", "s.*"), "classes")
    reps = classes.where("n > 0")
    members_ = written(sigs.select("doc_id", "k1", "k2", "n"), "sizes")  # what the result needs of all rows
    drop(sigs)

    # the first shingles of each set against the smallest id that has them first, too
    head = F.expr(f"filter(array({', '.join(f'substring(prefix, {8 * i + 1}, 8)' for i in range(EARLY))}), x -> length(x) = 8)")
    early = reps.select("rep", "n", F.explode(head).alias("h"))
    leader = early.groupBy("h").agg(F.min(F.struct("rep", "n")).alias("l"), F.count("*").alias("c")).where("c > 1")
    star = early.join(leader, "h").where("rep > l.rep").where(F.expr(f"100 * least(n, l.n) >= {percent} * greatest(n, l.n)"))
    links = written(verified(docs, written(star.select(F.col("l.rep").alias("a"), F.col("rep").alias("b")).distinct(), "pairs"), k, percent), "links")
    known = components(links)

    with_comp = reps.join(known, reps["rep"] == known["id"], "left").select("rep", "n", "prefix", "bits", F.coalesce("root", "rep").alias("comp"))
    blocks = to_blocks(with_comp, name="prefixes")
    keys = written(reps.select("k1", "k2", "rep"), "keys")
    drop(classes)

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i, p in zip(b.column(0).to_pylist(), b.column(1)):
                *_, h, c, d = _postings(unpack(p.as_buffer()), percent)
                order, some, begin = deal(h, buckets)
                raw = np.concatenate([h[order].view(np.uint8).reshape(-1, 8)[:, :KEY_BYTES], c[order].astype("<i8").view(np.uint8).reshape(-1, 8), d[order].astype("<u2").view(np.uint8).reshape(-1, 2)], axis=1)
                blobs = [raw[x:y].tobytes() for x, y in zip(begin[:-1], begin[1:])]
                yield pa.RecordBatch.from_arrays([pa.array([i] * len(some), pa.int64()), pa.array(some, pa.int32()), pa.array(blobs, pa.binary())], names=["block_id", "bucket", "keys"])

    flags = exchange_flags(blocks.select("block_id", "payload").mapInArrow(W.trimmed(emit), "block_id long, bucket int, keys binary"), mixed)

    def members(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for p, f in zip(b.column(0), b.column(1).to_pylist()):
                rows = unpack(p.as_buffer())
                h, row, number, keys, _, bands = _postings(rows, percent)
                at = np.flatnonzero(flags_of(keys, buckets, f)[number])
                r, cut = row[at], bands[number[at]]
                n = rows.column("n").to_numpy()[r]
                yield pa.RecordBatch.from_arrays([pa.array(h[at].view(np.int64)), pa.array(cut), rows.column("rep").take(pa.array(r)), pa.array(n), rows.column("comp").take(pa.array(r)), rows.column("bits").take(pa.array(r))], names=["h", "band", "rep", "n", "comp", "bits"])

    joined = blocks.join(flags.hint("shuffle_hash"), "block_id").select("payload", "flags")
    found = written(joined.mapInArrow(W.trimmed(members), "h long, band long, rep long, n long, comp long, bits binary"), "members")
    drop(blocks)
    tasks = max(64, buckets)

    units = search_units(found).withColumn("task", F.pmod(F.col("key"), F.lit(tasks))).drop("key")
    left = written(units.groupBy("task").applyInArrow(surviving_rows(percent), UNIT), "surviving")
    drop(found)
    wanted = written(left.select("task", "rep").distinct(), "wanted")
    sets = sets_of(docs, written(wanted.select(F.col("rep").alias("doc_id")).distinct(), "ids"), k)
    brought = wanted.join(sets.withColumnRenamed("doc_id", "rep"), "rep").select("task", "rep", "h")
    new = left.groupBy("task").cogroup(brought.groupBy("task")).applyInArrow(forest_links(percent), "a long, b long")
    final = components(written(links.unionByName(new), "links"))
    drop(left), drop(sets)
    labelled = keys.join(final, keys["rep"] == final["id"], "left").select("k1", "k2", "rep", F.coalesce("root", "rep").alias("component_id"))
    out = members_.select("doc_id", "k1", "k2", F.col("n").alias("n_shingles")).join(labelled, ["k1", "k2"], "left")
    return out.select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"), F.coalesce("rep", "doc_id").alias("rep"))


def op6_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_components(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")).drop("rep")


QUERIES = {"op6_ngram_join": op6_ngram_join}
ORACLES = {
    "op6_ngram_join": r"""WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
st AS (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 3, 1) + 1)) AS i FROM d WHERE len(ws) > 0),
sh AS MATERIALIZED (SELECT DISTINCT doc_id, md5(array_to_string(ws[i:i + 3], ' ')) AS g FROM st),
n AS MATERIALIZED (SELECT doc_id, count(*) AS n FROM sh GROUP BY doc_id),
pr AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS c FROM sh x JOIN sh y ON x.g = y.g AND x.doc_id < y.doc_id GROUP BY 1, 2),
ln AS MATERIALIZED (SELECT a, b FROM pr JOIN n p ON p.doc_id = a JOIN n q ON q.doc_id = b WHERE 100 * c >= 85 * (p.n + q.n - c)),
ed AS MATERIALIZED (SELECT a, b FROM ln UNION ALL SELECT b, a FROM ln),
r(id, top) AS (SELECT DISTINCT a, a FROM ed UNION SELECT ed.b, r.top FROM r JOIN ed ON ed.a = r.id)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, coalesce(t.top, d.doc_id) AS component_id FROM d LEFT JOIN n ON n.doc_id = d.doc_id LEFT JOIN (SELECT id, min(top) AS top FROM r GROUP BY id) t ON t.id = d.doc_id"""
}
