"""Substring dedup by difference-cover anchors.

A word is removed when a run of ``window`` consecutive words that covers it also starts anywhere
else. Anchors are hashed only at positions of a document that lie in a difference cover modulo
``PERIOD``: for any two starts some shift below the period puts both on the cover, so every
match of ``window`` words shares an aligned anchor of ``window - PERIOD + 1`` words. Anchors
that occur twice are extended to the windows that hold them, and only those windows are compared,
by hashes of all their words.

Keys go to hash buckets as packed bytes and come back as one bit each (see
``common.exchange_flags``). A block sends each key once, or twice if it holds it more often, so a passage in every
document fills its bucket with two keys a block at most; no pairs are made. Texts travel in compressed blocks.

Defined results: null and empty texts have no words and stay null or empty in ``text``;
repeated rows count as other occurrences; no rows give no rows; extra columns go along.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import words as W
from .common import exchange_flags, text_bytes, to_blocks, unpack, written

# A perfect difference set modulo 21; its differences are all of 1..20.
PERIOD = 21
COVER = (0, 1, 4, 14, 16)
ON_COVER = np.isin(np.arange(PERIOD), COVER)


def n_buckets(size: int, per_key: float, keys: int = 400_000) -> int:
    """Buckets of about ``keys`` keys, when a key comes every ``per_key`` bytes of text."""
    return int(min(max(64, size / per_key / keys), 1_000_000))


class _Block:
    """Word hashes, anchors and windows of one block."""

    def __init__(self, col: pa.Array, window: int):
        self.window = window
        self.data, self.off = W.column_bytes(col)
        self.s, self.e, self.first = W.spans(self.data, self.off)
        self.h = W.span_hashes(self.data, self.s, self.e)

    def anchors(self) -> tuple[np.ndarray, np.ndarray]:
        """(positions, keys) of anchors that some window of the document can hold."""
        k = self.window - PERIOD + 1
        g = W.windows(self.h, k)
        at = np.arange(len(g)) - np.repeat(self.first[:-1], np.diff(self.first))[: len(g)]
        n = np.repeat(np.diff(self.first), np.diff(self.first))[: len(g)]
        p = np.flatnonzero(W.inside_one(self.first, k) & ON_COVER[at % PERIOD] & (n >= self.window))
        return p, g[p]

    def candidates(self, hit: np.ndarray) -> np.ndarray:
        """Starts of windows that hold one of the anchors at the positions ``hit``."""
        n = len(self.h) - self.window + 1
        if n <= 0 or not len(hit):
            return np.zeros(0, np.int64)
        step = np.zeros(len(self.h) + PERIOD + 1, np.int32)
        np.add.at(step, np.maximum(hit - PERIOD + 1, 0), 1)
        np.add.at(step, hit + 1, -1)
        return np.flatnonzero((np.cumsum(step)[:n] > 0) & W.inside_one(self.first, self.window))

    def keys(self, starts: np.ndarray) -> np.ndarray:
        return W.windows(self.h, self.window)[starts]

    def covered(self, starts: np.ndarray) -> np.ndarray:
        step = np.zeros(len(self.h) + 1, np.int32)
        np.add.at(step, starts, 1)
        np.add.at(step, starts + self.window, -1)
        return np.cumsum(step)[:-1] > 0


def bucket_of(keys: np.ndarray, buckets: int) -> np.ndarray:
    return (W.mix(keys ^ W.U(0x5DEECE66D)) % W.U(buckets)).astype(np.int32)


def deal(keys: np.ndarray, buckets: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(order by bucket, buckets that have keys, where each one's keys begin and the total)."""
    b = bucket_of(keys, buckets)
    order = np.argsort(b, kind="stable")
    some, begin = np.unique(b[order], return_index=True)
    return order, some, np.append(begin, len(b))


def sent(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(what a block sends for its keys: each once, or twice if it is there more often; the place of each key's first in it)."""
    some, back, n = np.unique(keys, return_inverse=True, return_counts=True)
    n = np.minimum(n, 2)
    return np.repeat(some, n), (np.cumsum(n) - n)[back]


def key_rows(block_id: int, keys: np.ndarray, buckets: int, size: int) -> pa.RecordBatch:
    """What a block sends for its keys, by bucket; ``size`` low bytes of each."""
    keys = sent(keys)[0]
    order, some, begin = deal(keys, buckets)
    raw = np.ascontiguousarray(keys[order]).view(np.uint8).reshape(-1, 8)[:, :size]
    blobs = [raw[i:j].tobytes() for i, j in zip(begin[:-1], begin[1:])]
    return pa.RecordBatch.from_arrays([pa.array([block_id] * len(some), pa.int64()), pa.array(some, pa.int32()), pa.array(blobs, pa.binary())], names=["block_id", "bucket", "keys"])


def flags_of(keys: np.ndarray, buckets: int, flags) -> np.ndarray:
    """The flags of a block's keys, in their order."""
    order, some, begin = deal(keys, buckets)
    got = {f["bucket"]: f["bits"] for f in flags or ()}
    out = np.zeros(len(keys), bool)
    for b, i, j in zip(some.tolist(), begin[:-1].tolist(), begin[1:].tolist()):
        out[order[i:j]] = np.unpackbits(np.frombuffer(got[b], np.uint8), count=j - i).astype(bool)
    return out


def repeated_keys(keys: np.ndarray, buckets: int, flags) -> np.ndarray:
    """The flags of all keys of a block, from those that came back for what it sent."""
    some, first = sent(keys)
    return flags_of(some, buckets, flags)[first]


def repeats(size: int):
    """A judge: the keys (of ``size`` bytes) that occur more than once in the bucket."""

    def judge(blobs: list[bytes]) -> list[bytes]:
        raw = np.frombuffer(b"".join(blobs), np.uint8).reshape(-1, size)
        keys = np.zeros((len(raw), 8), np.uint8)
        keys[:, :size] = raw
        again = W.repeated(keys.view("<u8").ravel())
        cuts = np.cumsum([0, *(len(x) // size for x in blobs)])
        return [np.packbits(again[i:j]).tobytes() for i, j in zip(cuts[:-1], cuts[1:])]

    return judge


ANCHOR_BYTES = 5  # anchors only nominate windows, so a chance hit costs a comparison and no result


def repeated_windows(docs: DataFrame, text: str = "text", window: int = 35) -> tuple[DataFrame, int]:
    """(block_id, payload, flags1, flags2) of all rows in blocks, and the number of buckets."""
    if window < PERIOD + 4:
        raise ValueError(f"window must be {PERIOD + 4} words or more")
    buckets = n_buckets(text_bytes(docs, text), 26)
    blocks = to_blocks(docs, name="substrings")

    def emit_anchors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i, p in zip(b.column(0).to_pylist(), b.column(1)):
                yield key_rows(i, _Block(unpack(p.as_buffer()).column(text), window).anchors()[1], buckets, ANCHOR_BYTES)

    kinds = "block_id long, bucket int, keys binary"
    first = written(exchange_flags(blocks.select("block_id", "payload").mapInArrow(W.trimmed(emit_anchors), kinds), repeats(ANCHOR_BYTES)).withColumnRenamed("flags", "flags1"), "anchors")
    with_first = blocks.join(first.hint("shuffle_hash"), "block_id", "left").select("block_id", "payload", "flags1")

    def emit_windows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i, p, f in zip(b.column(0).to_pylist(), b.column(1), b.column(2).to_pylist()):
                x = _Block(unpack(p.as_buffer()).column(text), window)
                at, keys = x.anchors()
                yield key_rows(i, x.keys(x.candidates(at[repeated_keys(keys, buckets, f)])), buckets, 8)

    second = written(exchange_flags(with_first.mapInArrow(W.trimmed(emit_windows), kinds), repeats(8)).withColumnRenamed("flags", "flags2"), "windows")
    return blocks.join(first.join(second, "block_id", "left").hint("shuffle_hash"), "block_id", "left").select("payload", "flags1", "flags2"), buckets


def covered_words(col: pa.Array, flags1, flags2, window: int, buckets: int) -> tuple[_Block, np.ndarray]:
    """The block and which of its words a repeated window covers."""
    x = _Block(col, window)
    at, keys = x.anchors()
    starts = x.candidates(at[repeated_keys(keys, buckets, flags1)])
    return x, x.covered(starts[repeated_keys(x.keys(starts), buckets, flags2)])


def kept_text(x: _Block, k: int, gone: np.ndarray) -> bytes:
    """Words of row k that stay, joined by one space."""
    raw = x.data[x.off[k] : x.off[k + 1]].tobytes().split()
    i, j = x.first[k], x.first[k + 1]
    if gone[i:j].any():
        raw = [w for w, g in zip(raw, gone[i:j].tolist()) if not g]
    return b" ".join(raw)


def substring_report(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", window: int = 35) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256, spans (array of start, end word of what goes)."""
    kind = dict(docs.dtypes)[doc_id]
    joined, buckets = repeated_windows(docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text")), "text", window)
    names = ["doc_id", "n_words", "n_removed", "kept_sha256", "spans"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for p, f1, f2 in zip(b.column(0), b.column(1).to_pylist(), b.column(2).to_pylist()):
                rows = unpack(p.as_buffer())
                x, gone = covered_words(rows.column("text"), f1, f2, window, buckets)
                sha, cut = [], []
                for k in range(rows.num_rows):
                    sha.append(hashlib.sha256(kept_text(x, k, gone)).hexdigest())
                    g = gone[x.first[k] : x.first[k + 1]]
                    d = np.flatnonzero(np.diff(np.concatenate([[0], g.view(np.int8), [0]]))) if g.any() else []
                    cut.append([{"start": int(i), "end": int(j)} for i, j in zip(d[::2], d[1::2])])
                kinds = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))
                yield pa.RecordBatch.from_arrays([rows.column("doc_id"), pa.array(np.diff(x.first), pa.int64()), pa.array(W.per_document(gone, x.first), pa.int64()), pa.array(sha), pa.array(cut, kinds)], names=names)

    return joined.mapInArrow(W.trimmed(run), f"doc_id {kind}, n_words long, n_removed long, kept_sha256 string, spans array<struct<start:bigint,end:bigint>>")


def remove_substrings(docs: DataFrame, text: str = "text", window: int = 35) -> DataFrame:
    """``docs`` with repeated passages taken out of ``text``.

    A text that loses nothing stays as it is, byte for byte; others are their kept words
    joined by one space.
    """
    joined, buckets = repeated_windows(docs, text, window)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for p, f1, f2 in zip(b.column(0), b.column(1).to_pylist(), b.column(2).to_pylist()):
                rows = unpack(p.as_buffer())
                at = rows.schema.get_field_index(text)
                x, gone = covered_words(rows.column(at), f1, f2, window, buckets)
                lost = np.flatnonzero(W.per_document(gone, x.first))
                if len(lost):
                    texts = rows.column(at).to_pylist()
                    for k in lost.tolist():
                        texts[k] = kept_text(x, k, gone).decode()
                    rows = rows.set_column(at, rows.schema.field(at), pa.array(texts, rows.schema.field(at).type))
                yield rows

    return joined.mapInArrow(W.trimmed(run), docs.schema)


def op7_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return substring_report(docs).drop("spans")


QUERIES = {"op7_substring_dedup": op7_substring_dedup}
ORACLES = {
    "op7_substring_dedup": r"""WITH d AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents),
wd AS (SELECT doc_id, unnest(ws) AS w, unnest(range(1, len(ws) + 1)) AS i FROM d),
st AS (SELECT doc_id, ws, unnest(range(1, len(ws) - 33)) AS i FROM d WHERE len(ws) >= 35),
gr AS (SELECT doc_id, i, md5(array_to_string(ws[i:i + 34], ' ')) AS g FROM st),
hit AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY g) AS c FROM gr) q WHERE c > 1),
seen AS (SELECT wd.doc_id, wd.i, w, max(hit.i) OVER (PARTITION BY wd.doc_id ORDER BY wd.i ROWS UNBOUNDED PRECEDING) AS l FROM wd LEFT JOIN hit ON hit.doc_id = wd.doc_id AND hit.i = wd.i),
left_ AS (SELECT doc_id, count(*) AS n_words, count(CASE WHEN l IS NOT NULL AND i - l < 35 THEN 1 END) AS n_removed, string_agg(CASE WHEN l IS NULL OR i - l >= 35 THEN w END, ' ' ORDER BY i) AS kept FROM seen GROUP BY doc_id)
SELECT d.doc_id, coalesce(n_words, 0) AS n_words, coalesce(n_removed, 0) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256 FROM d LEFT JOIN left_ ON left_.doc_id = d.doc_id"""
}
