"""Byte-level BPE encoding and decoding through a global shuffle of distinct words.

A text is cut before each space that follows anything but white space: no match of the pre-token
pattern crosses such a place or looks past it, so each piece ("word", with its leading space) is
split by the pattern and merged on its own. A block of texts keeps, for each of its distinct words, the positions where it
stands (one packed stream of word numbers) and sends the distinct words themselves to hash buckets. All
occurrences of a word over all blocks meet in one bucket and are encoded once; their ids go
back to the blocks, which put them into place by position. Decoding takes token bytes from the rank table.

Common words cost one entry a block, so no key is hot; a bucket holds distinct words only.

Defined results: null text has no ids and decodes to null (to no bytes in the digests); repeated rows are encoded alike;
no rows give no rows; other columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import text_bytes, written
from .substring_dedup import n_buckets

BLOCK_BYTES = 12 << 20
_LATE = re.compile(r"\s ")


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


_codecs: dict = {}


def codec(path: str, pattern: str):
    """This worker's (encoding, token bytes by id)."""
    if (path, pattern) not in _codecs:
        import tiktoken

        ranks = load_ranks(path)
        table = [b""] * (max(ranks.values()) + 1)
        for t, i in ranks.items():
            table[i] = t
        _codecs[path, pattern] = tiktoken.Encoding("words", pat_str=pattern, mergeable_ranks=ranks, special_tokens={}), table
    return _codecs[path, pattern]


def words(text: str) -> list[str]:
    """Pieces whose ids are those of the text when joined; the second and later begin with a space that is left out.

    Where white space comes before a space, the pieces on both sides stay one.
    """
    parts = text.split(" ")
    if not _LATE.search(text) and parts[0]:
        return parts
    out, held = [], [parts[0]]
    for p in parts[1:]:
        last = held[-1]
        if last and not last[-1].isspace():
            out.append(" ".join(held))
            held = [p]
        else:
            held.append(p)
    out.append(" ".join(held))
    return out


class _Numbers(dict):
    def __missing__(self, word):
        self[word] = n = len(self)
        return n


def _squeeze(raw: bytes) -> bytes:
    return zstandard.ZstdCompressor(level=3).compress(raw)


def _expand(raw: bytes) -> bytes:
    return zstandard.ZstdDecompressor().decompress(raw)


def _pack_words(some: list[bytes]) -> bytes:
    return _squeeze(np.array([len(some), *map(len, some)], "<u4").tobytes() + b"".join(some))


def _unpack_words(raw: bytes) -> list[bytes]:
    raw = _expand(raw)
    n = int.from_bytes(raw[:4], "little")
    at = np.concatenate([[0], np.cumsum(np.frombuffer(raw, "<u4", n, 4), dtype=np.int64)]) + 4 + 4 * n
    at = at.tolist()
    return [raw[i:j] for i, j in zip(at[:-1], at[1:])]


def _pack_ids(each: list[bytes]) -> bytes:
    """Ids (four bytes each) of each word: counts, then the ids byte plane by byte plane."""
    return _squeeze(len(each).to_bytes(4, "little") + np.array([len(x) // 4 for x in each], "<u2" if max(map(len, each)) < 1 << 18 else "<u4").tobytes() + _planes_of(np.frombuffer(b"".join(each), "<u4")) + (b"\2" if max(map(len, each)) < 1 << 18 else b"\4"))


def _unpack_ids(raw: bytes) -> tuple[np.ndarray, np.ndarray]:
    """(ids a word, all ids)."""
    raw = _expand(raw)
    n, wide = int.from_bytes(raw[:4], "little"), raw[-1]
    counts = np.frombuffer(raw, f"<u{wide}", n, 4).astype(np.int64)
    return counts, np.ascontiguousarray(np.frombuffer(raw, np.uint8, 4 * int(counts.sum()), 4 + wide * n).reshape(4, -1).T).view("<u4").ravel()


def _planes_of(v: np.ndarray) -> bytes:
    return np.ascontiguousarray(v.astype("<u4").view(np.uint8).reshape(-1, 4).T).tobytes()


def _planes(v: np.ndarray) -> bytes:
    """Numbers byte plane by byte plane, squeezed."""
    return _squeeze(len(v).to_bytes(8, "little") + np.ascontiguousarray(v.astype("<u4").view(np.uint8).reshape(-1, 4).T).tobytes())


def _unplanes(raw: bytes) -> np.ndarray:
    raw = _expand(raw)
    n = int.from_bytes(raw[:8], "little")
    return np.ascontiguousarray(np.frombuffer(raw, np.uint8, offset=8).reshape(4, n).T).view("<u4").ravel()


def _blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, list, list[int], list[np.ndarray], list[bytes]]]:
    """(block id, document ids, words a document, word numbers a document, words by number). Null texts count -1 words.

    Depends on the partition's rows and their order alone.
    """
    part, seq = TaskContext.get().partitionId(), 0
    first, later = _Numbers(), _Numbers()
    keys, counts, flat, size = [], [], [], 0

    def done():
        table = [(" " + w).encode() for w in later] + [w.encode() for w in first]
        numbers = [np.where(x < 0, len(later) - 1 - x, x) for x in flat]
        return (part << 32) | seq, keys, counts, numbers, table

    for b in batches:
        for key, t in zip(b.column(0).to_pylist(), b.column(1)):
            t = t.as_py()
            if t:
                w = words(t)
                row = np.empty(len(w), np.int64)
                row[0] = -1 - first[w[0]]
                row[1:] = list(map(later.__getitem__, w[1:]))
                flat.append(row)
                size += len(t)
            keys.append(key), counts.append(len(w) if t else 0 if t == "" else -1)
            if size >= BLOCK_BYTES:
                yield done()
                seq, size, keys, counts, flat = seq + 1, 0, [], [], []
                first, later = _Numbers(), _Numbers()
    if keys:
        yield done()


def _dealt(table: list[bytes], buckets: int) -> list[tuple[int, list[int]]]:
    """(bucket, numbers of its words in the words' order), by bucket: the order of a block's table."""
    by: dict[int, list[int]] = {}
    for k, w in enumerate(table):
        by.setdefault(zlib.crc32(w) % buckets, []).append(k)
    return [(b, sorted(by[b], key=table.__getitem__)) for b in sorted(by)]


def block_words(docs: DataFrame, buckets: int) -> DataFrame:
    """block_id, bucket, body: the distinct words of each block by bucket."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for bid, _, _, _, table in _blocks(batches):
            dealt = _dealt(table, buckets)
            yield pa.RecordBatch.from_arrays([pa.array([bid] * len(dealt), pa.int64()), pa.array([b for b, _ in dealt], pa.int32()), pa.array([_pack_words([table[k] for k in some]) for _, some in dealt], pa.binary())], names=["block_id", "bucket", "body"])

    return docs.mapInArrow(run, "block_id long, bucket int, body binary")


def block_positions(docs: DataFrame, buckets: int) -> DataFrame:
    """block_id, doc_ids, counts, body: which word of the block's table stands at each place, and how many words there are."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for bid, keys, counts, flat, table in _blocks(batches):
            order = [k for _, some in _dealt(table, buckets) for k in some]
            number = np.empty(len(table), np.uint32)
            number[order] = np.arange(len(table))
            numbers = number[np.concatenate(flat)] if flat else np.zeros(0, np.uint32)
            yield pa.RecordBatch.from_arrays([pa.array([bid], pa.int64()), pa.array([len(table)], pa.int64()), pa.array([pack_ids(keys)], pa.binary()), pa.array([np.array(counts, "<i8").tobytes()], pa.binary()), pa.array([_planes(numbers)], pa.binary())], names=["block_id", "n_words", "doc_ids", "counts", "body"])

    return docs.mapInArrow(run, "block_id long, n_words long, doc_ids binary, counts binary, body binary")


def pack_ids(keys: list) -> bytes:
    sink = pa.BufferOutputStream()
    batch = pa.RecordBatch.from_arrays([pa.array(keys, pa.int64())], names=["k"])
    with pa.ipc.new_stream(sink, batch.schema) as w:
        w.write_batch(batch)
    return sink.getvalue().to_pybytes()


def _keys(raw: bytes) -> pa.Array:
    with pa.ipc.open_stream(pa.py_buffer(raw)) as r:
        return r.read_all().column(0).combine_chunks()


def answers(words_: DataFrame, path: str, pattern: str) -> DataFrame:
    """block_id, table (array of (bucket, ids of its words)): each distinct word is encoded once."""

    def one(t: pa.Table) -> pa.Table:
        encode = codec(path, pattern)[0].encode_ordinary
        known: dict[bytes, np.ndarray] = {}
        out = []
        for body in t["body"].to_pylist():
            ids = []
            for w in _unpack_words(body):
                got = known.get(w)
                if got is None:
                    got = known[w] = np.array(encode(w.decode()), "<u4").tobytes()
                ids.append(got)
            out.append(_pack_ids(ids))
        return pa.table({"block_id": t["block_id"], "bucket": t["bucket"], "ids": pa.array(out, pa.binary())})

    back = words_.groupBy("bucket").applyInArrow(one, "block_id long, bucket int, ids binary")
    return back.groupBy("block_id").agg(F.collect_list(F.struct("bucket", "ids")).alias("table"))


def _gather(flat: np.ndarray, begin: np.ndarray, size: np.ndarray, numbers: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(the runs of ``flat`` named by ``numbers``, one after another; where each run ends)."""
    n = size[numbers]
    end = np.cumsum(n)
    return flat[np.repeat(begin[numbers] - (end - n), n) + np.arange(end[-1] if len(end) else 0)], end


def encode_documents(docs: DataFrame, path: str, pattern: str, doc_id: str = "doc_id", text: str = "text", digest: bool = False, stable: bool = True) -> DataFrame:
    """doc_id, n_tokens and ids (array<int>; null for a null text), or ids_sha256 and decoded_sha256.

    stable: ``docs`` gives the same rows in the same partitions each time it is read (a scan of files, a written table),
    so that blocks can be made twice, once for their words and once for the positions, instead of being kept on
    disk between. Anything else (after a shuffle, say) must set it to False and is written first. A block whose
    words and positions disagree stops the job.
    """
    buckets = n_buckets(text_bytes(docs, text), 60, 60_000)
    rows = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text"))
    if not stable:
        rows = written(rows, "texts")
    table = answers(block_words(rows, buckets), path, pattern)
    joined = block_positions(rows, buckets).join(table.hint("shuffle_hash"), "block_id", "left").select("doc_ids", "counts", "body", "table", "n_words")
    schema = "doc_id long, n_tokens long, " + ("ids_sha256 string, decoded_sha256 string" if digest else "ids array<int>")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokens = codec(path, pattern)[1]
        for b in batches:
            for k in range(b.num_rows):
                keys, counts = _keys(b.column(0)[k].as_py()), np.frombuffer(b.column(1)[k].as_py(), "<i8")
                numbers = _unplanes(b.column(2)[k].as_py())
                each = [_unpack_ids(e["ids"]) for e in sorted(b.column(3)[k].as_py() or (), key=lambda e: e["bucket"])]
                size = np.concatenate([n for n, _ in each]) if each else np.zeros(0, np.int64)
                flat = np.concatenate([x for _, x in each]) if each else np.zeros(0, np.uint32)
                if len(size) != b.column(4)[k].as_py():
                    raise RuntimeError("a block's words and positions disagree: docs is not stable")
                begin = np.cumsum(size) - size
                at = np.concatenate([[0], np.cumsum(np.maximum(counts, 0))])
                for i in range(0, len(counts), 256):
                    j = min(i + 256, len(counts))
                    ids, end = _gather(flat, begin, size, numbers[at[i] : at[j]])
                    cut = np.concatenate([[0], end])[at[i : j + 1] - at[i]]
                    out = [keys.slice(i, j - i), pa.array(np.diff(cut), pa.int64())]
                    if digest:
                        raw = ids.tobytes()
                        out.append(pa.array([hashlib.sha256(raw[4 * x : 4 * y]).hexdigest() for x, y in zip(cut[:-1].tolist(), cut[1:].tolist())]))
                        out.append(pa.array([hashlib.sha256(b"".join(map(tokens.__getitem__, ids[x:y].tolist()))).hexdigest() for x, y in zip(cut[:-1].tolist(), cut[1:].tolist())]))
                    else:
                        out.append(pa.ListArray.from_arrays(pa.array(cut, pa.int32()), pa.array(ids.astype(np.int32)), mask=pa.array(counts[i:j] < 0)))
                    yield pa.RecordBatch.from_arrays(out, names=[x.split()[0] for x in schema.split(", ")])

    return joined.mapInArrow(run, schema)


def decode_documents(encoded: DataFrame, path: str, pattern: str) -> DataFrame:
    """Adds text to (doc_id, ids): the bytes of the ids' tokens, joined; null ids give null.

    The token-byte table has the vocabulary's size and is joined in each worker by position.
    Bytes that are no UTF-8 (ids cut inside a character) become replacement characters.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokens = codec(path, pattern)[1]
        for b in batches:
            text = [None if ids is None else b"".join(map(tokens.__getitem__, ids)).decode("utf-8", "replace") for ids in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(text, pa.string())], names=["doc_id", "ids", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id long, ids array<int>, text string")


def op3_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers as P

    return encode_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"), P.path("byte_bpe_multi_50k.tiktoken"), P.PATTERN, digest=True)


QUERIES = {"op3_byte_bpe": op3_byte_bpe}
ORACLES: dict[str, str] = {}
