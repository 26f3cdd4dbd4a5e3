"""Token-ID files: frequency-ranked ids in byte-aligned variable-length coding.

A file is a folder with ``pages`` and ``ranks``. A page holds whole documents in ascending id
order as two byte strings, the control bytes (four 2-bit lengths each) and the data bytes (one to
four a value, low byte first), so that decoding is a table lookup by control byte and one gather, without
a branch. Values are ranks of ids by how often they occur, so frequent ids take a byte.
Both folders are written by Spark's own committers: a lost executor leaves no torn page.

Defined results: null text is empty (its end id alone); null doc_id sorts first; equal doc_ids
stay next to each other in any order; no rows give a file without pages; extra columns are not stored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import drop, kept_folder, written
from .word_tokens import encoder

PAGE_IDS = 1 << 18
_LENGTHS = (np.arange(256)[:, None] >> np.array([0, 2, 4, 6]) & 3).astype(np.uint8) + 1  # by control byte


def vbyte_encode(values: np.ndarray) -> tuple[bytes, bytes]:
    """(control bytes, data bytes) of unsigned 32-bit values."""
    v = values.astype("<u4")
    size = 1 + (v > 0xFF) + (v > 0xFFFF) + (v > 0xFFFFFF)
    code = np.zeros(-(-len(v) // 4) * 4, np.uint8)
    code[: len(v)] = size - 1
    control = (code.reshape(-1, 4) << np.array([0, 2, 4, 6], np.uint8)).sum(axis=1, dtype=np.uint8)
    return control.tobytes(), v.view(np.uint8).reshape(-1, 4)[np.arange(4) < size[:, None]].tobytes()


def vbyte_decode(control: bytes, data: bytes, n: int) -> np.ndarray:
    size = _LENGTHS[np.frombuffer(control, np.uint8)].ravel()[:n].astype(np.int64)
    end = np.cumsum(size)
    raw = np.frombuffer(data + b"\0\0\0", np.uint8)
    at = end - size
    out = np.zeros(n, np.uint32)
    for k in range(4):
        live = np.flatnonzero(size > k) if k else slice(None)
        out[live] |= raw[at[live] + k].astype(np.uint32) << np.uint32(8 * k)
    return out


def encoded(docs: DataFrame, tokenizer: str, end_id: int, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n, ids (two bytes each where all ids allow it, else four; the end id last), and each task's counts.

    A task's last row has no ids but ``counts``: how often it saw each id, eight bytes a value.
    """
    kind = dict(docs.dtypes)[doc_id]
    names = ["doc_id", "n", "ids", "counts"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(tokenizer)
        most = max(encode.tokenizer.get_vocab_size(True), end_id + 1)
        width = "<u2" if most <= 1 << 16 else "<u4"
        total = np.zeros(most, np.int64)
        id_type = None
        for b in batches:
            id_type = b.schema.field(0).type
            for i in range(0, b.num_rows, 512):
                rows = b.slice(i, 512)
                ids = [np.append(x, np.uint32(end_id)).astype(width) for x in encode(rows.column(1).to_pylist())]
                total += np.bincount(np.concatenate(ids), minlength=most)
                yield pa.RecordBatch.from_arrays([rows.column(0), pa.array([len(x) for x in ids], pa.int64()), pa.array([x.tobytes() for x in ids], pa.binary()), pa.nulls(len(ids), pa.binary())], names=names)
        if id_type is not None:
            yield pa.RecordBatch.from_arrays([pa.nulls(1, id_type), pa.nulls(1, pa.int64()), pa.nulls(1, pa.binary()), pa.array([total.astype("<i8").tobytes()], pa.binary())], names=names)

    return docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text")).mapInArrow(run, f"doc_id {kind}, n long, ids binary, counts binary")


def wide(ids: bytes, n: int) -> np.ndarray:
    return np.frombuffer(ids, "<u2" if len(ids) == 2 * n else "<u4").astype(np.uint32)


def counts_of(ids: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """(ids that occur, the most frequent first; how often). At most the tokenizer's vocabulary reaches the driver."""

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for x in b.column(0).to_pylist():
                c = np.frombuffer(x, "<i8")
                at = np.flatnonzero(c)
                yield pa.RecordBatch.from_arrays([pa.array(at, pa.int64()), pa.array(c[at], pa.int64())], names=["id", "c"])

    some = ids.where("counts IS NOT NULL").select("counts")
    got = some.mapInArrow(spread, "id long, c long").groupBy("id").agg(F.sum("c").alias("c")).toPandas()
    got = got.sort_values(["c", "id"], ascending=[False, True])
    return got["id"].to_numpy(np.int64), got["c"].to_numpy(np.int64)


PAGE = "part int, page int, at long, n_ids long, docs binary, doc_ids binary, control binary, data binary"


def write_token_file(docs: DataFrame, path: str, tokenizer: str, end_id: int, doc_id: str = "doc_id", text: str = "text", part_ids: int = 8 << 20) -> None:
    """Encodes every text and writes the file. doc_id must be an integer column."""
    spark = docs.sparkSession
    ids = written(encoded(docs, tokenizer, end_id, doc_id, text), "ids")
    by_rank, often = counts_of(ids)
    rank = np.zeros(int(by_rank.max(initial=0)) + 1, np.uint32)
    rank[by_rank] = np.arange(len(by_rank))
    parts = max(1, int(often.sum()) // part_ids)

    def pages(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, page, at = TaskContext.get().partitionId(), 0, 0
        keys, sizes, held = [], [], []

        def row() -> pa.RecordBatch:
            nonlocal page, at
            v = np.concatenate(held)
            control, data = vbyte_encode(rank[v])
            has = np.array([k is not None for k in keys], np.uint8)
            out = [part, page, at, len(v), np.array(sizes, "<u4").tobytes(), has.tobytes() + np.array([k or 0 for k in keys], "<i8").tobytes(), control, data]
            page, at = page + 1, at + len(v)
            keys.clear(), sizes.clear(), held.clear()
            kinds = [pa.int32(), pa.int32(), pa.int64(), pa.int64(), *[pa.binary()] * 4]
            return pa.RecordBatch.from_arrays([pa.array([x], k) for x, k in zip(out, kinds)], names=[x.split()[0] for x in PAGE.split(", ")])

        for b in batches:
            for k, n, x in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2)):
                if held and sum(sizes[-1:]) + sum(map(len, held[:-1])) + n > PAGE_IDS:
                    yield row()
                keys.append(k), sizes.append(n), held.append(wide(x.as_py(), n))
        if held:
            yield row()

    dealt = ids.where("counts IS NULL").select("doc_id", "n", "ids").repartitionByRange(parts, "doc_id").sortWithinPartitions("doc_id")
    dealt.mapInArrow(pages, PAGE).write.parquet(f"{path}/pages")
    spark.createDataFrame([(by_rank.astype("<u4").tobytes(),)], "ids binary").write.parquet(f"{path}/ranks")
    drop(ids)


def read_token_file(spark: SparkSession, path: str, digest: bool = False) -> DataFrame:
    """doc_id, start (ids of all documents before it), n_tokens, and ids (binary, four bytes each) or ids_crc32."""
    pages = spark.read.schema(PAGE).parquet(f"{path}/pages")
    before, base = 0, {}
    for r in sorted(pages.groupBy("part").agg(F.sum("n_ids").alias("n")).collect()):  # a row a part
        base[r["part"]], before = before, before + r["n"]
    by_rank = np.frombuffer(spark.read.schema("ids binary").parquet(f"{path}/ranks").first()["ids"], "<u4")
    last, kind = ("ids_crc32", pa.int64()) if digest else ("ids", pa.binary())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                part, _, at, n, docs, keys, control, data = (c[i].as_py() for c in b.columns)
                size = np.frombuffer(docs, "<u4").astype(np.int64)
                ids = by_rank[vbyte_decode(control, data, n)].tobytes()
                cut = np.concatenate([[0], np.cumsum(size)])
                each = [ids[4 * x : 4 * y] for x, y in zip(cut[:-1].tolist(), cut[1:].tolist())]
                has = np.frombuffer(keys, np.uint8, len(size)).astype(bool)
                keys = pa.array(np.frombuffer(keys, "<i8", offset=len(size)), pa.int64(), mask=~has)
                yield pa.RecordBatch.from_arrays([keys, pa.array(base[part] + at + cut[:-1], pa.int64()), pa.array(size, pa.int64()), pa.array([zlib.crc32(x) for x in each] if digest else each, kind)], names=["doc_id", "start", "n_tokens", last])

    return pages.mapInArrow(run, f"doc_id long, start long, n_tokens long, {last} {'long' if digest else 'binary'}")


def op1_token_file(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    path = kept_folder(spark, "tokens")
    write_token_file(spark.read.parquet(f"{sf_dir}/documents.parquet"), path, public_tokenizers.path("word_bpe_49k.json"), end_id=1)
    return read_token_file(spark, path, digest=True)


QUERIES = {"op1_token_file": op1_token_file}
ORACLES: dict[str, str] = {}
