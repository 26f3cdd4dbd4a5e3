"""Shared pieces of the training-data operators: tables in the shared folder, text blocks, components.

Nothing outside this subpackage imports it.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..core.store import drop, kept_folder, reclaim, remove, shared_folder, tables, written

__all__ = ["components", "drop", "exchange_flags", "fresh", "kept_folder", "pack", "reclaim", "remove", "shared_folder", "tables", "text_bytes", "to_blocks", "unpack", "written"]


def text_bytes(docs: DataFrame, column: str = "text") -> int:
    """Bytes of all texts (one aggregate over the column)."""
    return int(docs.select(F.coalesce(F.sum(F.octet_length(column)), F.lit(0))).first()[0])


def fresh(docs: DataFrame, *taken: str) -> list[str]:
    """Column names like ``taken`` that ``docs`` doesn't have."""
    have = {c.lower() for c in docs.columns}
    out = []
    for name in taken:
        while name.lower() in have:
            name = f"_{name}"
        have.add(name.lower())
        out.append(name)
    return out


# --- blocks: slices of rows as one compressed binary --------------------------------------------

BLOCK_SCHEMA = "block_id long, n_rows long, payload binary"


def pack(batch: pa.RecordBatch) -> bytes:
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, batch.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as w:
        w.write_batch(batch)
    return sink.getvalue().to_pybytes()


def unpack(payload) -> pa.RecordBatch:
    with pa.ipc.open_stream(pa.py_buffer(payload)) as r:
        t = r.read_all().combine_chunks()
    found = t.to_batches()
    return found[0] if found else pa.RecordBatch.from_pylist([], schema=t.schema)


def to_blocks(df: DataFrame, block_bytes: int = 4 << 20, name: str = "blocks") -> DataFrame:
    """Rows of ``df`` in blocks of about ``block_bytes`` (a longer row is a block of its own), written.

    A block's id and order are fixed once written, so that passes over the blocks can
    exchange flags by (block, position) instead of keys.
    """

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, k = TaskContext.get().partitionId(), 0
        for b in batches:
            at, usual = 0, max(1, int(block_bytes * b.num_rows / max(1, b.nbytes)))
            while at < b.num_rows:
                step = usual
                rows = b.slice(at, min(step, b.num_rows - at))
                while rows.num_rows > 1 and rows.nbytes > 2 * block_bytes:
                    rows = rows.slice(0, rows.num_rows // 2)
                yield pa.RecordBatch.from_arrays([pa.array([(part << 32) | k], pa.int64()), pa.array([rows.num_rows], pa.int64()), pa.array([pack(rows)], pa.binary())], names=["block_id", "n_rows", "payload"])
                at, k = at + rows.num_rows, k + 1

    return written(df.mapInArrow(cut, BLOCK_SCHEMA), name)


# --- flags exchanged through hash buckets -------------------------------------------------------


def exchange_flags(emitted: DataFrame, judge) -> DataFrame:
    """Judges keys that blocks have sent to hash buckets and returns one flag a key to each block.

    emitted: block_id long, bucket int, keys binary; all occurrences of a key are in one
    bucket. judge: list of binaries (one a row) -> list of packed flag bits. Returns
    block_id, flags (array of (bucket, bits)). What moves is the keys one way and one bit a
    key back; a bucket's rows are as many as blocks, whatever the skew of the keys.
    """

    def one(table: pa.Table) -> pa.Table:
        bits = judge(table["keys"].combine_chunks().to_pylist())
        return pa.table({"block_id": table["block_id"], "bucket": table["bucket"], "bits": pa.array(bits, pa.binary())})

    back = emitted.groupBy("bucket").applyInArrow(one, "block_id long, bucket int, bits binary")
    return back.groupBy("block_id").agg(F.collect_list(F.struct("bucket", "bits")).alias("flags"))


# --- components ---------------------------------------------------------------------------------


def components(links: DataFrame, a: str = "a", b: str = "b", most: int = 60) -> DataFrame:
    """(id, root): the smallest id reachable through ``links``, for ids that have a link.

    Alternating large-star and small-star rounds, DataFrame operators only; each round's
    edges are a table of the shared folder. Edges never grow in number; stops when a round
    changes none.
    """
    edges = links.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u != v").distinct()
    edges = written(edges, "cc")
    was = None
    for _ in range(most):
        both = edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = large.where("u != v").distinct()
        # small star: each u hangs its smaller neighbours, and itself, on the smallest of them
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").where("v != m").select(F.col("v").alias("u"), F.col("m").alias("v")).union(least.select("u", F.col("m").alias("v")))
        new = written(small.where("u != v").distinct(), "cc")
        now = new.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")), F.count_distinct("u")).first()
        if now[0] == now[2] and new.join(new.select(F.col("v").alias("u")).distinct(), "u", "left_semi").isEmpty():
            drop(edges)
            edges = new  # stars already: one centre each, and no centre hangs on another
            break
        if was == tuple(now):
            drop(new)
            break
        old, edges, was = edges, new, tuple(now)
        drop(old)
    else:
        raise RuntimeError(f"components did not settle in {most} rounds")
    return edges.select(F.col("u").alias("id"), F.col("v").alias("root")).union(edges.select(F.col("v").alias("id"), F.col("v").alias("root")).distinct())
