"""Packing by cutting-stock column generation.

Documents are cut into pieces of ``capacity`` ids and a rest. The histogram of piece lengths
(rounded up to ``unit`` ids: at most capacity/unit classes, whatever the corpus) is covered by
patterns: a linear program over patterns, whose dual prices a knapsack dynamic program turns into
the next pattern, until no pattern pays. Solutions are rounded down and the remainder, at
most a few pieces a class, is filled by decreasing size. Pieces are ranked by class and document in two passes
(ranges of rows, then a count a range), and ranks are mapped to sequences by a join with the patterns (a table as small
as the histogram). No pass over pieces runs in one task.

Defined results: a null text is empty (its end id alone); repeated and null ids are packed row by row;
no rows give no sequences; extra columns go nowhere.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..core.ids import global_rank
from .common import written
from .word_tokens import encoder


def knapsack(sizes: np.ndarray, prices: np.ndarray, capacity: int) -> tuple[float, np.ndarray]:
    """The best multiset of items (value, count of each) by dynamic programming; sizes ascend."""
    best, took = np.zeros(capacity + 1), np.full(capacity + 1, -1)
    fits = np.searchsorted(sizes, np.arange(capacity + 1), "right").tolist()
    for w in range(1, capacity + 1):
        best[w] = best[w - 1]
        if m := fits[w]:
            value = best[w - sizes[:m]] + prices[:m]
            k = value.argmax()
            if value[k] > best[w] + 1e-12:
                best[w], took[w] = value[k], k
    count, w = np.zeros(len(sizes), np.int64), capacity
    while w > 0:
        if took[w] < 0:
            w -= 1
        else:
            count[took[w]] += 1
            w -= sizes[took[w]]
    return float(best[capacity]), count


def column_generation(sizes: np.ndarray, demand: np.ndarray, capacity: int, gap: float = 1e-3, rounds: int = 2000) -> tuple[np.ndarray, np.ndarray]:
    """(patterns as rows, fractional uses) of the linear relaxation, by the revised simplex method.

    The best pattern's value v bounds the optimum from below by objective / v, so it stops
    at v <= 1 + gap, within that share of the optimum.
    """
    n = len(sizes)
    basis = np.diag(capacity // sizes).astype(float)  # columns: as many of one size as fit
    inverse = np.diag(1 / np.diag(basis))
    uses = np.diag(inverse) * demand
    for _ in range(rounds):  # rounding errors can only cost a little padding: plan() covers the demand exactly
        prices = inverse.sum(axis=0)
        value, pattern = knapsack(sizes, prices, capacity)
        if value <= 1 + gap:
            break
        some = np.flatnonzero(pattern)  # a pattern has few sizes
        d = (inverse[:, some] * pattern[some]).sum(axis=1)
        ratio = np.where(d > 1e-9, uses / np.where(d > 1e-9, d, 1), np.inf)
        out = int(np.argmin(ratio))
        uses = np.maximum(uses - ratio[out] * d, 0)
        uses[out] = ratio[out]
        basis[:, out] = pattern
        pivot = inverse[out] / d[out]
        inverse -= np.outer(d, pivot)
        inverse[out] = pivot
    return basis.T.round().astype(np.int64).reshape(n, n), uses


def plan(sizes: np.ndarray, demand: np.ndarray, capacity: int) -> list[tuple[int, dict[int, int]]]:
    """(how often, {index of the size: pieces}) that cover the demand exactly."""
    if not len(sizes):
        return []
    patterns, uses = column_generation(sizes, demand, capacity)
    left, out = demand.astype(np.int64).copy(), []
    for p, x in sorted(zip(patterns.tolist(), uses), key=lambda z: -z[1]):
        p = np.array(p)
        most = min((left[p > 0] // p[p > 0]).tolist(), default=0)
        if (times := min(int(x + 1e-6), most)) > 0:
            out.append((times, {int(i): int(p[i]) for i in np.flatnonzero(p)}))
            left -= times * p
    order = np.argsort(-sizes)
    while left.any():  # first fit decreasing, many bins at a time
        room, p = capacity, np.zeros(len(sizes), np.int64)
        for i in order:
            p[i] = min(left[i], room // sizes[i])
            room -= p[i] * sizes[i]
        times = int((left[p > 0] // p[p > 0]).min())
        out.append((times, {int(i): int(p[i]) for i in np.flatnonzero(p)}))
        left -= times * p
    return out


def pieces_of(docs: DataFrame, tokenizer: str, end_id: int, capacity: int, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, start, length, ids_crc32, doc_tokens of each piece."""
    kind = dict(docs.dtypes)[doc_id]
    names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(tokenizer)
        for b in batches:
            row, start, length, crc, total = [], [], [], [], []
            for k, x in enumerate(v for i in range(0, b.num_rows, 512) for v in encode(b.column(1).slice(i, 512).to_pylist())):
                raw = np.append(x, np.uint32(end_id)).astype("<u4").tobytes()
                n = len(raw) // 4
                for at in range(0, n, capacity):
                    piece = raw[4 * at : 4 * (at + capacity)]
                    row.append(k), start.append(at), length.append(len(piece) // 4), crc.append(zlib.crc32(piece)), total.append(n)
            yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(row, pa.int64())), *(pa.array(x, pa.int64()) for x in (start, length, crc, total))], names=names)

    return docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text")).mapInArrow(run, f"doc_id {kind}, start long, length long, ids_crc32 long, doc_tokens long")


def packed(pieces: DataFrame, capacity: int = 2048, unit: int = 8) -> DataFrame:
    """Adds sequence_id and offset to a (written) table of pieces with a ``length``."""
    spark = pieces.sparkSession
    size = F.ceil(F.col("length") / unit).cast("int")
    ranked = global_rank(pieces.withColumn("_class", size), ["_class", "doc_id", "start"], "_place", 0)
    total = {r["_class"]: r["n"] for r in ranked.groupBy("_class").agg(F.count("*").alias("n")).collect()}  # at most capacity / unit rows
    base, at = [], 0
    for c in sorted(total):
        base.append((c, at))
        at += total[c]
    sizes = np.array(sorted(total), np.int64)
    demand = np.array([total[int(c)] for c in sizes], np.int64)
    slots, used, sequence = [], dict.fromkeys(sizes.tolist(), 0), 0
    for times, pattern in plan(sizes, demand, capacity // unit):
        for i, k in pattern.items():
            c = int(sizes[i])
            slots.append((c, used[c], used[c] + times * k, k, sequence))
            used[c] += times * k
        sequence += times
    bases = spark.createDataFrame(base, "_class int, _base long")
    table = spark.createDataFrame(slots, "_class int, _lo long, _hi long, _k long, _seq long")
    ranked = ranked.join(F.broadcast(bases), "_class").withColumn("_rank", F.col("_place") - F.col("_base"))
    placed = ranked.join(F.broadcast(table), "_class").where((F.col("_rank") >= F.col("_lo")) & (F.col("_rank") < F.col("_hi")))
    placed = placed.withColumn("sequence_id", F.col("_seq") + F.floor((F.col("_rank") - F.col("_lo")) / F.col("_k")).cast("long"))
    before = F.sum("length").over(Window.partitionBy("sequence_id").orderBy(F.desc("_class"), "_rank").rowsBetween(Window.unboundedPreceding, -1))
    return placed.withColumn("offset", F.coalesce(before, F.lit(0))).drop("_class", "_place", "_base", "_rank", "_lo", "_hi", "_k", "_seq")


def pack_documents(docs: DataFrame, tokenizer: str, end_id: int = 1, capacity: int = 2048, unit: int = 8) -> DataFrame:
    """One row a piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset."""
    return packed(written(pieces_of(docs, tokenizer, end_id, capacity), "pieces"), capacity, unit)


def op10_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return pack_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"), public_tokenizers.path("word_bpe_49k.json"))


QUERIES = {"op10_packing": op10_packing}
ORACLES: dict[str, str] = {}
