"""Weighted lists as one run of fields: each holds an identifier and, beside it, the edge's weight.

A row's fields have one width for identifiers and one for weights, those of its largest (``local``) or of the graph's; both are read in one
extraction. Identifiers are stored less one.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..bits.pack import field, pack, unpack
from .model import CHUNK, Graph
from .store import written

ROWS = "v long, chunk int, d long, id_width int, w_width int, payload binary"
MOST = 62  # bits of a field


def _top(values: np.ndarray, begin: np.ndarray) -> np.ndarray:
    """Bits of each list's largest value."""
    top = np.zeros(len(begin) - 1, np.int64)
    full = np.diff(begin) > 0
    if full.any():
        top[full] = np.maximum.reduceat(values, begin[:-1][full])
    return np.array([int(x).bit_length() for x in top], np.int64)


@dataclass
class WeightedGraph:
    graph: Graph
    rows: DataFrame
    chunk: int = CHUNK

    @classmethod
    def build(cls, g: Graph, local: bool = True, chunk: int = CHUNK) -> WeightedGraph:
        n = max(g.n - 1, 0).bit_length()
        widest = 0 if local else int(g.edges.agg(F.max("w")).first()[0] or 0).bit_length()
        names = [x.split()[0] for x in ROWS.split(", ")]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                off = b.column(2).offsets.to_numpy().astype(np.int64)
                begin = off - off[0]
                u = b.column(2).values.to_numpy()[off[0] : off[-1]].astype(np.int64) - 1
                lo = b.column(3).offsets.to_numpy()
                w = b.column(3).values.to_numpy()[lo[0] : lo[-1]].astype(np.int64)
                if len(w) and w.min() < 0:
                    raise ValueError("weights must not be negative")
                d = np.diff(begin)
                a, c = (_top(u, begin), _top(w, begin)) if local else (np.full(len(d), n), np.full(len(d), widest))
                if len(d) and int((a + c).max()) > MOST:
                    raise ValueError(f"an identifier and a weight need more than {MOST} bits")
                payloads = pack((w << np.repeat(a, d)) | u, a + c, begin)
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(d, pa.int64()), pa.array(a, pa.int32()), pa.array(c, pa.int32()), pa.array(payloads, pa.binary())], names=names)

        return cls(g, written(g.adjacency(chunk).select("v", "chunk", "nbrs", "ws").mapInArrow(run, ROWS), "weighted"), chunk)

    def cells(self, rows: DataFrame | None = None) -> DataFrame:
        """(v, u, w), decoded."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                v, d, a, c = (b.column(k).to_numpy().astype(np.int64) for k in range(4))
                x = unpack(b.column(4).to_pylist(), a + c, np.concatenate([[0], np.cumsum(d)]))
                a = np.repeat(a, d)
                yield pa.RecordBatch.from_arrays([pa.array(y, pa.int64()) for y in (np.repeat(v, d), (x & ((1 << a) - 1)) + 1, x >> a)], names=["v", "u", "w"])

        return (self.rows if rows is None else rows).select("v", "d", "id_width", "w_width", "payload").mapInArrow(run, "v long, u long, w long")

    def edge_at(self, asked: DataFrame) -> DataFrame:
        """(v, i, u, w) of the i-th edges (from 1) of vertices: one field each; i beyond a list gives no row."""
        want = asked.select("v", "i", F.floor((F.col("i") - 1) / self.chunk).cast("int").alias("chunk"))
        step = self.chunk

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                out = []
                for v, i, a, c, raw in zip(*(col.to_pylist() for col in b.columns)):
                    x = field(raw, a + c, (i - 1) % step)
                    out.append((v, i, (x & ((1 << a) - 1)) + 1, x >> a))
                yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in out], pa.int64()) for k in range(4)], names=["v", "i", "u", "w"])

        joined = self.rows.join(want, ["v", "chunk"]).where(F.pmod(F.col("i") - 1, F.lit(step)) < F.col("d"))
        return joined.select("v", "i", "id_width", "w_width", "payload").mapInArrow(run, "v long, i long, u long, w long")

    def bits(self) -> DataFrame:
        """payload_bits and rows."""
        return self.rows.agg(F.sum(8 * F.octet_length("payload")).cast("long").alias("payload_bits"), F.count("*").alias("rows"))
