"""Graphs in compressed form: packed adjacency rows and an offset structure; algorithms read cells from them.

Rows are a vertex chunk each (v, chunk, d, width, first, payload), in vertex order within range files. Which transformer is
used is fixed when the plan is built: no row pays for a choice. Transformers whose lists refer to each other (``blocked``) store blocks of
lists; a block is read whole and decodes alone, however files are split and batches cut.

The payloads in vertex order are the array A; ``offsets`` makes the structure O over it, which tells where a list's bytes lie.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..adjacency.permute import apply_degree
from ..adjacency.transform import FixedWidth, FullVarint, GapVarint, PrefixGroups, RefInterval
from ..graphs import derive
from .ids import prefix_sums
from .model import CHUNK, Graph
from .store import written

ROWS = "v long, chunk int, d long, width long, first long, payload binary"
BLOCKS = "block long, v array<long>, chunk array<int>, d array<long>, payload array<binary>"
BLOCK_LISTS = 256
BLOCK_LABELS = 1 << 20
PAGE = 1 << 20


def _lists(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    off = col.offsets.to_numpy()
    return col.values.to_numpy()[off[0] : off[-1]].astype(np.int64), (off - off[0]).astype(np.int64)


def _names(schema: str) -> list[str]:
    return [x.split()[0] for x in schema.split(", ")]


@dataclass
class CompressedGraph:
    """graph: labels as stored; rows: packed lists; transformer: how they are packed; chunk: labels a row; blocks: what is stored if lists refer to each other."""

    graph: Graph
    rows: DataFrame
    transformer: object
    chunk: int = CHUNK
    blocks: DataFrame | None = None

    @classmethod
    def build(cls, g: Graph, transformer, chunk: int = CHUNK, keep: bool = True) -> CompressedGraph:
        transformer = transformer.fitted(g)
        adj = g.adjacency(chunk).select("v", "chunk", "nbrs")
        store = written if keep else lambda df, name: df
        if getattr(transformer, "blocked", False):
            return cls._in_blocks(g, transformer, chunk, adj)
        n = g.n

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                x, begin = _lists(b.column(2))
                payloads, width, first = transformer.encode(x, begin, b.column(0).to_numpy(), n)
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(np.diff(begin), pa.int64()), pa.array(width, pa.int64()), pa.array(np.asarray(first, np.int64)), pa.array(payloads, pa.binary())], names=_names(ROWS))

        return cls(g, store(adj.mapInArrow(run, ROWS), "adjacency"), transformer, chunk)

    @classmethod
    def _in_blocks(cls, g: Graph, transformer, chunk: int, adj: DataFrame) -> CompressedGraph:
        from pyspark import TaskContext

        n = g.n

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            part, k = TaskContext.get().partitionId(), 0
            v, c, lists = [], [], []

            def block() -> pa.RecordBatch:
                nonlocal k
                begin = np.concatenate([[0], np.cumsum([len(x) for x in lists])]).astype(np.int64)
                payloads, _, _ = transformer.encode(np.concatenate(lists), begin, np.array(v), n)
                kinds = [pa.int64(), pa.list_(pa.int64()), pa.list_(pa.int32()), pa.list_(pa.int64()), pa.list_(pa.binary())]
                values = [(part << 32) | k, list(v), list(c), np.diff(begin).tolist(), payloads]
                k += 1
                v.clear(), c.clear(), lists.clear()
                return pa.RecordBatch.from_arrays([pa.array([x], t) for x, t in zip(values, kinds)], names=_names(BLOCKS))

            for b in batches:
                for i, j, x in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2)):
                    v.append(i), c.append(j), lists.append(x.values.to_numpy().astype(np.int64))
                    if len(v) == BLOCK_LISTS or sum(map(len, lists)) >= BLOCK_LABELS:
                        yield block()
            if v:
                yield block()

        ordered = adj.repartitionByRange("v", "chunk").sortWithinPartitions("v", "chunk")  # neighbours in order refer to each other
        blocks = written(ordered.mapInArrow(run, BLOCKS), "blocks")
        one = blocks.select(F.explode(F.arrays_zip("v", "chunk", "d", "payload")).alias("x")).select("x.v", "x.chunk", "x.d", F.lit(0).cast("long").alias("width"), F.lit(0).cast("long").alias("first"), "x.payload")
        return cls(g, one, transformer, chunk, blocks)

    def decode(self, rows: DataFrame) -> DataFrame:
        """(v, u) of packed rows; narrow. Rows of transformers that are not ``blocked``."""
        transformer, n = self.transformer, self.graph.n

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                v, d = b.column(0).to_numpy(), b.column(2).to_numpy()
                u = transformer.decode(b.column(5).to_pylist(), b.column(3).to_numpy(), b.column(4).to_numpy(), d, v, n)
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(v, d), pa.int64()), pa.array(u, pa.int64())], names=["v", "u"])

        return rows.select("v", "chunk", "d", "width", "first", "payload").mapInArrow(run, "v long, u long")

    def _from_blocks(self, asked: DataFrame | None) -> DataFrame:
        """(v, i, u) of the asked vertices, or of all: whole blocks are decoded."""
        transformer, n, step = self.transformer, self.graph.n, self.chunk
        if asked is None:
            picked = self.blocks.withColumn("want", F.lit(None).cast("array<long>"))
        else:
            held = self.blocks.select("block", F.explode("v").alias("v")).join(asked.select("v").distinct(), "v")
            picked = self.blocks.join(held.groupBy("block").agg(F.collect_set("v").alias("want")), "block")  # no more than a block's lists

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for v, chunk, d, payload, want in zip(*(c.to_pylist() for c in b.columns)):
                    v, d = np.array(v, np.int64), np.array(d, np.int64)
                    u = transformer.decode(payload, None, None, d, v, n)
                    begin = np.cumsum(d) - d
                    i = np.arange(len(u)) - np.repeat(begin, d) + step * np.repeat(np.array(chunk, np.int64), d) + 1
                    row = np.repeat(v, d)
                    keep = slice(None) if want is None else np.isin(row, want)
                    yield pa.RecordBatch.from_arrays([pa.array(x[keep], pa.int64()) for x in (row, i, u)], names=["v", "i", "u"])

        return picked.select("v", "chunk", "d", "payload", "want").mapInArrow(run, "v long, i long, u long")

    def cells(self) -> DataFrame:
        """All (v, u), decoded."""
        return self.decode(self.rows) if self.blocks is None else self._from_blocks(None).select("v", "u")

    def neighbors(self, asked: DataFrame) -> DataFrame:
        """(v, u) of the asked vertices (v): packed rows, or blocks, are picked before anything is decoded."""
        if self.blocks is not None:
            return self._from_blocks(asked).select("v", "u")
        return self.decode(self.rows.join(asked.select("v").distinct(), "v", "left_semi"))

    def degree(self, asked: DataFrame) -> DataFrame:
        """(v, d), from the rows' counts alone: payloads are not read."""
        return asked.join(self.rows.groupBy("v").agg(F.sum("d").alias("d")), "v", "left").select("v", F.coalesce("d", F.lit(0)).alias("d"))

    def edge_at(self, asked: DataFrame) -> DataFrame:
        """(v, i, u): the i-th neighbour (from 1), one field for fixed widths; null beyond the list.

        A chunk is found by its place; with gaps or variable lengths the chunk is decoded up to i.
        """
        from ..bits.pack import field

        if self.blocks is not None:
            known = asked.join(self.degree(asked.select("v").distinct()).where("d > 0").select("v"), "v", "left_semi")
            return known.join(self._from_blocks(asked), ["v", "i"], "left").select("v", "i", "u")
        transformer, n, step = self.transformer, self.graph.n, self.chunk
        direct = isinstance(transformer, FixedWidth) and not transformer.gap
        want = asked.select("v", "i", F.floor((F.col("i") - 1) / step).cast("int").alias("chunk"))
        joined = self.rows.join(want, ["v", "chunk"]).select("v", "i", "d", "width", "first", "payload")

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                v, i, d, width, first = (b.column(k).to_numpy() for k in range(5))
                at = (i - 1) % step
                out = []
                for k, raw in enumerate(b.column(5).to_pylist()):
                    if at[k] >= d[k]:
                        out.append(None)
                    elif direct:
                        out.append(field(raw, int(width[k]), int(at[k])) + 1)
                    else:
                        out.append(int(transformer.decode([raw], width[k : k + 1], first[k : k + 1], d[k : k + 1], v[k : k + 1], n)[at[k]]))
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(out, pa.int64())], names=["v", "i", "u"])

        return joined.mapInArrow(run, "v long, i long, u long")

    def has_edge(self, pairs: DataFrame) -> DataFrame:
        """(v, u, found) of the asked pairs: only lists of asked vertices are decoded."""
        there = self.neighbors(pairs).withColumn("found", F.lit(True))
        return pairs.join(there, ["v", "u"], "left").select("v", "u", F.coalesce("found", F.lit(False)).alias("found"))

    def bits(self) -> DataFrame:
        """payload_bits, side_bits (widths and first labels that stand beside payloads) and rows: what is really written."""
        width, first = self.transformer.side_bits(self.graph.n)
        return self.rows.agg(F.sum(8 * F.octet_length("payload")).cast("long").alias("payload_bits"), (F.count("*") * (width + first)).alias("side_bits"), F.count("*").alias("rows"))

    def offsets(self, kind: str = "sparse", size: int = 1 << 16) -> DataFrame:
        """O over A, stored: for each range of vertices a structure that gives the byte in A where a list begins."""
        from ..offsets.access import build

        per = self.rows.groupBy("v").agg(F.sum(F.octet_length("payload")).alias("bytes"))
        every = self.graph.vertices().select(F.col("id").alias("v")).join(per, "v", "left")
        blocks = every.select("v", F.greatest(F.coalesce("bytes", F.lit(0)), F.lit(1)).cast("long").alias("blocks"))  # an empty list has a byte, so that no two begin together
        return written(build(prefix_sums(blocks, [F.col("v")], "blocks"), kind, size), "offsets")

    def array(self, size: int = PAGE) -> DataFrame:
        """A, stored: (page, at, v, width, first, d, payload) pieces by the page that a row's first byte is on."""
        chunks = self.rows.select("v", "chunk", "d", "width", "first", "payload", F.octet_length("payload").cast("long").alias("blocks"))
        spare = self.graph.vertices().select(F.col("id").alias("v")).join(self.rows.select("v").distinct(), "v", "left_anti")
        gap = spare.select("v", F.lit(0).alias("chunk"), F.lit(0).cast("long").alias("d"), F.lit(0).cast("long").alias("width"), F.lit(0).cast("long").alias("first"), F.unhex(F.lit("00")).alias("payload"), F.lit(1).cast("long").alias("blocks"))
        placed = prefix_sums(chunks.unionByName(gap), [F.col("v"), F.col("chunk")], "blocks")
        return written(placed.select(F.floor(F.col("off") / size).cast("long").alias("page"), F.col("off").alias("at"), "v", "d", "width", "first", "payload"), "array")

    def neighbors_by_offset(self, asked: DataFrame, o: DataFrame, a: DataFrame, kind: str = "sparse", size: int = 1 << 16, page: int = PAGE) -> DataFrame:
        """(v, u) of the asked vertices through O and A: select gives a list's byte, its page is read, what begins there is decoded.

        Lists of one row (``chunk`` or fewer labels) of transformers that are not ``blocked``; longer ones continue in the rows that follow.
        """
        from ..offsets.access import select

        found = select(o, kind, asked.select("v").distinct(), size).select(F.floor(F.col("off") / page).cast("long").alias("page"), F.col("off").alias("at"))
        rows = a.join(found, ["page", "at"]).where("d > 0").select("v", F.lit(0).alias("chunk"), "d", "width", "first", "payload")
        return self.decode(rows)


TRANSFORMERS = {"global": FixedWidth(False), "local": FixedWidth(True), "global_gap": FixedWidth(False, True), "local_gap": FixedWidth(True, True), "full_varint": FullVarint(), "gap_varint": GapVarint(), "ref_interval": RefInterval()}


def _round_trip(name: str, graph: str):
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        g = derive.load(spark, sf_dir, graph)
        return CompressedGraph.build(g, TRANSFORMERS[name], 64 if name != "ref_interval" else CHUNK).cells()

    return query


def _prefix(near: bool):
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        g = derive.load(spark, sf_dir, "g_page_link")
        return CompressedGraph.build(g, PrefixGroups(3, max(g.n - 1, 1).bit_length(), near)).cells()

    return query


def _asked(spark: SparkSession, sf_dir: str, seed: int = 1) -> tuple[CompressedGraph, DataFrame]:
    from ..offsets.access import chosen

    g = derive.load(spark, sf_dir, "g_cust_part")
    return CompressedGraph.build(g, TRANSFORMERS["local"]), written(chosen(g, 1000, seed), "asked")


def access_neighbors(spark: SparkSession, sf_dir: str) -> DataFrame:
    cg, asked = _asked(spark, sf_dir)
    return cg.neighbors(asked)


def access_degree(spark: SparkSession, sf_dir: str) -> DataFrame:
    cg, asked = _asked(spark, sf_dir)
    return cg.degree(asked)


def access_edge_at(spark: SparkSession, sf_dir: str) -> DataFrame:
    cg, asked = _asked(spark, sf_dir)
    return cg.edge_at(asked.select("v", F.explode(F.array(*(F.lit(i).cast("long") for i in (1, 2, 5)))).alias("i"))).where("u IS NOT NULL")


def access_has_edge(spark: SparkSession, sf_dir: str) -> DataFrame:
    cg, asked = _asked(spark, sf_dir)
    pairs = asked.select("v", F.explode(F.array(F.col("v") + 1, F.lit(1501).cast("long"), F.lit(3).cast("long"))).alias("u")).distinct()
    return cg.has_edge(pairs)


def access_by_offset(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Neighbours of the asked vertices, read through stored offsets."""
    cg, asked = _asked(spark, sf_dir)
    return cg.neighbors_by_offset(asked, cg.offsets(), cg.array())


def _ref(spark: SparkSession, sf_dir: str) -> tuple[CompressedGraph, DataFrame]:
    g = derive.load(spark, sf_dir, "g_cust_part")
    from ..offsets.access import chosen

    return CompressedGraph.build(g, TRANSFORMERS["ref_interval"]), written(chosen(g, 1000, 1), "asked")


def refint_neighbors(spark: SparkSession, sf_dir: str) -> DataFrame:
    cg, asked = _ref(spark, sf_dir)
    return cg.neighbors(asked)


def refint_edge_at(spark: SparkSession, sf_dir: str) -> DataFrame:
    cg, asked = _ref(spark, sf_dir)
    return cg.edge_at(asked.select("v", F.explode(F.array(*(F.lit(i).cast("long") for i in (1, 2, 5)))).alias("i"))).where("u IS NOT NULL")


def refint_has_edge(spark: SparkSession, sf_dir: str) -> DataFrame:
    cg, asked = _ref(spark, sf_dir)
    pairs = asked.select("v", F.explode(F.array(F.col("v") + 1, F.lit(1501).cast("long"), F.lit(3).cast("long"))).alias("u")).distinct()
    return cg.has_edge(pairs)


def access_weight(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Weights packed beside neighbours, decoded from both ends."""
    from .weighted import WeightedGraph

    return WeightedGraph.build(derive.load(spark, sf_dir, "g_part_supp")).cells()


def access_weight_at(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The second edge and its weight of each vertex that has one: a field each."""
    from .weighted import WeightedGraph

    g = derive.load(spark, sf_dir, "g_part_supp")
    return WeightedGraph.build(g, False).edge_at(g.vertices().select(F.col("id").alias("v"), F.lit(2).cast("long").alias("i")))


def aa_lists(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = derive.load(spark, sf_dir, "g_page_link")
    return g.adjacency().select("v", "d", F.md5(F.array_join(F.transform("nbrs", lambda x: x.cast("string")), ",")).alias("list_md5"))


def pack_bits_hash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The bit string of each stored list (fields of the list's width, high bit first), read from the packed bytes, as its digest."""
    import hashlib

    from ..bits.pack import unpack

    cg = CompressedGraph.build(derive.load(spark, sf_dir, "g_part_supp"), TRANSFORMERS["local"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for d, w, raw in zip(*(b.column(k).to_pylist() for k in (1, 2, 3))):
                x = unpack([raw], np.array([w]), np.array([0, d])).tolist()
                out.append(hashlib.md5("".join(format(y, f"0{w}b") if w else "" for y in x).encode()).hexdigest())
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), pa.array(out, pa.string())], names=["v", "w", "bits_md5"])

    return cg.rows.select("v", "d", "width", "payload").mapInArrow(run, "v long, w long, bits_md5 string")


def graph_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    return derive.load(spark, sf_dir, "g_page_link").cells()


def dmd_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Degree labels and gaps, decoded: the relabelled cells."""
    return CompressedGraph.build(apply_degree(derive.load(spark, sf_dir, "g_page_link")), GapVarint()).cells()


_ASK = "dg AS (SELECT v, count(*) AS d FROM cells GROUP BY v), ids AS (SELECT unnest(range(1, (SELECT n FROM nv) + 1)) AS v), ask AS (SELECT v FROM ids ORDER BY md5('1:' || v), v LIMIT 1000)"
_CELLS = derive.with_graph("g_page_link") + "SELECT v, u FROM cells"
QUERIES = {f"roundtrip_{k}": _round_trip(k, "g_page_link") for k in TRANSFORMERS} | {"roundtrip_prefix": _prefix(False), "roundtrip_prefix_near": _prefix(True)}
ORACLES = {k: _CELLS for k in QUERIES}
QUERIES |= {"refint_neighbors": refint_neighbors, "refint_edge_at": refint_edge_at, "refint_has_edge": refint_has_edge, "access_by_offset": access_by_offset, "access_weight_at": access_weight_at}
QUERIES |= {"access_neighbors": access_neighbors, "access_degree": access_degree, "access_edge_at": access_edge_at, "access_has_edge": access_has_edge, "access_weight": access_weight, "aa_lists": aa_lists, "pack_bits_hash": pack_bits_hash, "graph_cells": graph_cells, "dmd_roundtrip": dmd_roundtrip}
QUERIES |= {f"graph_edges_{k[2:]}": (lambda name: lambda s, d: derive.load(s, d, name).edges)(k) for k in derive.SQL}
QUERIES |= {"graph_knn": lambda s, d: derive.load(s, d, "g_knn").edges}
ORACLES |= {f"graph_edges_{k[2:]}": derive.with_graph(k) + "SELECT src, dst, w FROM edges" for k in derive.SQL}
ORACLES |= {
    "access_neighbors": derive.with_graph("g_cust_part", _ASK) + "SELECT cells.v, u FROM cells JOIN ask ON ask.v = cells.v",
    "access_degree": derive.with_graph("g_cust_part", _ASK) + "SELECT ask.v, coalesce(d, 0) AS d FROM ask LEFT JOIN dg ON dg.v = ask.v",
    "access_edge_at": derive.with_graph("g_cust_part", _ASK) + "SELECT v, i, u FROM (SELECT cells.v, u, row_number() OVER (PARTITION BY cells.v ORDER BY u) AS i FROM cells JOIN ask ON ask.v = cells.v) q WHERE i IN (1, 2, 5)",
    "access_has_edge": derive.with_graph("g_cust_part", _ASK) + "SELECT p.v, p.u, c.v IS NOT NULL AS found FROM (SELECT v, v + 1 AS u FROM ask UNION SELECT v, 1501 FROM ask UNION SELECT v, 3 FROM ask) p LEFT JOIN cells c ON c.v = p.v AND c.u = p.u",
    "access_weight_at": derive.with_graph("g_part_supp") + "SELECT v, CAST(2 AS BIGINT) AS i, u, w FROM (SELECT v, u, w, row_number() OVER (PARTITION BY v ORDER BY u) AS k FROM cells) q WHERE k = 2",
    "access_weight": derive.with_graph("g_part_supp") + "SELECT v, u, w FROM cells",
    "access_by_offset": derive.with_graph("g_cust_part", _ASK) + "SELECT cells.v, u FROM cells JOIN ask ON ask.v = cells.v",
    "aa_lists": derive.with_graph("g_page_link") + "SELECT v, count(*) AS d, md5(string_agg(CAST(u AS VARCHAR), ',' ORDER BY u)) AS list_md5 FROM cells GROUP BY v",
    "pack_bits_hash": derive.with_graph("g_part_supp", "pw AS (SELECT v, CASE WHEN max(u) <= 1 THEN 0 ELSE length(bin(max(u) - 1)) END AS w FROM cells GROUP BY v)") + "SELECT cells.v, any_value(pw.w) AS w, md5(string_agg(lpad(bin(u - 1), CAST(pw.w AS INTEGER), '0'), '' ORDER BY u)) AS bits_md5 FROM cells JOIN pw ON pw.v = cells.v GROUP BY cells.v",
    "graph_cells": derive.with_graph("g_page_link") + "SELECT v, u, w FROM cells",
    "dmd_roundtrip": derive.with_graph("g_page_link", "dg AS (SELECT v, count(*) AS d FROM cells GROUP BY v), pm AS (SELECT v AS id, row_number() OVER (ORDER BY d DESC, v) AS new_id FROM dg)") + "SELECT a.new_id AS v, b.new_id AS u FROM cells JOIN pm a ON a.id = v JOIN pm b ON b.id = u",
}
ORACLES |= {f"refint_{k}": ORACLES[f"access_{k}"] for k in ("neighbors", "edge_at", "has_edge")}
