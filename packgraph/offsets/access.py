"""Offsets of a graph as structures a vertex range, and select by a join on the range number."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..bits.width import ceil_lg
from ..core.ids import prefix_sums
from ..core.model import Graph
from ..core.store import written
from ..fine.sizes import ALL, DEGREE_SQL, apply_degree
from ..graphs import derive
from .kinds import KINDS

RANGE = 1 << 16


def layout(g: Graph, word_bits: int = 64, block_bits: int = 64) -> DataFrame:
    """(v, blocks, off): the blocks of each list (one at least, so that no two lists start together) and those before it."""
    blocks = F.greatest(F.ceil(F.col("d") * word_bits / block_bits), F.lit(1)).cast("long")
    return prefix_sums(g.degrees().select(F.col("id").alias("v"), blocks.alias("blocks")), [F.col("v")], "blocks")


BUILT = "range_id long, n long, base long, payload_bits long, index_bits long, stored_bits long, payload binary"


def build(offsets: DataFrame, kind: str, size: int = RANGE) -> DataFrame:
    """A structure for each range of ``size`` vertices: all its bytes (``payload``), what its codes and directories count as, and its first offset."""

    def one(t: pa.Table) -> pa.Table:
        t = t.sort_by("v")
        off, blocks = t["off"].to_numpy(), t["blocks"].to_numpy()
        s = KINDS[kind](off - off[0], int(off[-1] - off[0] + blocks[-1]))
        counts = [[len(off)], [int(off[0])], [int(s.payload_bits)], [int(s.index_bits)], [8 * len(s.raw)]]
        return pa.table([t["range_id"].slice(0, 1), *(pa.array(x, pa.int64()) for x in counts), pa.array([s.raw], pa.binary())], names=[x.split()[0] for x in BUILT.split(", ")])

    ranged = offsets.select(F.floor((F.col("v") - 1) / size).cast("long").alias("range_id"), "v", "off", "blocks")
    return ranged.groupBy("range_id").applyInArrow(one, BUILT)


def select(built: DataFrame, kind: str, asked: DataFrame, size: int = RANGE) -> DataFrame:
    """(v, off) of the asked vertices, by select on the bytes of a table of ``build``; only ranges that are asked are opened."""

    def one(t: pa.Table, q: pa.Table) -> pa.Table:
        if not t.num_rows or not q.num_rows:
            return pa.table({"v": pa.array([], pa.int64()), "off": pa.array([], pa.int64())})
        s = KINDS[kind].load(t["payload"][0].as_py())
        v = q["v"].to_numpy()
        return pa.table({"v": v, "off": s.select(v - 1 - size * t["range_id"][0].as_py()).astype(np.int64) + t["base"][0].as_py()})

    key = F.floor((F.col("v") - 1) / size).cast("long").alias("range_id")
    stored = built.select("range_id", "base", "payload")
    return stored.groupBy("range_id").cogroup(asked.select(key, "v").groupBy("range_id")).applyInArrow(one, "v long, off long")


def lg_binomial(n: float, k: float) -> float:
    """log2 C(n, k); the first terms of the expansion where log-gammas would cancel."""
    if k <= 0 or k >= n:
        return 0.0
    if n > 1e12 and k < n / 1e3:
        return (k * math.log(n / k) + k - 0.5 * math.log(2 * math.pi * k) - k * k / (2 * n)) / math.log(2)
    return (math.lgamma(n + 1) - math.lgamma(k + 1) - math.lgamma(n - k + 1)) / math.log(2)


def chosen(g: Graph, k: int = 1000, seed: int = 1) -> DataFrame:
    """k vertices (all if fewer), by a hash: the same in each run."""
    keyed = g.vertices().select(F.col("id").alias("v"), F.md5(F.concat(F.lit(f"{seed}:"), F.col("id").cast("string"))).alias("h"))
    return keyed.orderBy("h", "v").limit(k).select("v")


def _bits(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    return layout(derive.load(spark, sf_dir, name))


def _select(kind: str, graph: str):
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        g = derive.load(spark, sf_dir, graph)
        return select(written(build(layout(g), kind, 512), "offsets"), kind, g.vertices().select(F.col("id").alias("v")), 512)

    return query


_POS = "dg AS (SELECT v, count(*) AS d FROM cells GROUP BY v), ids AS (SELECT unnest(range(1, (SELECT n FROM nv) + 1)) AS v), bl AS (SELECT ids.v, greatest(coalesce(d, 0), 1) AS blocks FROM ids LEFT JOIN dg ON dg.v = ids.v), ps AS (SELECT v, blocks, CAST(sum(blocks) OVER (ORDER BY v) - blocks AS BIGINT) AS off FROM bl)"
_SIZE_COLS = {
    "ptr32": "32 * (n + 1)", "ptr64": "64 * (n + 1)", "ptrlog": f"n * {ceil_lg('c')}", "bvpl": "c", "bvsd": "n * lo + n + (c >> lo) + 1",
}


def size_rows(g: Graph, word_bits: int = 64, block_bits: int = 64) -> DataFrame:
    """graph, kind, bits by the closed forms, from counts alone. c: blocks of the whole array."""
    cells = g.edges.count() * 2
    c = cells * word_bits // block_bits
    low = max(0, (c // g.n).bit_length() - 1) if g.n else 0
    values = {"ptr32": 32 * (g.n + 1), "ptr64": 64 * (g.n + 1), "ptrlog": g.n * (max(cells - 1, 0).bit_length() if cells > 1 else 0), "bvpl": c, "bvsd": g.n * low + g.n + (c >> low) + 1}
    return g.spark.createDataFrame([(g.name, block_bits, k, int(v)) for k, v in values.items()], "graph string, block_bits long, kind string, bits long")


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def _sizes(kinds: tuple[str, ...], graphs=("g_part_supp", "g_road", "g_page_link"), blocks=(64,)):
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        loaded = [derive.load(spark, sf_dir, k) for k in graphs]
        return _union([size_rows(g, 64, b) for g in loaded for b in blocks]).where(F.col("kind").isin(*kinds))

    return query


def _sizes_sql(kinds: tuple[str, ...], graphs=("g_part_supp", "g_road", "g_page_link"), blocks=(64,)) -> str:
    parts = []
    for g in graphs:
        for b in blocks:
            base = f"sz AS (SELECT n, (SELECT count(*) FROM cells) AS cl, (SELECT count(*) FROM cells) * 64 // {b} AS c FROM nv), lw AS (SELECT *, CASE WHEN c // n > 0 THEN length(bin(c // n)) - 1 ELSE 0 END AS lo FROM sz)"
            forms = _SIZE_COLS | {"ptrlog": f"n * {ceil_lg('cl')}"}
            picks = " UNION ALL ".join(f"SELECT '{g}' AS graph, CAST({b} AS BIGINT) AS block_bits, '{k}' AS kind, CAST({forms[k]} AS BIGINT) AS bits FROM lw" for k in kinds)
            parts.append(f"SELECT * FROM ({derive.with_graph(g, base)}{picks})")
    return " UNION ALL ".join(parts)


def entropy_bits(g: Graph) -> DataFrame:
    """Class and index bits of the blocks of 15 of the whole bit vector, from positions alone (one aggregation)."""
    ps = layout(g)
    per = ps.groupBy(F.floor(F.col("off") / 15).alias("b")).agg(F.count("*").alias("c"))
    width = F.expr("CASE c " + " ".join(f"WHEN {c} THEN {(math.comb(15, c) - 1).bit_length()}" for c in range(16)) + " END")
    whole = ps.agg(F.sum("blocks").alias("u"))
    some = per.agg(F.sum(width).alias("i"))
    return some.join(F.broadcast(whole), F.lit(True)).select(F.lit(g.name).alias("graph"), (4 * F.ceil(F.col("u") / 15) + F.coalesce("i", F.lit(0))).cast("long").alias("bits"))


def _entropy(spark: SparkSession, sf_dir: str) -> DataFrame:
    return entropy_bits(derive.load(spark, sf_dir, "g_part_supp"))


def _share(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Offsets against adjacency data (per cent, both plain 32 bits) and mean degrees in hundredths, by graph: sparse ones gain."""
    frames = []
    for k in ALL:
        g = derive.load(spark, sf_dir, k)
        frames.append(g.edges.agg(F.count("*").alias("m")).select(F.lit(k).alias("graph"), F.lit(g.n).cast("long").alias("n"), "m").selectExpr("graph", "n", "m", "100 * m div n AS degree_table_x100", "200 * m div n AS degree_true_x100", "100 * (n + 1) div (2 * m) AS offset_percent"))
    return _union(frames)


def _bound(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Least bits of any offset bit vector: log2 C(U, n)."""
    rows = []
    for k in ("g_part_supp", "g_road", "g_page_link"):
        g = derive.load(spark, sf_dir, k)
        rows.append((k, float(round(lg_binomial(2 * g.edges.count(), g.n)))))
    return spark.createDataFrame(rows, "graph string, bits double")


def _after(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Entropy-coded offsets before and after degree relabelling; arrays do not change."""
    g = derive.load(spark, sf_dir, "g_page_link")
    a, b = entropy_bits(g), entropy_bits(apply_degree(g))
    return a.withColumn("labels", F.lit("given")).unionByName(b.withColumn("labels", F.lit("degree")))


def _zlib(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Measured bits of general compression and of the succinct kinds, by graph."""
    frames = []
    for k in ("g_cust_part", "g_part_supp", "g_road"):
        off = written(layout(derive.load(spark, sf_dir, k)), "layout")
        for kind in ("plain", "sparse", "entropy", "zlib", "zlib_plain", "zlib_blocked"):
            frames.append(build(off, kind).groupBy().agg(F.sum("payload_bits").alias("payload_bits"), F.sum("index_bits").alias("index_bits")).select(F.lit(k).alias("graph"), F.lit(kind).alias("kind"), "payload_bits", "index_bits"))
    return _union(frames)


def _fetch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Offsets of 1,000 chosen vertices through each select."""
    g = derive.load(spark, sf_dir, "g_road")
    off = written(layout(g), "layout")
    asked = written(chosen(g), "asked")
    return _union([select(written(build(off, k), "offsets"), k, asked).withColumn("kind", F.lit(k)) for k in ("ptr64", "plain", "interleaved", "entropy", "sparse")])


_SEL = {"off_select_plain": "plain", "off_select_interleaved": "interleaved", "off_select_entropy": "entropy", "off_select_sparse": "sparse", "off_select_btree": "btree", "off_select_gap": "gap", "off_select_ptr": "ptr64", "off_select_ptrlog": "ptrlog", "off_select_zlib": "zlib_blocked"}
QUERIES = {k: _select(kind, "g_page_link") for k, kind in _SEL.items()} | {
    "aa_offsets": lambda s, d: _bits("g_part_supp", s, d).select("v", "off"), "off_bitvector": lambda s, d: _bits("g_road", s, d).select("v", "off"),
    "off_size_ptr": _sizes(("ptr32", "ptr64")), "off_size_ptrlog": _sizes(("ptrlog",)), "size_ptrlog": _sizes(("ptrlog",), ("g_cust_part",)), "off_size_sparse": _sizes(("bvsd",)), "off_size_entropy": _entropy, "exp_offset_sizes": _sizes(("ptr32", "ptr64", "ptrlog", "bvpl", "bvsd"), ALL),
    "off_block_sweep": _sizes(("bvpl", "bvsd"), ("g_road", "g_cust_order", "g_copurchase"), (8, 16, 32, 64)), "offset_share": _share, "bound_offsets": _bound, "off_after_relabel": _after, "off_zlib": _zlib, "exp_offset_fetch": _fetch,
}
_ENT = "(SELECT 4 * ((sum(blocks) + 14) // 15) FROM {ps}) + (SELECT sum(CASE c " + " ".join(f"WHEN {c} THEN {(math.comb(15, c) - 1).bit_length()}" for c in range(16)) + " END) FROM (SELECT off // 15 AS b, count(*) AS c FROM {ps} GROUP BY 1) q)"
_POS2 = _POS.replace("dg AS", "dg2 AS").replace("FROM cells", "FROM rc").replace("LEFT JOIN dg ON dg.v", "LEFT JOIN dg2 ON dg2.v").replace("bl AS", "bl2 AS").replace("FROM bl)", "FROM bl2)").replace("ps AS", "ps2 AS").replace("ids AS (", "ids2 AS (").replace("FROM ids ", "FROM ids2 AS ids ")
ORACLES = {k: derive.with_graph("g_page_link", _POS) + "SELECT v, off FROM ps" for k in _SEL} | {
    "aa_offsets": derive.with_graph("g_part_supp", _POS) + "SELECT v, off FROM ps", "off_bitvector": derive.with_graph("g_road", _POS) + "SELECT v, off FROM ps",
    "off_size_ptr": _sizes_sql(("ptr32", "ptr64")), "off_size_ptrlog": _sizes_sql(("ptrlog",)), "size_ptrlog": _sizes_sql(("ptrlog",), ("g_cust_part",)), "off_size_sparse": _sizes_sql(("bvsd",)), "exp_offset_sizes": _sizes_sql(("ptr32", "ptr64", "ptrlog", "bvpl", "bvsd"), ALL),
    "off_size_entropy": derive.with_graph("g_part_supp", _POS) + "SELECT 'g_part_supp' AS graph, CAST(" + _ENT.format(ps="ps") + " AS BIGINT) AS bits",
    "off_block_sweep": _sizes_sql(("bvpl", "bvsd"), ("g_road", "g_cust_order", "g_copurchase"), (8, 16, 32, 64)),
    "offset_share": " UNION ALL ".join(f"SELECT * FROM ({derive.with_graph(g)}SELECT '{g}' AS graph, n, m, 100 * m // n AS degree_table_x100, 200 * m // n AS degree_true_x100, 100 * (n + 1) // (2 * m) AS offset_percent FROM nv, (SELECT count(*) AS m FROM edges) q)" for g in ALL),
    "bound_offsets": " UNION ALL ".join(f"SELECT * FROM ({derive.with_graph(g)}SELECT '{g}' AS graph, round((lgamma(c + 1) - lgamma(n + 1) - lgamma(c - n + 1)) / ln(2)) AS bits FROM nv, (SELECT count(*) AS c FROM cells) q)" for g in ("g_part_supp", "g_road", "g_page_link")),
    "off_after_relabel": derive.with_graph("g_page_link", _POS + ", " + DEGREE_SQL.replace("dg AS", "dg3 AS").replace("FROM dg)", "FROM dg3)") + ", " + _POS2) + "SELECT 'g_page_link' AS graph, 'given' AS labels, CAST(" + _ENT.format(ps="ps") + " AS BIGINT) AS bits UNION ALL SELECT 'g_page_link', 'degree', CAST(" + _ENT.format(ps="ps2") + " AS BIGINT)",
    "exp_offset_fetch": derive.with_graph("g_road", _POS + ", ask AS (SELECT v FROM ids ORDER BY md5('1:' || v), v LIMIT 1000)") + "SELECT ps.v, off, kind FROM ps JOIN ask ON ask.v = ps.v, (SELECT unnest(['ptr64', 'plain', 'interleaved', 'entropy', 'sparse']) AS kind) k",
}
