"""Adjacency schemes side by side, coded bytes, reference candidates and searches on compressed forms."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..adjacency.arrange import arrangement_cost
from ..adjacency.bisect import bisect, cmb_permuter, rb_permuter, vertex_cut
from ..adjacency.permute import apply_degree, hash_permuter
from ..algos.traverse import _SSSP_SQL, bfs, bfs_sql, load, sssp
from ..bits.width import varint_bits
from ..core.compressed import TRANSFORMERS, CompressedGraph
from ..core.ids import assign_ids
from ..core.store import written
from ..core.weighted import WeightedGraph
from ..fine.sizes import ALL, CODECS, DEGREE_SQL, _sql, _union, row_by_row, sizes, stored
from ..graphs import derive

ONLY = {k: CODECS[k] for k in ("trad32", "varint", "gap_varint")}


def exp_adj_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Plain, full and gap-coded sizes under given and degree labels, on all table graphs."""
    frames = []
    for k in ALL:
        with stored(spark, sf_dir, k) as g:
            frames.append(row_by_row(sizes(g, ONLY)).withColumn("labels", F.lit("given")))
            frames.append(row_by_row(sizes(apply_degree(g), ONLY)).withColumn("labels", F.lit("degree")))
    return _union(frames)


def size_gap_random(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Gap coding under a random order: what labels are worth."""
    g = derive.load(spark, sf_dir, "g_page_link")
    return sizes(g.relabel(hash_permuter(g)), {"gap_varint": CODECS["gap_varint"]})


def size_rb(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Gap coding under given, random, degree and bisection labels of one graph."""
    g = derive.load(spark, sf_dir, "g_user_next")
    only = {"gap_varint": CODECS["gap_varint"]}
    forms = {"given": g, "random": g.relabel(hash_permuter(g)), "degree": apply_degree(g), "bisection": g.relabel(written(rb_permuter(g, 2), "perm"))}
    return _union([sizes(x, only).withColumn("labels", F.lit(k)) for k, x in forms.items()])


def size_brb(spark: SparkSession, sf_dir: str, levels: int = 3) -> DataFrame:
    """Bits of prefix groups under given labels: group count, then prefix and count of each, then stripped suffixes in whole bytes."""
    g = derive.load(spark, sf_dir, "g_page_link")
    low = max((g.n - 1).bit_length() - levels, 0)
    groups = g.cells().withColumn("p", F.shiftright(F.col("u") - 1, low)).groupBy("v", "p").agg(F.count("*").alias("c"))
    per = groups.groupBy("v").agg(F.count("*").alias("k"), F.sum("c").alias("d"), F.sum(F.expr(f"{varint_bits('p')} + {varint_bits('c')}")).alias("h"))
    return per.agg(F.sum(F.expr(f"{varint_bits('k')} + h + 8 * ((d * {low} + 7) div 8)")).cast("long").alias("bits"))


def dmd_bytes_hash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The coded bytes of each list under degree labels, as digests of their hexadecimal form."""
    cg = CompressedGraph.build(apply_degree(derive.load(spark, sf_dir, "g_page_link")), TRANSFORMERS["gap_varint"])
    return cg.rows.select("v", F.md5(F.hex("payload")).alias("bytes_md5"))


def refint_intervals(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(v, start, length) of runs of four or more consecutive neighbours."""
    c = derive.load(spark, sf_dir, "g_copurchase").cells()
    k = F.col("u") - F.row_number().over(Window.partitionBy("v").orderBy("u"))
    return c.withColumn("g", k).groupBy("v", "g").agg(F.min("u").alias("start"), F.count("*").alias("length")).where("length >= 4").drop("g")


def refint_best_overlap(spark: SparkSession, sf_dir: str, window: int = 7) -> DataFrame:
    """(v, back, shared): the earlier list, at most ``window`` before, that shares most (ties: the nearest). Lists meet by neighbour and by a block of ids, so no
    hub pairs all of its neighbours."""
    c = derive.load(spark, sf_dir, "g_page_link").cells().select("v", "u")
    size = window + 1
    a = c.withColumn("b", F.explode(F.array(F.floor(F.col("v") / size), F.floor(F.col("v") / size) - 1)))
    b = c.select(F.col("v").alias("r"), "u", F.floor(F.col("v") / size).alias("b"))
    met = a.join(b, ["u", "b"]).where((F.col("v") - F.col("r")).between(1, window)).groupBy("v", (F.col("v") - F.col("r")).alias("back")).agg(F.count("*").alias("shared"))
    best = met.groupBy("v").agg(F.max(F.struct("shared", (-F.col("back")).alias("near"))).alias("m"))
    return best.select("v", (-F.col("m.near")).alias("back"), F.col("m.shared").alias("shared"))


def graph_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    return assign_ids(derive.page_links(spark, sf_dir).select("href").distinct(), "href")


def bfs_push_pull(spark: SparkSession, sf_dir: str) -> DataFrame:
    cells = load(spark, sf_dir, "g_page_link", "local")[1]
    return bfs(cells, 1, "push").withColumnRenamed("dist", "push").join(bfs(cells, 1, "pull").withColumnRenamed("dist", "pull"), "id")


def exp_sssp_local(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Shortest paths on list-wise identifiers with their weights packed beside them."""
    return sssp(written(WeightedGraph.build(derive.load(spark, sf_dir, "g_part_supp")).cells(), "cells"), 1)


def udaf_bitvector(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each list as words of a bit vector of 60 bits, by a built-in aggregate."""
    c = derive.load(spark, sf_dir, "g_page_link").cells()
    return c.groupBy("v", F.expr("u div 60").alias("word")).agg(F.bit_or(F.expr("shiftleft(1L, cast(u % 60 as int))")).alias("bits"))


def cmb_dm_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Gap cost of combined labels: three halvings by id, then degrees inside each cluster."""
    g = derive.load(spark, sf_dir, "g_page_link")
    return arrangement_cost(g, written(cmb_permuter(g, 3, "dm", 0), "perm"), "mgapa")


def cmb_dm_cost_refined(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same after three refined cuts."""
    g = derive.load(spark, sf_dir, "g_page_link")
    return arrangement_cost(g, written(cmb_permuter(g, 3, "dm"), "perm"), "mgapa")


def vertex_cut_level1(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = derive.load(spark, sf_dir, "g_page_link")
    return vertex_cut(g, bisect(g, 1, 2).withColumnRenamed("path", "side"))


QUERIES = {f.__name__: f for f in (exp_adj_sizes, size_gap_random, size_rb, size_brb, dmd_bytes_hash, refint_intervals, refint_best_overlap, graph_ids, bfs_push_pull, exp_sssp_local, udaf_bitvector, cmb_dm_cost, cmb_dm_cost_refined, vertex_cut_level1)}
QUERIES["refint_roundtrip"] = lambda s, d: CompressedGraph.build(derive.load(s, d, "g_part_supp"), TRANSFORMERS["ref_interval"]).cells()
_X = "printf('%02X', CAST({} AS INTEGER))"
_BYTES = f"CASE WHEN z < 128 THEN {_X.format('z')} WHEN z < 16384 THEN {_X.format('z % 128 + 128')} || {_X.format('z // 128')} ELSE {_X.format('z % 128 + 128')} || {_X.format('z // 128 % 128 + 128')} || {_X.format('z // 16384')} END"
_HALF = "CASE WHEN 2 * (row_number() OVER (PARTITION BY {p} ORDER BY id) - 1) < count(*) OVER (PARTITION BY {p}) THEN '0' ELSE '1' END"
_L3 = f"ids AS (SELECT unnest(range(1, (SELECT n FROM nv) + 1)) AS id), l1 AS (SELECT id, {_HALF.format(p='1')} AS p FROM ids), l2 AS (SELECT id, p || {_HALF.format(p='p')} AS p FROM l1), l3 AS (SELECT id, p || {_HALF.format(p='p')} AS p FROM l2)"
ORACLES = {
    "exp_adj_sizes": f"SELECT graph, codec, bits, 'given' AS labels FROM ({_sql(ALL, ONLY)}) a UNION ALL SELECT graph, codec, bits, 'degree' FROM ({_sql(ALL, ONLY, DEGREE_SQL, 'rc')}) b",
    "size_gap_random": _sql(("g_page_link",), {"gap_varint": CODECS["gap_varint"]}, "pm AS (SELECT id, row_number() OVER (ORDER BY md5('1:' || id), id) AS new_id FROM (SELECT unnest(range(1, (SELECT n FROM nv) + 1)) AS id) q), rc AS (SELECT a.new_id AS v, b.new_id AS u, w FROM cells JOIN pm a ON a.id = v JOIN pm b ON b.id = u)", "rc"),
    "size_brb": derive.with_graph("g_page_link", f"lo AS (SELECT greatest(length(bin(n - 1)) - 3, 0) AS low FROM nv), gr AS (SELECT v, (u - 1) >> (SELECT low FROM lo) AS p, count(*) AS c FROM cells GROUP BY 1, 2), pv AS (SELECT v, count(*) AS k, sum(c) AS d, sum({varint_bits('p')} + {varint_bits('c')}) AS h FROM gr GROUP BY v)") + f"SELECT CAST(sum({varint_bits('k')} + h + 8 * ((d * low + 7) // 8)) AS BIGINT) AS bits FROM pv, lo",
    "dmd_bytes_hash": derive.with_graph("g_page_link", DEGREE_SQL + ", gp AS (SELECT v, u, u - lag(u) OVER (PARTITION BY v ORDER BY u) AS gap FROM rc), gz AS (SELECT v, u, CASE WHEN gap IS NOT NULL THEN gap WHEN u >= v THEN 2 * (u - v) ELSE 2 * (v - u) - 1 END AS z FROM gp)") + f"SELECT v, md5(string_agg({_BYTES}, '' ORDER BY u)) AS bytes_md5 FROM gz GROUP BY v",
    "refint_intervals": derive.with_graph("g_copurchase") + "SELECT v, min(u) AS start, count(*) AS length FROM (SELECT v, u, u - row_number() OVER (PARTITION BY v ORDER BY u) AS g FROM cells) q GROUP BY v, g HAVING count(*) >= 4",
    "refint_best_overlap": derive.with_graph("g_page_link") + "SELECT v, back, shared FROM (SELECT v, back, shared, row_number() OVER (PARTITION BY v ORDER BY shared DESC, back) AS k FROM (SELECT a.v, a.v - b.v AS back, count(*) AS shared FROM cells a JOIN cells b ON a.u = b.u AND a.v - b.v BETWEEN 1 AND 7 GROUP BY 1, 2) q) z WHERE k = 1",
    "graph_ids": "SELECT href, row_number() OVER (ORDER BY href) AS id FROM (SELECT DISTINCT unnest(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) AS href FROM pages) q",
    "bfs_push_pull": bfs_sql("g_page_link").replace("SELECT id, dist FROM r", "SELECT id, dist AS push, dist AS pull FROM r"),
    "exp_sssp_local": _SSSP_SQL,
    "udaf_bitvector": derive.with_graph("g_page_link") + "SELECT v, u // 60 AS word, bit_or(CAST(1 AS BIGINT) << (u % 60)) AS bits FROM cells GROUP BY 1, 2",
    "cmb_dm_cost": derive.with_graph("g_page_link", _L3 + ", di AS (SELECT v, count(*) AS d FROM cells JOIN l3 a ON a.id = v JOIN l3 b ON b.id = u WHERE a.p = b.p GROUP BY v), pm AS (SELECT l3.id, row_number() OVER (ORDER BY p, coalesce(d, 0) DESC, l3.id) AS new_id FROM l3 LEFT JOIN di ON di.v = l3.id), rc AS (SELECT a.new_id AS v, b.new_id AS u FROM cells JOIN pm a ON a.id = v JOIN pm b ON b.id = u)") + "SELECT CAST(sum(x) AS BIGINT) AS cost FROM (SELECT CASE WHEN lag(u) OVER (PARTITION BY v ORDER BY u) IS NULL THEN abs(u - v) ELSE u - lag(u) OVER (PARTITION BY v ORDER BY u) END AS x FROM rc) q",
    "refint_roundtrip": derive.with_graph("g_part_supp") + "SELECT v, u FROM cells",
}
