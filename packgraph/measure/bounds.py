"""Storage lower bounds, expected sizes of random graphs, hierarchical sizes and the access-cost model."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..bits.width import ceil_lg
from ..core.machine import MachineModel
from ..core.machine import ceil_lg as int_ceil_lg
from ..core.model import Graph
from ..fine.sizes import ALL, _union, per_vertex
from ..graphs import derive
from ..offsets.access import lg_binomial

SMALL = ("g_part_supp", "g_road", "g_page_link")


def bounds(g: Graph, word_bits: int = 64, block_bits: int = 64) -> DataFrame:
    """graph, entity, bits: least bits of an identifier, an offset, a weight, of all list-wise identifiers, of the offset vector and of the graph."""
    per = per_vertex(g)
    t = per.agg(F.sum("d").alias("c"), F.max("wv").alias("wm"), F.sum(F.expr(f"d * {ceil_lg('mx')}")).alias("local_ids")).first()
    c = t["c"] or 0
    rows = [
        ("vertex id, global", int_ceil_lg(g.n)), ("vertex ids, local", int(t["local_ids"] or 0)), ("offset", int_ceil_lg(c)), ("edge weight", int_ceil_lg(t["wm"] or 0)),
        ("bit vector", int(round(lg_binomial(c * word_bits // block_bits, g.n)))), ("graph", int(round(lg_binomial(g.n * (g.n - 1) / 2, c / 2)))),
    ]
    return g.spark.createDataFrame([(g.name, k, int(v)) for k, v in rows], "graph string, entity string, bits long")


def bound_graph(n: float, m: float) -> float:
    """log2 C(C(n, 2), m)."""
    return lg_binomial(n * (n - 1) / 2, m)


def expected_size_er(n: int, p: float, w_max: int) -> tuple[float, float]:
    """(adjacency bits, offset bits) expected of a uniform random graph."""
    cells = p * n * (n - 1)
    return cells * (math.ceil(math.log2(n)) + math.ceil(math.log2(w_max))), n * math.ceil(math.log2(max(cells, 2)))


def expected_size_powerlaw(n: int, alpha: float, beta: float, w_max: int, base: float = math.e) -> tuple[float, float, float]:
    """(expected edges, adjacency bits, offset bits) when alpha d^-beta vertices have degree d, up to the likely largest degree."""
    top = (alpha * n * math.log(n, base) / (beta - 1)) ** (1 / (beta - 1))
    edges = alpha / 2 * math.log(top) if beta == 2 else alpha / (2 * (2 - beta)) * (top ** (2 - beta) - 1)
    cells = 2 * max(edges, 1)
    return edges, cells * (math.ceil(math.log2(n)) + math.ceil(math.log2(w_max))), n * math.ceil(math.log2(max(cells, 2)))


def _er(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Expected sizes of graphs on as many vertices as the orders up to each, and 256 more; a hundredth of the pairs."""
    t = derive.table(spark, sf_dir, "orders").select((F.col("o_orderkey") + 256).cast("long").alias("n")).withColumn("lg_n", F.expr(ceil_lg("n")).cast("long"))
    cells = F.expr("n * (n - 1) div 100")
    return t.withColumn("cells", cells).select("lg_n", "n", "cells", F.expr(f"cells * ({ceil_lg('n')} + 8)").alias("a_bits"), F.expr(f"n * {ceil_lg('cells')}").alias("o_bits"), F.expr("cells * 40").alias("plain_bits"))


def _powerlaw(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Expected sizes for a few exponents, on as many vertices as the orders up to each, and 256 more; logarithms and powers in double precision,
    edges in whole numbers."""
    t = derive.table(spark, sf_dir, "orders").select((F.col("o_orderkey") + 256).cast("long").alias("n")).withColumn("lg_n", F.expr(ceil_lg("n")).cast("long")).join(F.broadcast(spark.createDataFrame([(2.2,), (2.5,), (3.0,)], "beta double")), F.lit(True))
    t = t.withColumn("top", F.expr("pow(0.5 * n * ln(n) / (beta - 1), 1 / (beta - 1))"))
    t = t.withColumn("edges", F.expr("cast(floor(n * 0.5 / (2 * (2 - beta)) * (pow(top, 2 - beta) - 1)) as bigint)"))
    return t.select("lg_n", "n", "beta", "edges", F.expr(f"2 * edges * ({ceil_lg('n')} + 8)").alias("a_bits"), F.expr(f"n * {ceil_lg('2 * edges')}").alias("o_bits"))


def _curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Packed against 32 + 8 bits a cell over n (a hundredth): the gain shrinks as identifiers grow."""
    return _er(spark, sf_dir).select("n", F.expr("100 * (a_bits + o_bits) div (plain_bits + 32 * (n + 1))").alias("percent_of_plain"))


def _bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _union([bounds(derive.load(spark, sf_dir, k)) for k in SMALL])


def _bound_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = []
    for k in SMALL:
        g = derive.load(spark, sf_dir, k)
        rows.append((k, float(round(bound_graph(g.n, g.edges.count())))))
    return spark.createDataFrame(rows, "graph string, bits double")


def split_ids(g: Graph, elements: int) -> DataFrame:
    """v, element, intra, d, far: a vertex's element and place in it, and how many neighbours are in others."""
    size = -(-g.n // elements)
    c = g.cells().select("v", F.expr(f"(v - 1) div {size}").alias("e"), F.expr(f"(u - 1) div {size}").alias("f"))
    return c.groupBy("v", "e").agg(F.count("*").alias("d"), F.sum(F.when(F.col("e") != F.col("f"), 1).otherwise(0)).alias("far")).select("v", F.col("e").alias("element"), F.expr(f"(v - 1) % {size}").alias("intra"), "d", "far")


def _dist(levels: tuple[int, ...], name: str):
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        rows = []
        for k in SMALL:
            g = derive.load(spark, sf_dir, k)
            m = MachineModel(levels)
            cells = 2 * g.edges.count()
            rows.append((k, m.model_bits(g.n) if len(levels) > 2 else g.n * int_ceil_lg(-(-g.n // levels[-1])) + levels[-1] * int_ceil_lg(levels[-1]), m.physical_bits(g.n, cells)))
        return spark.createDataFrame(rows, "graph string, id_bits long, cell_bits long")

    return query


def _split(spark: SparkSession, sf_dir: str) -> DataFrame:
    return split_ids(derive.load(spark, sf_dir, "g_part_supp"), 4)


def _dist_local(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Intra parts with list-wise widths, in four elements."""
    g = derive.load(spark, sf_dir, "g_part_supp")
    size = -(-g.n // 4)
    per = g.cells().groupBy("v").agg(F.count("*").alias("d"), F.max(F.expr(f"(u - 1) % {size} + 1")).alias("mx"))
    return per.agg(F.sum(F.expr(f"d * {ceil_lg('mx')} + {ceil_lg(ceil_lg('mx'))}")).cast("long").alias("bits"))


def access_model(g: Graph, costs: dict[str, int] | None = None) -> DataFrame:
    """v, edge, neighbours, degree: cycles of reading one field, a list, a degree. Cycle counts of extract, shift, and, add are the
    published 2, 1, 1, 2; those of a cache miss, a multiplication and a subtraction are parameters."""
    t = {"cm": 100, "mul": 3, "sub": 1, "shf": 1, "and": 1, "bxr": 2, "add": 2} | (costs or {})
    edge = 2 * t["cm"] + t["mul"] + t["shf"] + t["and"] + t["bxr"]
    step = t["add"] + t["shf"] + t["and"] + t["bxr"]
    d = g.degrees().where("d > 0")
    return d.select(F.col("id").alias("v"), F.lit(edge).cast("long").alias("edge"), (edge + (F.col("d") - 1) * step).alias("neighbours"), F.lit(2 * t["cm"] + t["sub"]).cast("long").alias("degree"))


def _access(spark: SparkSession, sf_dir: str) -> DataFrame:
    return access_model(derive.load(spark, sf_dir, "g_page_link"))


def _geomean(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Geometric mean of gap-coded to plain sizes by vertex, rounded to 6 places."""
    per = per_vertex(derive.load(spark, sf_dir, "g_part_supp"))
    return per.agg(F.round(F.exp(F.avg(F.log(F.col("gb") / (32 * F.col("d"))))), 6).alias("geomean"))


def _offsets_weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Prices scaled to whole steps of 5 from the least, for weights that are not whole."""
    p = derive.table(spark, sf_dir, "part").select("p_partkey", F.round(F.col("p_retailprice") * 100).cast("long").alias("c"))
    low = p.agg(F.min("c").alias("lo"))
    return p.join(F.broadcast(low), F.lit(True)).select("p_partkey", F.expr("(c - lo) div 500").alias("w"))


QUERIES = {
    "theory_er": _er, "theory_powerlaw": _powerlaw, "theory_curve": _curve, "bounds_fine": _bounds, "bound_graph": _bound_graph, "size_dist_nodes": _dist((1, 4), "nodes"), "size_dist_hier": _dist((1, 5, 25), "hier"),
    "split_ids": _split, "size_dist_local": _dist_local, "access_model": _access, "geomean_gap_ratio": _geomean, "weight_scaled": _offsets_weights,
}
_N = f"(SELECT CAST({ceil_lg('n')} AS BIGINT) AS lg_n, n FROM (SELECT CAST(o_orderkey + 256 AS BIGINT) AS n FROM orders) a)"
_ER = f"SELECT lg_n, n, cells, cells * ({ceil_lg('n')} + 8) AS a_bits, n * {ceil_lg('cells')} AS o_bits, cells * 40 AS plain_bits FROM (SELECT lg_n, n, n * (n - 1) // 100 AS cells FROM {_N} b) c"
_LG = "(lgamma({0} + 1) - lgamma({1} + 1) - lgamma({0} - {1} + 1)) / ln(2)"


def _each(sql: str, more: str = "") -> str:
    return " UNION ALL ".join(f"SELECT * FROM ({derive.with_graph(k, more)}{sql.format(g=k)})" for k in SMALL)


_GAP = "CASE WHEN z = 0 THEN 8 ELSE 8 * ((length(bin(z)) + 6) // 7) END"
ORACLES = {
    "geomean_gap_ratio": derive.with_graph("g_part_supp", "gp AS (SELECT v, u, u - lag(u) OVER (PARTITION BY v ORDER BY u) AS gap FROM cells), zg AS (SELECT v, CASE WHEN gap IS NOT NULL THEN gap WHEN u >= v THEN 2 * (u - v) ELSE 2 * (v - u) - 1 END AS z FROM gp)")
    + f"SELECT round(exp(avg(ln(gb / (32 * d)))), 6) AS geomean FROM (SELECT v, count(*) AS d, sum({_GAP}) AS gb FROM zg GROUP BY v) q",
    "theory_er": _ER,
    "theory_powerlaw": f"SELECT lg_n, n, beta, edges, 2 * edges * ({ceil_lg('n')} + 8) AS a_bits, n * {ceil_lg('2 * edges')} AS o_bits FROM (SELECT lg_n, n, beta, CAST(floor(n * 0.5 / (2 * (2 - beta)) * (pow(top, 2 - beta) - 1)) AS BIGINT) AS edges FROM (SELECT lg_n, n, beta, pow(CAST(0.5 AS DOUBLE) * n * ln(n) / (beta - 1), 1 / (beta - 1)) AS top FROM {_N} b, (SELECT unnest([CAST(2.2 AS DOUBLE), 2.5, 3.0]) AS beta) t) u) v",
    "theory_curve": f"SELECT n, 100 * (a_bits + o_bits) // (plain_bits + 32 * (n + 1)) AS percent_of_plain FROM ({_ER}) z",
    "bounds_fine": _each(
        f"SELECT '{{g}}' AS graph, entity, bits FROM (SELECT 'vertex id, global' AS entity, CAST({ceil_lg('n')} AS BIGINT) AS bits FROM nv UNION ALL SELECT 'vertex ids, local', CAST(sum(d * {ceil_lg('mx')}) AS BIGINT) FROM pv UNION ALL SELECT 'offset', {ceil_lg('c')} FROM tt UNION ALL SELECT 'edge weight', {ceil_lg('wm')} FROM tt UNION ALL SELECT 'bit vector', CAST(round({_LG.format('c', 'n')}) AS BIGINT) FROM tt, nv UNION ALL SELECT 'graph', CAST(round({_LG.format('(CAST(n AS DOUBLE) * (n - 1) / 2)', '(c / 2)')}) AS BIGINT) FROM tt, nv) q",
        "pv AS (SELECT v, count(*) AS d, max(u) AS mx FROM cells GROUP BY v), tt AS (SELECT count(*) AS c, max(w) AS wm FROM cells)",
    ),
    "bound_graph": _each(f"SELECT '{{g}}' AS graph, round({_LG.format('(CAST(n AS DOUBLE) * (n - 1) / 2)', 'm')}) AS bits FROM nv, (SELECT count(*) AS m FROM edges) q"),
    "size_dist_nodes": _each(f"SELECT '{{g}}' AS graph, n * {ceil_lg('(n + 3) // 4')} + 8 AS id_bits, c * {ceil_lg('(n + 3) // 4')} + 8 AS cell_bits FROM nv, (SELECT count(*) AS c FROM cells) q"),
    "size_dist_hier": _each(f"SELECT '{{g}}' AS graph, n * {ceil_lg('(n + 24) // 25')} + 15 AS id_bits, c * {ceil_lg('(n + 24) // 25')} + 15 + 125 AS cell_bits FROM nv, (SELECT count(*) AS c FROM cells) q"),
    "split_ids": derive.with_graph("g_part_supp") + "SELECT v, (v - 1) // s AS element, (v - 1) % s AS intra, count(*) AS d, CAST(sum(CASE WHEN (v - 1) // s <> (u - 1) // s THEN 1 ELSE 0 END) AS BIGINT) AS far FROM cells, (SELECT (n + 3) // 4 AS s FROM nv) q GROUP BY 1, 2, 3",
    "size_dist_local": derive.with_graph("g_part_supp", "pv AS (SELECT v, count(*) AS d, max((u - 1) % s + 1) AS mx FROM cells, (SELECT (n + 3) // 4 AS s FROM nv) q GROUP BY v)") + f"SELECT CAST(sum(d * {ceil_lg('mx')} + {ceil_lg(ceil_lg('mx'))}) AS BIGINT) AS bits FROM pv",
    "access_model": derive.with_graph("g_page_link") + "SELECT v, CAST(207 AS BIGINT) AS edge, 207 + (d - 1) * 6 AS neighbours, CAST(201 AS BIGINT) AS degree FROM (SELECT v, count(*) AS d FROM cells GROUP BY v) q",
    "weight_scaled": "SELECT p_partkey, (c - (SELECT min(CAST(round(p_retailprice * 100) AS BIGINT)) FROM part)) // 500 AS w FROM (SELECT p_partkey, CAST(round(p_retailprice * 100) AS BIGINT) AS c FROM part) q",
}
