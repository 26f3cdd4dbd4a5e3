"""Sizes in bits of the fine-element codecs, in one aggregation over the cells.

All figures of a graph come from one pass: cells are grouped by vertex once (one exchange), and graph-wide maxima are a second,
tiny aggregate joined as a single row.
"""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..adjacency.permute import apply_degree, degree_permuter
from ..bits.width import bit_length, ceil_lg, varint_bits, zigzag
from ..core.model import Graph
from ..core.store import remove, tables, written
from ..graphs import derive
from .relabel import greedy_relabel

#: codec: bits of one vertex (columns d, mx, mg, fg, vb, gb, n, gmax, wmax, wv)
LOCAL = f"d * {ceil_lg('mx')} + {ceil_lg(ceil_lg('mx'))}"
CODECS = {
    "trad32": "32 * d",
    "trad64": "64 * d",
    "global": f"d * {ceil_lg('n')}",
    "local": LOCAL,
    "global_gap": f"{ceil_lg('n')} + (d - 1) * {bit_length('gmax')}",
    "local_gap": f"{ceil_lg('n')} + (d - 1) * {bit_length('mg')} + {ceil_lg(ceil_lg('n') + ' + 1')}",
    "varint": "vb",
    "gap_varint": "gb",
    "weight_global": f"d * ({ceil_lg('n')} + {ceil_lg('wmax')})",
    "weight_local": f"d * ({ceil_lg('mx')} + {ceil_lg('wmax')}) + {ceil_lg(ceil_lg('mx'))} + {ceil_lg(ceil_lg('wmax'))}",
    "weight_local_list": f"d * ({ceil_lg('mx')} + {ceil_lg('wv')}) + {ceil_lg(ceil_lg('mx'))} + {ceil_lg(ceil_lg('wv'))}",
}


def per_vertex(g: Graph) -> DataFrame:
    """v, d, mx (largest neighbour), mg (largest interior gap), vb and gb (varint bits), wv (largest weight)."""
    c = g.consecutive().withColumn("gap", F.col("u") - F.col("before"))
    coded = F.when(F.col("gap").isNull(), F.expr(zigzag("u - v"))).otherwise(F.col("gap"))
    c = c.withColumn("vb", F.expr(varint_bits("u"))).withColumn("z", coded).withColumn("gb", F.expr(varint_bits("z")))
    return c.groupBy("v").agg(F.count("*").alias("d"), F.max("u").alias("mx"), F.coalesce(F.max("gap"), F.lit(0)).alias("mg"), F.sum("vb").alias("vb"), F.sum("gb").alias("gb"), F.max("w").alias("wv"))


def sizes(g: Graph, codecs: dict[str, str] | None = None) -> DataFrame:
    """graph, codec, bits: one row a codec."""
    codecs = codecs or CODECS
    rows = per_vertex(g)
    whole = rows.agg(F.coalesce(F.max("mg"), F.lit(0)).alias("gmax"), F.coalesce(F.max("wv"), F.lit(0)).alias("wmax"))
    all_ = rows.join(F.broadcast(whole), F.lit(True)).withColumn("n", F.lit(g.n).cast("long"))  # one row
    total = all_.agg(*(F.coalesce(F.sum(F.expr(e)), F.lit(0)).cast("long").alias(k) for k, e in codecs.items()))
    names = ", ".join(f"'{k}', {k}" for k in codecs)
    return total.select(F.lit(g.name).alias("graph"), F.expr(f"stack({len(codecs)}, {names}) AS (codec, bits)"))


def sizes_sql(graph: str, codecs: dict[str, str] | None = None, cells: str = "cells") -> str:
    """The same as common table expressions and a query, from edges, nv and cells."""
    codecs = codecs or CODECS
    picks = " UNION ALL ".join(f"SELECT '{graph}' AS graph, '{k}' AS codec, CAST(coalesce(sum({e}), 0) AS BIGINT) AS bits FROM av" for k, e in codecs.items())
    return f"""gp AS (SELECT v, u, w, u - lag(u) OVER (PARTITION BY v ORDER BY u) AS gap FROM {cells}),
gz AS (SELECT v, u, w, gap, CASE WHEN gap IS NULL THEN {zigzag('u - v')} ELSE gap END AS z FROM gp),
pv AS (SELECT v, count(*) AS d, max(u) AS mx, coalesce(max(gap), 0) AS mg, sum({varint_bits('u')}) AS vb, sum({varint_bits('z')}) AS gb, max(w) AS wv FROM gz GROUP BY v),
wh AS (SELECT max(mg) AS gmax, max(wv) AS wmax FROM pv),
av AS (SELECT pv.*, wh.gmax, wh.wmax, nv.n FROM pv, wh, nv) {picks}"""


DEFAULT = ("g_part_supp", "g_page_link")
ALL = ("g_part_supp", "g_cust_part", "g_cust_order", "g_copurchase", "g_road", "g_user_next", "g_doc_tok", "g_page_link")


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


@contextmanager
def stored(spark: SparkSession, sf_dir: str, name: str) -> Iterator[Graph]:
    """A table graph with its edges written, for callers that read them several times; every table made for and of it goes at the end."""
    before = set(tables())
    try:
        g = derive.load(spark, sf_dir, name)
        yield Graph(g.name, g.n, written(g.edges, "edges"))
    finally:
        remove(spark, [x for x in tables() if x not in before])


def row_by_row(few: DataFrame) -> DataFrame:
    """The same few rows, computed now."""
    return few.sparkSession.createDataFrame(few.collect(), few.schema)  # a row a codec


def _one(codec: str):
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        return _union([sizes(derive.load(spark, sf_dir, g), {codec: CODECS[codec]}) for g in DEFAULT])

    return query


def _sql(graphs, codecs: dict[str, str], more: str = "", cells: str = "cells") -> str:
    return " UNION ALL ".join(f"SELECT * FROM ({derive.with_graph(g, (more + ', ' if more else '') + sizes_sql(g, codecs, cells))})" for g in graphs)


def relabelled(g: Graph, how: str) -> Graph:
    return apply_degree(g) if how == "degree" else g.relabel(greedy_relabel(g))


def _relabel(codec: str, how: str, name: str):
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        frames = []
        for k in DEFAULT:
            g = derive.load(spark, sf_dir, k)
            frames.append(sizes(relabelled(g, how), {codec: CODECS[codec]}).withColumn("codec", F.lit(name)))
        return _union(frames)

    return query


DEGREE_SQL = "dg AS (SELECT v, count(*) AS d FROM cells GROUP BY v), pm AS (SELECT v AS id, row_number() OVER (ORDER BY d DESC, v) AS new_id FROM dg), rc AS (SELECT a.new_id AS v, b.new_id AS u, w FROM cells JOIN pm a ON a.id = v JOIN pm b ON b.id = u)"
GREEDY_SQL = "dg AS (SELECT v, count(*) AS d FROM cells GROUP BY v), rk AS (SELECT v, row_number() OVER (ORDER BY d, v) AS r FROM dg), mk AS (SELECT u, min(r) AS r FROM cells JOIN rk USING (v) GROUP BY u), pm AS (SELECT u AS id, row_number() OVER (ORDER BY r, u) AS new_id FROM mk), rc AS (SELECT a.new_id AS v, b.new_id AS u, w FROM cells JOIN pm a ON a.id = v JOIN pm b ON b.id = u)"


def _relabel_sql(codec: str, how: str, name: str) -> str:
    more = DEGREE_SQL if how == "degree" else GREEDY_SQL
    return "SELECT graph, '" + name + "' AS codec, bits FROM (" + _sql(DEFAULT, {codec: CODECS[codec]}, more, "rc") + ") z"


_SINGLE = {
    "size_trad32": "trad32", "size_trad64": "trad64", "size_global": "global", "size_local": "local", "size_global_gap": "global_gap", "size_local_gap": "local_gap",
    "varint_sizes": "varint", "size_gap_varint": "gap_varint", "size_gap_identity": "gap_varint", "size_weight_global": "weight_global", "size_weight_local": "weight_local", "size_weight_local_list": "weight_local_list",
}
_RELABEL = {"size_local_relabel": ("local", "greedy"), "size_local_gap_relabel": ("local_gap", "greedy"), "size_dmf": ("varint", "degree"), "size_dmd": ("gap_varint", "degree")}


def exp_fine_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _union([sizes(derive.load(spark, sf_dir, g)) for g in ALL])


def exp_greedy_gain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Local size before and after greedy relabelling, per table graph."""
    frames = []
    for k in ALL:
        with stored(spark, sf_dir, k) as g:
            a = row_by_row(sizes(g, _only_local)).withColumnRenamed("bits", "before")
            b = row_by_row(sizes(relabelled(g, "greedy"), _only_local)).withColumnRenamed("bits", "after")
            frames.append(a.join(b, ["graph", "codec"]))
    return _union(frames)


def compare_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each codec against 32-bit identifiers: per cent of it (whole, rounded down) and bits an edge (hundredths)."""
    frames = []
    for k in DEFAULT:
        s = sizes(derive.load(spark, sf_dir, k))
        base = s.where("codec = 'trad32'").select("graph", F.col("bits").alias("base"))
        frames.append(s.join(base, "graph").select("graph", "codec", "bits", F.expr("100 * bits div base").alias("percent"), F.expr("6400 * bits div base").alias("bits_per_edge_x100")))
    return _union(frames)


_only_local = {"local": CODECS["local"], "local_gap": CODECS["local_gap"]}
QUERIES = {k: _one(c) for k, c in _SINGLE.items()} | {k: _relabel(c, how, k) for k, (c, how) in _RELABEL.items()} | {"exp_fine_sizes": exp_fine_sizes, "exp_greedy_gain": exp_greedy_gain, "compare_sizes": compare_sizes}
ORACLES = {k: _sql(DEFAULT, {c: CODECS[c]}) for k, c in _SINGLE.items()} | {k: _relabel_sql(c, how, k) for k, (c, how) in _RELABEL.items()}
ORACLES |= {
    "exp_fine_sizes": _sql(ALL, CODECS),
    "exp_greedy_gain": f"SELECT a.graph, a.codec, a.bits AS before, b.bits AS after FROM ({_sql(ALL, _only_local)}) a JOIN ({_sql(ALL, _only_local, GREEDY_SQL, 'rc')}) b ON a.graph = b.graph AND a.codec = b.codec",
    "compare_sizes": f"WITH s AS ({_sql(DEFAULT, CODECS)}) SELECT s.graph, s.codec, s.bits, 100 * s.bits // b.bits AS percent, 6400 * s.bits // b.bits AS bits_per_edge_x100 FROM s JOIN s b ON s.graph = b.graph AND b.codec = 'trad32'",
}
