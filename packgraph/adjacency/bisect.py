"""Recursive bisection, all parts of a level at once, and what is built on it: full and bounded label trees, cuts, combined schemes.

A part is halved by ids to begin with; then, in rounds, vertices of the two sides with the largest joint gains are paired by rank and swapped
(a hash lets about half of the pairs through, against swings). Every round is two joins and one aggregation over all cells, whatever the
number of parts; the smaller side of a cut is never off by more than one vertex unless an imbalance is allowed.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..core.compressed import CompressedGraph
from ..core.ids import global_rank
from ..core.model import Graph
from ..core.store import drop, written
from ..graphs import derive
from .arrange import arrangement_cost, local_search, odb_solve, pod_solve
from .transform import GapVarint


def whole(g: Graph) -> DataFrame:
    """(id, path): all vertices in one part."""
    return g.vertices().select("id", F.lit("").alias("path"))


TASK = 1 << 20  # vertices of a part that one task may rank
PARTS = 100_000  # parts whose bounds may be broadcast; beyond them no part is large


def _ranked(df: DataFrame, keys: list[str], order: list, out: str, most: int) -> DataFrame:
    """Adds the rank (from 1) within ``keys``. Parts beyond ``TASK`` are ranked as ranges of all rows, less what comes before the part."""
    if most <= TASK:
        return df.withColumn(out, F.row_number().over(Window.partitionBy(*keys).orderBy(*order)))
    all_ = global_rank(df, [*(F.col(k) for k in keys), *order], "_all")
    return _by_part(all_, keys, F.min("_all").alias("_from")).withColumn(out, F.col("_all") - F.col("_from") + 1).drop("_all", "_from")


def _by_part(df: DataFrame, keys: list[str], *aggs) -> DataFrame:
    """Adds aggregates over ``keys``, which are combined before they move."""
    per = df.groupBy(*keys).agg(*aggs)
    return df.join(F.broadcast(per) if per.limit(PARTS + 1).count() <= PARTS else per, keys)


def _halved(parts: DataFrame, most: int = 0) -> DataFrame:
    """side 0 or 1 by id within each part."""
    ranked = _by_part(_ranked(parts.select("id", "path"), ["path"], [F.col("id")], "_r", most), ["path"], F.count("*").alias("_c"))
    return ranked.withColumn("side", F.when(2 * (F.col("_r") - 1) < F.col("_c"), 0).otherwise(1)).select("id", "path", "side")


def gains(cells: DataFrame, sides: DataFrame) -> DataFrame:
    """(id, path, side, gain): neighbours of the part on the other side less those on the own side."""
    a = sides.select(F.col("id").alias("v"), F.col("path").alias("pv"), F.col("side").alias("sv"))
    b = sides.select(F.col("id").alias("u"), F.col("path").alias("pu"), F.col("side").alias("su"))
    inside = cells.select("v", "u").join(a, "v").join(b, "u").where("pv = pu")
    gain = inside.groupBy("v").agg(F.sum(F.when(F.col("sv") != F.col("su"), 1).otherwise(-1)).alias("gain"))
    return sides.join(gain, F.col("id") == F.col("v"), "left").select("id", "path", "side", F.coalesce("gain", F.lit(0)).alias("gain"))


def bisect_level(cells: DataFrame, parts: DataFrame, rounds: int = 4, seed: int = 1, imbalance: float = 0.0) -> DataFrame:
    """(id, path) one bit longer. Parts of one vertex stay as they are."""
    marked = written(_by_part(parts, ["path"], F.count("*").alias("c")), "marked")
    done, open_ = marked.where("c = 1").select("id", "path"), marked.where("c > 1").select("id", "path")
    most = marked.agg(F.max("c")).first()[0] or 0
    sides = written(_halved(open_, most), "sides")
    for r in range(rounds):
        g = written(_ranked(gains(cells, sides), ["path", "side"], [F.desc("gain"), F.col("id")], "r", most), "gains")
        pair = g.where("side = 0").select("path", "r", F.col("id").alias("x"), F.col("gain").alias("gx")).join(g.where("side = 1").select("path", "r", F.col("id").alias("y"), F.col("gain").alias("gy")), ["path", "r"])
        coin = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), F.lit(str(r)), "path", "r")), 1, 8), 16, 10).cast("long") % 2 == 0
        moved = pair.where(F.col("gx") + F.col("gy") > 0).where(coin).select(F.explode(F.array("x", "y")).alias("id"))
        if imbalance:
            # beyond pairs, a side may give up to this share of a part's vertices with a gain of their own
            size = g.groupBy("path").agg(F.count("*").alias("c"))
            extra = g.where("gain > 0 AND side = 1").join(size, "path").where(F.col("r") <= F.floor(F.col("c") * imbalance / 2)).select("id")
            moved = moved.union(extra).distinct() if r == rounds - 1 else moved
        moved = written(moved, "moved")
        if moved.isEmpty():
            drop(g), drop(moved)
            break
        new = g.join(moved.withColumn("m", F.lit(1)), "id", "left").select("id", "path", F.when(F.col("m") == 1, 1 - F.col("side")).otherwise(F.col("side")).alias("side"))
        new = written(new, "sides")
        drop(g), drop(moved)
        if cut_size(cells, new) > cut_size(cells, sides):
            drop(new)
            break  # keep the best
        drop(sides)
        sides = new
    # the side of the smaller least id gets bit 0
    first = sides.groupBy("path").agg(F.min(F.struct("id", "side")).alias("f")).select(F.col("path").alias("p"), F.col("f.side").alias("zero"))
    new = sides.join(first, F.col("path") == F.col("p")).select("id", F.concat("path", F.when(F.col("side") == F.col("zero"), "0").otherwise("1")).alias("path"))
    out = written(new.union(done), "parts")
    drop(sides), drop(marked)
    return out


def cut_size(cells: DataFrame, sides: DataFrame) -> int:
    """Edges within parts whose ends are on different sides."""
    a = sides.select(F.col("id").alias("v"), F.col("path").alias("pv"), F.col("side").alias("sv"))
    b = sides.select(F.col("id").alias("u"), F.col("path").alias("pu"), F.col("side").alias("su"))
    return cells.where("v < u").join(a, "v").join(b, "u").where("pv = pu AND sv != su").count()


def bisect(g: Graph, levels: int | None = None, rounds: int = 4, imbalance: float = 0.0) -> DataFrame:
    """(id, path) after ``levels`` cuts, or until each part is one vertex."""
    cells, parts = written(g.cells().select("v", "u"), "cells"), whole(g)
    k = 0
    while levels is None or k < levels:
        parts = bisect_level(cells, parts, rounds, imbalance=imbalance)
        k += 1
        if parts.groupBy("path").count().where("count > 1").isEmpty():
            break
    return parts


def rb_permuter(g: Graph, rounds: int = 4) -> DataFrame:
    """Labels in the order of leaves: visiting leaves in order is sorting their paths."""
    return global_rank(bisect(g, None, rounds), [F.col("path"), F.col("id")], "new_id").select("id", "new_id")


def brb_permuter(g: Graph, levels: int, rounds: int = 4) -> DataFrame:
    """(id, new_id): clusters of ``levels`` cuts in order, ids within; a label's leading part is the cluster."""
    return global_rank(bisect(g, levels, rounds), [F.col("path"), F.col("id")], "new_id").select("id", "new_id")


def cmb_permuter(g: Graph, levels: int, inner: str = "odb", rounds: int = 4) -> DataFrame:
    """Clusters of ``levels`` cuts, each labelled on its own from its inner edges: odb and pod exactly where a cluster is small and by local search
    beyond, dm by degree. A cluster is one task's work; deeper cuts make them smaller."""
    import pyarrow as pa

    parts = written(bisect(g, levels, rounds), "parts")
    path = parts.select(F.col("id").alias("v"), "path")
    inside = g.edges.join(path.select(F.col("v").alias("src"), F.col("path").alias("p")), "src").join(path.select(F.col("v").alias("dst"), F.col("path").alias("q")), "dst").where("p = q").select(F.col("p").alias("path"), "src", "dst")

    def solve(v: pa.Table, e: pa.Table) -> pa.Table:
        ids = sorted(v["id"].to_pylist())
        at = {x: k for k, x in enumerate(ids)}
        edges = [(at[a], at[b]) for a, b in zip(e["src"].to_pylist(), e["dst"].to_pylist())]
        if inner == "dm":
            d = [0] * len(ids)
            for a, b in edges:
                d[a] += 1
                d[b] += 1
            label = [0] * len(ids)
            for k, x in enumerate(sorted(range(len(ids)), key=lambda x: (-d[x], x))):
                label[x] = k + 1
        elif len(ids) <= 8:
            label = (pod_solve if inner == "pod" else odb_solve)(len(ids), edges)[1]
        else:  # both have the same cost: inner gaps telescope
            label = local_search(len(ids), edges)
        return pa.table({"id": ids, "path": [v["path"][0].as_py()] * len(ids), "local": pa.array(label, pa.int64())})

    solved = parts.groupBy("path").cogroup(inside.groupBy("path")).applyInArrow(solve, "id long, path string, local long")
    return global_rank(solved, [F.col("path"), F.col("local")], "new_id").select("id", "new_id")


def cut_profile(g: Graph, parts: DataFrame) -> DataFrame:
    """(level, edge_cut): edges whose ends part at each level of the tree."""
    a, b = parts.select(F.col("id").alias("src"), F.col("path").alias("p")), parts.select(F.col("id").alias("dst"), F.col("path").alias("q"))
    j = g.edges.join(a, "src").join(b, "dst").where("p != q")
    level = F.expr("1 + size(filter(sequence(1, least(length(p), length(q))), i -> substring(p, 1, i) = substring(q, 1, i)))")
    return j.withColumn("level", level.cast("long")).groupBy("level").agg(F.count("*").alias("edge_cut"))


def vertex_cut(g: Graph, sides: DataFrame) -> DataFrame:
    """(id): a set of vertices that covers every cut edge, by rounds: who has the most open cut edges among its cut neighbours, ties by id, is taken."""
    s = sides.select("id", "side")
    open_ = g.cells().select("v", "u").join(s.select(F.col("id").alias("v"), F.col("side").alias("a")), "v").join(s.select(F.col("id").alias("u"), F.col("side").alias("b")), "u").where("a != b").select("v", "u")
    open_, out = written(open_, "open"), None
    while not open_.isEmpty():  # a round takes one vertex at least
        d = open_.groupBy("v").agg(F.count("*").alias("d"))
        rival = open_.join(d.select(F.col("v").alias("u"), F.col("d").alias("du")), "u").groupBy("v").agg(F.max(F.struct("du", (-F.col("u")).alias("nu"))).alias("m"))
        top = written(d.join(rival, "v").where("struct(d, -v) > struct(m.du, m.nu)").select(F.col("v").alias("id")), "top")
        out = top if out is None else out.union(top)
        open_ = written(open_.join(top.select(F.col("id").alias("v")), "v", "left_anti").join(top.select(F.col("id").alias("u")), "u", "left_anti"), "open")
    return out if out is not None else g.spark.createDataFrame([], "id long")


def shadow_pointers(g: Graph, sides: DataFrame) -> DataFrame:
    """edge_cut, vertex_cut (separator vertices) and shadow_pointers: a separator vertex is cloned into both sides, a pointer for each further copy."""
    sep = written(vertex_cut(g, sides), "separator")
    s = sides.select("id", "side")
    cut = g.edges.join(s.select(F.col("id").alias("src"), F.col("side").alias("a")), "src").join(s.select(F.col("id").alias("dst"), F.col("side").alias("b")), "dst").where("a != b")
    return cut.agg(F.count("*").alias("edge_cut")).join(F.broadcast(sep.agg(F.count("*").alias("vertex_cut"))), F.lit(True)).withColumn("shadow_pointers", F.col("vertex_cut"))


def _level1(rounds: int):
    return lambda spark, sf_dir: bisect(derive.load(spark, sf_dir, "g_page_link"), 1, rounds)


def _gains(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Gains of the first halving, the quantity each round ranks."""
    g = derive.load(spark, sf_dir, "g_page_link")
    return gains(g.cells(), _halved(whole(g))).select("id", "side", "gain")


def _rb(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rb_permuter(derive.load(spark, sf_dir, "g_user_next"), 2)


def _brb(spark: SparkSession, sf_dir: str) -> DataFrame:
    return brb_permuter(derive.load(spark, sf_dir, "g_page_link"), 3, 3)


def _cmb(inner: str):
    return lambda spark, sf_dir: cmb_permuter(derive.load(spark, sf_dir, "g_page_link"), 3, inner, 2)


def _profile(rounds: int):
    """Cut edges by level of the tree; without rounds, of the one that halves by id alone."""

    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        g = derive.load(spark, sf_dir, "g_page_link")
        return cut_profile(g, bisect(g, 3, rounds))

    return query


def _imbalance(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = derive.load(spark, sf_dir, "g_page_link")
    out = None
    for d in (0.0, 0.05, 0.2):
        row = cut_profile(g, bisect(g, 1, 3, d)).withColumn("imbalance", F.lit(d))
        out = row if out is None else out.union(row)
    return out


def _shadow(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = derive.load(spark, sf_dir, "g_page_link")
    return shadow_pointers(g, bisect(g, 1, 3).withColumnRenamed("path", "side"))


def _brb_levels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Gap cost and coded bits after 0 to 4 cuts: fewer with depth, each level the work of one more."""
    g, rows = derive.load(spark, sf_dir, "g_page_link"), []
    for k in range(5):
        perm = written(brb_permuter(g, k, 3), "perm")
        bits = CompressedGraph.build(g.relabel(perm), GapVarint()).bits().first()["payload_bits"]
        rows.append((k, int(arrangement_cost(g, perm, "mgapa").first()["cost"]), int(bits)))
    return spark.createDataFrame(rows, "levels long, mgapa long, payload_bits long")


_SIDES = "ids AS (SELECT unnest(range(1, (SELECT n FROM nv) + 1)) AS id), sd AS (SELECT id, CASE WHEN 2 * (row_number() OVER (ORDER BY id) - 1) < (SELECT n FROM nv) THEN 0 ELSE 1 END AS side FROM ids)"
QUERIES = {"rb_level1": _level1(0), "rb_level1_refined": _level1(4), "rb_gains": _gains, "rb_labels": _rb, "brb_prefixes": _brb, "cmb_labels": _cmb("odb"), "cmb_dm_labels": _cmb("dm"), "cut_profile": _profile(0), "cut_profile_refined": _profile(4), "cuts_by_imbalance": _imbalance, "shadow_pointers": _shadow, "exp_brb_levels": _brb_levels}
ORACLES = {
    "rb_level1": derive.with_graph("g_page_link", _SIDES) + "SELECT id, CAST(side AS VARCHAR) AS path FROM sd",
    "rb_gains": derive.with_graph("g_page_link", _SIDES) + "SELECT sd.id, sd.side, CAST(coalesce(g, 0) AS BIGINT) AS gain FROM sd LEFT JOIN (SELECT v, sum(CASE WHEN a.side <> b.side THEN 1 ELSE -1 END) AS g FROM cells JOIN sd a ON a.id = v JOIN sd b ON b.id = u GROUP BY v) q ON q.v = sd.id",
    "cut_profile": derive.with_graph("g_page_link", "ids AS (SELECT unnest(range(1, (SELECT n FROM nv) + 1)) AS id), l1 AS (SELECT id, CASE WHEN 2 * (row_number() OVER (ORDER BY id) - 1) < count(*) OVER () THEN '0' ELSE '1' END AS p FROM ids), l2 AS (SELECT id, p || CASE WHEN 2 * (row_number() OVER (PARTITION BY p ORDER BY id) - 1) < count(*) OVER (PARTITION BY p) THEN '0' ELSE '1' END AS p FROM l1), l3 AS (SELECT id, p || CASE WHEN 2 * (row_number() OVER (PARTITION BY p ORDER BY id) - 1) < count(*) OVER (PARTITION BY p) THEN '0' ELSE '1' END AS p FROM l2)") + "SELECT CAST(CASE WHEN a.p[1] <> b.p[1] THEN 1 WHEN a.p[2] <> b.p[2] THEN 2 ELSE 3 END AS BIGINT) AS level, count(*) AS edge_cut FROM edges JOIN l3 a ON a.id = src JOIN l3 b ON b.id = dst WHERE a.p <> b.p GROUP BY 1",
}
