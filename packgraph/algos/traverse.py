"""Breadth-first search, shortest paths, components, PageRank, betweenness and triangles as DataFrame loops.

Each round's state is a small written table; each round costs one join and one aggregate over what changed. ``cells`` is
(v, u) or (v, u, w); pass a written table, it is read in each round.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..core.compressed import TRANSFORMERS, CompressedGraph
from ..core.store import drop, written
from ..graphs import derive

#: Edges of a part of the triangle count, and of the blocks in which edges are sent.
PART_EDGES = 6_000_000
BLOCK_EDGES = 2_000_000


def bfs(cells: DataFrame, source: int, mode: str = "auto", alpha: int = 14, beta: int = 24) -> DataFrame:
    """(id, dist) of what is reached. push: the frontier's cells look for new ends; pull: unreached ends
    look for the frontier. auto switches by the published rule: pull while the frontier's cells exceed 1/alpha of those unreached,
    push again when the frontier is below 1/beta of the vertices."""
    spark = cells.sparkSession
    size = written(cells.groupBy("v").agg(F.count("*").alias("d")), "degrees")
    total = size.agg(F.sum("d"), F.count("*")).first()
    left, n = total[0] or 0, total[1]
    levels = [written(spark.createDataFrame([(source, 0)], "id long, dist long"), "level")]  # what is seen is their union
    level, pull = 0, mode == "pull"
    while True:
        frontier, seen = levels[-1].where(F.col("dist") == level).select("id"), union_all(levels)
        if mode == "auto":
            f = frontier.join(size, F.col("id") == F.col("v")).agg(F.coalesce(F.sum("d"), F.lit(0)), F.count("*")).first()
            left -= f[0]
            pull = (f[0] > left / alpha) if not pull else (f[1] >= n / beta)
        ends = seen.select(F.col("id").alias("e"))
        if pull:
            open_ = cells.join(ends, F.col("v") == F.col("e"), "left_anti")
            found = open_.join(frontier, F.col("u") == F.col("id"), "left_semi").select(F.col("v").alias("id")).distinct()
        else:
            found = cells.join(frontier, F.col("v") == F.col("id"), "left_semi").select("u").distinct().join(ends, F.col("u") == F.col("e"), "left_anti").select(F.col("u").alias("id"))
        level += 1
        new = written(found.withColumn("dist", F.lit(level).cast("long")), "level")
        if new.isEmpty():
            drop(new), drop(size)
            return seen
        levels.append(new)
        if len(levels) > MERGE:
            merged = written(union_all(levels), "level")
            for x in levels:
                drop(x)
            levels = [merged]


MERGE = 16


def union_all(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def sssp(cells: DataFrame, source: int, delta: int | None = None) -> DataFrame:
    """(id, dist) by delta-stepping: light edges (w <= delta) are relaxed within a bucket until it is stable, heavy ones once.

    What a round improves stays apart and joins the distances once a bucket.
    """
    spark = cells.sparkSession
    if delta is None:
        delta = max(1, int(cells.agg(F.avg("w")).first()[0] or 1))
    light, heavy = cells.where(F.col("w") <= delta), cells.where(F.col("w") > delta)
    parts = [written(spark.createDataFrame([(source, 0)], "id long, dist long"), "dist")]
    bucket = 0

    def known() -> DataFrame:
        return parts[0] if len(parts) == 1 else union_all(parts).groupBy("id").agg(F.min("dist").alias("dist"))

    def merge() -> None:
        if len(parts) > 1:
            whole = written(known(), "dist")
            for x in parts:
                drop(x)
            parts[:] = [whole]

    def relax(some: DataFrame, edges: DataFrame) -> DataFrame:
        """Improved distances."""
        tried = some.join(edges, F.col("id") == F.col("v")).groupBy("u").agg(F.min(F.col("dist") + F.col("w")).alias("t"))
        better = tried.join(known(), F.col("u") == F.col("id"), "left").where("dist IS NULL OR t < dist").select(F.col("u").alias("id"), F.col("t").alias("dist"))
        return written(better, "better")

    while True:
        inside = (F.col("dist") >= bucket * delta) & (F.col("dist") < (bucket + 1) * delta)
        some = known().where(inside)
        while True:
            better = relax(some, light)
            some = better.where(inside)
            if better.isEmpty():
                drop(better)
                break
            parts.append(better)
            if len(parts) > MERGE:
                merge()
                some = known().join(better.select("id"), "id", "left_semi").where(inside)
            if some.isEmpty():
                break
        parts.append(relax(known().where(inside), heavy))
        merge()
        nxt = parts[0].where(F.col("dist") >= (bucket + 1) * delta).agg(F.min("dist")).first()[0]
        if nxt is None:
            return parts[0]
        bucket = nxt // delta


def connected_components(cells: DataFrame, vertices: DataFrame) -> DataFrame:
    """(id, comp): hooking to the smallest neighbouring label, then pointer jumping, until nothing changes."""
    label = written(vertices.select("id", F.col("id").alias("comp")), "comp")
    while True:
        near = cells.join(label, F.col("u") == F.col("id")).groupBy("v").agg(F.min("comp").alias("m"))
        hooked = label.join(near, F.col("id") == F.col("v"), "left").select("id", "comp", F.least("comp", F.coalesce("m", "comp")).alias("m"))
        # the old root follows its smallest new label too
        root = hooked.groupBy(F.col("comp").alias("r")).agg(F.min("m").alias("rm"))
        moved = hooked.join(root, F.col("m") == F.col("r"), "left").select("id", "comp", F.least("m", F.coalesce("rm", "m")).alias("new"))
        new = written(moved, "comp")
        changed = not new.where("new != comp").isEmpty()
        drop(label)
        label = new.select("id", F.col("new").alias("comp"))
        if not changed:
            return label


def pagerank(cells: DataFrame, n: int, vertices: DataFrame, rounds: int = 5, scale: int = 1_000_000_000) -> DataFrame:
    """(id, rank) in whole units of 1 / scale: contributions are gathered, so no update is shared, and sums of integers do not depend on order."""
    degree = written(cells.groupBy("v").agg(F.count("*").alias("d")), "degrees")
    base = 15 * scale // 100 // n if n else 0
    rank = vertices.select("id", F.lit(scale // n if n else 0).cast("long").alias("rank"))
    for _ in range(rounds):
        was = rank
        share = rank.join(degree, F.col("id") == F.col("v")).select(F.col("id").alias("f"), F.expr("rank div d").alias("c"))
        got = cells.join(share, F.col("u") == F.col("f")).groupBy("v").agg(F.sum("c").alias("s"))
        rank = written(vertices.join(got, F.col("id") == F.col("v"), "left").select("id", F.expr(f"cast({base} + (85 * coalesce(s, 0)) div 100 as bigint)").alias("rank")), "rank")
        drop(was)
    drop(degree)
    return rank


def betweenness(cells: DataFrame, sources: list[int]) -> DataFrame:
    """(id, bc): dependencies of the sources summed and halved, rounded to 6 places. Forward path counts by level, then backward shares."""
    spark, out = cells.sparkSession, None
    for s in sources:
        levels = [spark.createDataFrame([(s, 1)], "id long, sigma long")]
        seen = levels[0].select("id")
        while True:
            nxt = cells.join(levels[-1], F.col("v") == F.col("id")).groupBy("u").agg(F.sum("sigma").alias("sigma")).join(seen.withColumnRenamed("id", "e"), F.col("u") == F.col("e"), "left_anti")
            nxt = written(nxt.select(F.col("u").alias("id"), "sigma"), "level")
            if nxt.isEmpty():
                break
            levels.append(nxt)
            was, seen = seen, written(seen.union(nxt.select("id")), "seen")
            drop(was)
        drop(seen)
        delta = levels[-1].select("id", "sigma", F.lit(0.0).alias("delta"))
        for k in range(len(levels) - 2, -1, -1):
            below = delta.select(F.col("id").alias("c"), ((1 + F.col("delta")) / F.col("sigma")).alias("share"))
            got = cells.join(below, F.col("u") == F.col("c")).join(levels[k].select("id"), F.col("v") == F.col("id"), "left_semi").groupBy("v").agg(F.sum("share").alias("s"))
            if k < len(levels) - 1:
                mine = delta.where(F.col("id") != s).select("id", "delta")
                out = mine if out is None else out.union(mine)
            delta = written(levels[k].join(got, F.col("id") == F.col("v"), "left").select("id", "sigma", (F.col("sigma") * F.coalesce("s", F.lit(0.0))).alias("delta")), "delta")
    if out is None:
        return spark.createDataFrame([], "id long, bc double")
    return out.groupBy("id").agg(F.round(F.sum("delta") / 2, 6).alias("bc"))


def triangle_parts(cells: DataFrame, make, schema: str, most: int = PART_EDGES) -> DataFrame:
    """``make(a, b, c)`` of the triangles (arrays of ids) of each part, as a record batch of ``schema``.

    Vertices have one of p colours; a part is three colours, and gets the edges between them, so that each edge goes to p parts and a
    triangle's three edges meet in the part of its own colours alone. What moves is p times the edges, packed, and no wedge.
    p is such that parts of evenly spread edges have about ``most``.
    """
    import numpy as np
    import pyarrow as pa

    from .triangles import closed, pack_edges, unpack_edges

    edges = cells.where("v < u").select("v", "u")
    p = max(1, math.ceil(3 * math.sqrt(edges.count() / most)))

    def split(batches):
        held, n = [], 0
        for b in batches:
            held.append((b.column(0).to_numpy(), b.column(1).to_numpy()))
            n += b.num_rows
            if n >= BLOCK_EDGES:
                yield from pack_edges(held, p)
                held, n = [], 0
        if held:
            yield from pack_edges(held, p)

    def count(table: pa.Table) -> pa.Table:
        found = list(closed(*unpack_edges(table), p, table["part"][0].as_py()))
        a, b, c = (np.concatenate([x[k] for x in found]) if found else np.zeros(0, np.int64) for k in range(3))
        return pa.Table.from_batches([make(a, b, c)])

    blocks = edges.mapInArrow(split, "x int, y int, n long, payload binary")
    colours = F.array_sort(F.array("x", "y", "z"))
    sent = blocks.withColumn("z", F.explode(F.array(*map(F.lit, range(p))))).select(((colours[0] * p + colours[1]) * p + colours[2]).alias("part"), "n", "payload")
    return sent.groupBy("part").applyInArrow(count, schema)


def triangles(cells: DataFrame) -> DataFrame:
    """(a, b, c) of each triangle once, a < b < c."""
    import numpy as np
    import pyarrow as pa

    def make(*ends) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in np.sort(np.stack(ends), axis=0)], names=["a", "b", "c"])

    return triangle_parts(cells, make, "a long, b long, c long")


def triangle_total(cells: DataFrame) -> DataFrame:
    """triangles: how many there are; a part sends its number."""
    import pyarrow as pa

    def make(a, b, c) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([len(a)], pa.int64())], names=["t"])

    return triangle_parts(cells, make, "t long").agg(F.coalesce(F.sum("t"), F.lit(0)).alias("triangles"))


def triangle_counts(cells: DataFrame) -> DataFrame:
    """(id, triangles) of vertices in some; a part sends a number a vertex."""
    import numpy as np
    import pyarrow as pa

    def make(*ends) -> pa.RecordBatch:
        v, n = np.unique(np.concatenate(ends), return_counts=True)
        return pa.RecordBatch.from_arrays([pa.array(v, pa.int64()), pa.array(n, pa.int64())], names=["id", "t"])

    return triangle_parts(cells, make, "id long, t long").groupBy("id").agg(F.sum("t").alias("triangles"))


def load(spark: SparkSession, sf_dir: str, graph: str, codec: str | None = "gap_varint"):
    """(graph, its cells written, from the compressed form where a codec is named; weights only without one)."""
    g = derive.load(spark, sf_dir, graph)
    return g, written(CompressedGraph.build(g, TRANSFORMERS[codec]).cells() if codec else g.cells(), "cells")


def _bfs(mode: str, codec: str, graph: str = "g_cust_part"):
    return lambda spark, sf_dir: bfs(load(spark, sf_dir, graph, codec)[1], 1, mode)


def _sssp(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sssp(load(spark, sf_dir, "g_part_supp", None)[1], 1)


def _cc(codec: str):
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        g, cells = load(spark, sf_dir, "g_page_link", codec)
        return connected_components(cells, g.vertices())

    return query


def _pr(codec: str):
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        g, cells = load(spark, sf_dir, "g_part_supp", codec)
        return pagerank(cells, g.n, g.vertices())

    return query


def _tc(codec: str):
    return lambda spark, sf_dir: triangle_total(load(spark, sf_dir, "g_copurchase", codec)[1])


def bfs_sql(graph: str) -> str:
    # each level extends by cells whose end is new; UNION drops repeats, the least level wins
    return derive.with_graph(graph, "r(id, dist) USING KEY (id) AS (SELECT CAST(1 AS BIGINT), CAST(0 AS BIGINT) UNION SELECT c.u, min(r.dist) + 1 FROM r JOIN cells c ON c.v = r.id LEFT JOIN recurring.r AS o ON o.id = c.u WHERE o.id IS NULL GROUP BY c.u)") + "SELECT id, dist FROM r"


def _rounds_sql(graph: str, first: str, step: str, rounds: int, last: str) -> str:
    parts = [f"t0 AS ({first})"] + [f"t{k + 1} AS MATERIALIZED ({step.format(t=f't{k}')})" for k in range(rounds)]
    return derive.with_graph(graph, "ids AS (SELECT unnest(range(1, (SELECT n FROM nv) + 1)) AS id), dg AS (SELECT v, count(*) AS d FROM cells GROUP BY v), " + ", ".join(parts)) + last.format(t=f"t{rounds}")


_CC_SQL = _rounds_sql("g_page_link", "SELECT id, id AS comp FROM ids", "SELECT t.id, least(t.comp, coalesce(m, t.comp)) AS comp FROM {t} t LEFT JOIN (SELECT v, min(comp) AS m FROM cells JOIN {t} ON {t}.id = u GROUP BY v) q ON q.v = t.id", 24, "SELECT id, comp FROM {t}")
_PR_SQL = _rounds_sql("g_part_supp", "SELECT id, 1000000000 // (SELECT n FROM nv) AS rank FROM ids", "SELECT ids.id, CAST((150000000 // (SELECT n FROM nv)) + (85 * coalesce(s, 0)) // 100 AS BIGINT) AS rank FROM ids LEFT JOIN (SELECT cells.v, sum({t}.rank // dg.d) AS s FROM cells JOIN {t} ON {t}.id = u JOIN dg ON dg.v = u GROUP BY cells.v) q ON q.v = ids.id", 5, "SELECT id, rank FROM {t}")
_SSSP_SQL = _rounds_sql("g_part_supp", "SELECT id, CASE WHEN id = 1 THEN CAST(0 AS BIGINT) END AS dist FROM ids", "SELECT t.id, least(t.dist, m) AS dist FROM {t} t LEFT JOIN (SELECT v, min(dist + w) AS m FROM cells JOIN {t} ON {t}.id = u GROUP BY v) q ON q.v = t.id", 14, "SELECT id, dist FROM {t} WHERE dist IS NOT NULL")
_TC_SQL = derive.with_graph("g_copurchase") + "SELECT count(*) AS triangles FROM edges a JOIN edges b ON b.src = a.dst JOIN edges c ON c.src = a.src AND c.dst = b.dst"
QUERIES = {
    "bfs_dist": _bfs("auto", "gap_varint"), "bfs_push": _bfs("push", "local"), "bfs_pull": _bfs("pull", "global"), "bfs_refint": _bfs("auto", "ref_interval"), "sssp_dist": _sssp,
    "cc_labels": _cc("local"), "cc_labels_gap": _cc("gap_varint"), "pagerank_fixed": _pr("gap_varint"), "pagerank_global": _pr("global"), "pagerank_refint": _pr("ref_interval"), "triangle_count": _tc("gap_varint"), "triangle_count_local": _tc("local_gap"),
    "triangles_per_vertex": lambda s, d: triangle_counts(load(s, d, "g_copurchase")[1]),
    "bc_scores": lambda s, d: betweenness(load(s, d, "g_page_link")[1], [1, 2]),
}
ORACLES = {k: bfs_sql("g_cust_part") for k in ("bfs_dist", "bfs_push", "bfs_pull", "bfs_refint")} | {
    "sssp_dist": _SSSP_SQL, "cc_labels": _CC_SQL, "cc_labels_gap": _CC_SQL, "pagerank_fixed": _PR_SQL, "pagerank_global": _PR_SQL, "pagerank_refint": _PR_SQL, "triangle_count": _TC_SQL, "triangle_count_local": _TC_SQL,
    "triangles_per_vertex": derive.with_graph("g_copurchase", "tr AS (SELECT a.src AS x, a.dst AS y, b.dst AS z FROM edges a JOIN edges b ON b.src = a.dst JOIN edges c ON c.src = a.src AND c.dst = b.dst)") + "SELECT id, count(*) AS triangles FROM (SELECT x AS id FROM tr UNION ALL SELECT y FROM tr UNION ALL SELECT z FROM tr) q GROUP BY id",
}
