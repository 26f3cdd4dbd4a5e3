"""Data a distributed search moves between machine elements, and statistics of timings."""

from __future__ import annotations

import math
import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..algos.traverse import bfs, bfs_sql, pagerank
from ..core.compressed import TRANSFORMERS, CompressedGraph
from ..core.machine import ceil_lg
from ..core.model import Graph
from ..core.store import written
from ..graphs import derive


ELEMENTS = (4, 25, 1024)


def comm_volume(g: Graph, dist: DataFrame, elements: int, ptr_bits: int = 64) -> DataFrame:
    """dist, messages, plain_bits, split_bits by level of a search: ends in other elements, one message for each pair of sending element and end.

    Split identifiers need the intra part only, and one header (element and count) for each pair of elements and level.
    """
    size = -(-g.n // elements)
    c = g.cells().join(dist, F.col("v") == F.col("id")).select("dist", F.expr(f"(v - 1) div {size}").alias("e"), "u", F.expr(f"(u - 1) div {size}").alias("f")).where("e != f")
    sent = c.select("dist", "e", "f", "u").distinct().groupBy("dist", "e", "f").agg(F.count("*").alias("k"))
    intra, header = ceil_lg(size), ceil_lg(elements) + 32
    return sent.groupBy("dist").agg(F.sum("k").alias("messages"), F.sum(F.col("k") * ptr_bits).alias("plain_bits"), F.sum(F.col("k") * intra + header).alias("split_bits"))


def _comm(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = derive.load(spark, sf_dir, "g_cust_part")
    cells = written(g.cells(), "cells")
    dist, out = written(bfs(cells, 1), "dist"), None
    for h in ELEMENTS:
        row = comm_volume(g, dist, h).withColumn("elements", F.lit(h).cast("long"))
        out = row if out is None else out.union(row)
    return out


def summarise_times(df: DataFrame, value: str, drop_percent: int = 1) -> DataFrame:
    """n, mean, median, lo, hi of measurements (order: column ``run``): the first percent is dropped as warm-up; the interval of the median at 95 % is
    taken from order statistics."""
    n = df.count()
    kept = df.where(F.col("run") > math.ceil(n * drop_percent / 100)).select(F.col(value).alias("x"))
    k = n - math.ceil(n * drop_percent / 100)
    half = 1.96 * math.sqrt(k) / 2
    lo, hi = max(1, math.floor(k / 2 - half)), min(k, math.ceil(1 + k / 2 + half))
    from ..core.ids import global_rank

    r = global_rank(kept, [F.col("x")], "r")
    at = lambda i: F.max(F.when(F.col("r") == i, F.col("x")))
    return r.agg(F.count("*").alias("n"), F.round(F.avg("x"), 6).alias("mean"), ((at((k + 1) // 2) + at(k // 2 + 1)) / 2).alias("median"), at(lo).alias("lo"), at(hi).alias("hi"))


def _timing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ..core.ids import global_rank

    runs = global_rank(derive.table(spark, sf_dir, "events").select("event_id", F.round("value", 4).alias("value")), [F.col("event_id")], "run")
    return summarise_times(runs, "value")


def timed(df: DataFrame) -> float:
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def bench_codecs(spark: SparkSession, sf_dir: str, graph: str = "g_part_supp", codecs=("global", "local", "local_gap", "gap_varint", "full_varint", "ref_interval")) -> DataFrame:
    """codec, payload_bits, build_s, scan_s, bfs_s, pr_s: what each form costs to make, to read and to search."""
    g, rows = derive.load(spark, sf_dir, graph), []
    for k in codecs:
        began = time.perf_counter()
        cg = CompressedGraph.build(g, TRANSFORMERS[k])
        built = time.perf_counter() - began
        scan = timed(cg.cells())
        began = time.perf_counter()
        bfs(cg.cells(), 1).count()
        searched = time.perf_counter() - began
        rows.append((k, int(cg.bits().first()["payload_bits"]), built, scan, searched, timed(pagerank(cg.cells(), g.n, g.vertices(), 2))))
    return spark.createDataFrame(rows, "codec string, payload_bits long, build_s double, scan_s double, bfs_s double, pr_s double")


def scale_curve(spark: SparkSession, sf_dir: str, workers=(1, 2, 4)) -> DataFrame:
    """workers, seconds of decoding one graph with so many tasks."""
    cg = CompressedGraph.build(derive.load(spark, sf_dir, "g_cust_part"), TRANSFORMERS["gap_varint"])
    rows = [(t, timed(cg.decode(cg.rows.repartition(t)))) for t in workers]
    return spark.createDataFrame(rows, "workers long, seconds double")


QUERIES = {"bfs_comm_volume": _comm, "timing_summary": _timing, "exp_library": bench_codecs, "scale_curve": scale_curve}
_H = " UNION ALL ".join(
    f"SELECT dist, CAST(sum(k) AS BIGINT) AS messages, CAST(sum(k * 64) AS BIGINT) AS plain_bits, CAST(sum(k * length(bin(s - 1)) + {ceil_lg(h) + 32}) AS BIGINT) AS split_bits, CAST({h} AS BIGINT) AS elements "
    f"FROM (SELECT dist, (v - 1) // s AS e, (u - 1) // s AS f, count(DISTINCT u) AS k, any_value(s) AS s FROM cells JOIN r ON r.id = v, (SELECT (n + {h - 1}) // {h} AS s FROM nv) z WHERE (v - 1) // s <> (u - 1) // s GROUP BY 1, 2, 3) q GROUP BY dist"
    for h in ELEMENTS
)
ORACLES = {
    "bfs_comm_volume": bfs_sql("g_cust_part").rsplit("SELECT id, dist FROM r", 1)[0] + _H,
    "timing_summary": "WITH a AS (SELECT round(value, 4) AS x, row_number() OVER (ORDER BY event_id) AS run, count(*) OVER () AS n FROM events), k AS (SELECT x, row_number() OVER (ORDER BY x) AS r, count(*) OVER () AS k FROM a WHERE run > ceil(n * 0.01)) SELECT count(*) AS n, round(avg(x), 6) AS mean, (max(CASE WHEN r = (k + 1) // 2 THEN x END) + max(CASE WHEN r = k // 2 + 1 THEN x END)) / 2 AS median, max(CASE WHEN r = greatest(1, floor(k / 2 - 0.98 * sqrt(k))) THEN x END) AS lo, max(CASE WHEN r = least(k, ceil(1 + k / 2 + 0.98 * sqrt(k))) THEN x END) AS hi FROM k",
}
