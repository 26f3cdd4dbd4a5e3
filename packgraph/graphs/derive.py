"""Graphs of the given tables, each as a plan and as SQL that gives the same rows.

SQL defines ``edges`` (src, dst, w) and ``nv`` (n) as common table expressions.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..core.ids import global_rank
from ..core.model import Graph


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def part_supp(spark: SparkSession, d: str) -> Graph:
    parts, supps = table(spark, d, "part").count(), table(spark, d, "supplier").count()
    e = table(spark, d, "lineitem").groupBy("l_partkey", "l_suppkey").agg(F.sum("l_quantity").cast("long").alias("w"))
    return Graph("g_part_supp", parts + supps, e.select((F.col("l_partkey") + 1).alias("src"), (F.col("l_suppkey") + 1 + parts).alias("dst"), "w"))


def cust_part(spark: SparkSession, d: str) -> Graph:
    customers, parts = table(spark, d, "customer").count(), table(spark, d, "part").count()
    j = table(spark, d, "orders").join(table(spark, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"))
    e = j.groupBy("o_custkey", "l_partkey").agg(F.sum("l_quantity").cast("long").alias("w"))
    return Graph("g_cust_part", customers + parts, e.select((F.col("o_custkey") + 1).alias("src"), (F.col("l_partkey") + 1 + customers).alias("dst"), "w"))


def cust_order(spark: SparkSession, d: str) -> Graph:
    customers, orders = table(spark, d, "customer").count(), table(spark, d, "orders").count()
    e = table(spark, d, "orders").select((F.col("o_custkey") + 1).alias("src"), (F.col("o_orderkey") + 1 + customers).alias("dst"), F.round(F.col("o_totalprice") * 100).cast("long").alias("w"))
    return Graph("g_cust_order", customers + orders, e)


def _together(spark: SparkSession, d: str, key: str) -> DataFrame:
    """Pairs of keys of one order; an order's lines are few, so the self-join stays linear in orders."""
    x = table(spark, d, "lineitem").select("l_orderkey", F.col(key).alias("a")).distinct()
    return x.join(x.withColumnRenamed("a", "b"), "l_orderkey").where("a < b").groupBy("a", "b").agg(F.count("*").alias("w")).select((F.col("a") + 1).alias("src"), (F.col("b") + 1).alias("dst"), "w")


def copurchase(spark: SparkSession, d: str) -> Graph:
    return Graph("g_copurchase", table(spark, d, "part").count(), _together(spark, d, "l_partkey"))


def supp_co(spark: SparkSession, d: str) -> Graph:
    return Graph("g_supp_co", table(spark, d, "supplier").count(), _together(spark, d, "l_suppkey"))


def _in_time(spark: SparkSession, d: str) -> DataFrame:
    """Events with their place in time (rank) over all events."""
    return global_rank(table(spark, d, "events").select("event_id", "user_id", "event_type", "ts"), [F.col("ts"), F.col("event_id")], "rk")


def _seconds(a: str, b: str):
    return F.unix_timestamp(F.col(b).cast("timestamp")) - F.unix_timestamp(F.col(a).cast("timestamp"))


def road(spark: SparkSession, d: str) -> Graph:
    from pyspark.sql import Window

    ev = _in_time(spark, d)
    mine = Window.partitionBy("user_id").orderBy("ts", "event_id")
    own = ev.select("event_id", "ts", F.lead("event_id").over(mine).alias("nx"), F.lead("ts").over(mine).alias("nt")).where("nx IS NOT NULL")
    after = ev.select((F.col("rk") - 1).alias("rk"), F.col("event_id").alias("nx"), F.col("ts").alias("nt"))
    buys = ev.where("event_type = 'purchase'").join(after, "rk").select("event_id", "ts", "nx", "nt")
    e = own.union(buys).select((F.col("event_id") + 1).alias("src"), (F.col("nx") + 1).alias("dst"), _seconds("ts", "nt").alias("w"))
    return Graph.from_edges("g_road", ev.count(), e)


def user_next(spark: SparkSession, d: str) -> Graph:
    ev = _in_time(spark, d)
    after = ev.select((F.col("rk") - 1).alias("rk"), F.col("user_id").alias("nu"))
    e = ev.join(after, "rk").select((F.col("user_id") + 1).alias("src"), (F.col("nu") + 1).alias("dst"), F.lit(1).alias("w"))
    n = ev.agg(F.max("user_id")).first()[0]
    return Graph.from_edges("g_user_next", (n if n is not None else -1) + 1, e, "sum")


def doc_tokens(spark: SparkSession, d: str) -> DataFrame:
    words = table(spark, d, "documents").select("doc_id", F.explode(F.split(F.lower("text"), "[^a-z]+")).alias("tok"))
    return words.where("tok != ''").groupBy("doc_id", "tok").agg(F.count("*").alias("w"))


def doc_tok(spark: SparkSession, d: str) -> Graph:
    docs, uses = table(spark, d, "documents").count(), doc_tokens(spark, d)
    ids = global_rank(uses.select("tok").distinct(), [F.col("tok")], "t")
    e = uses.join(ids, "tok").select((F.col("doc_id") + 1).alias("src"), (F.col("t") + docs).alias("dst"), "w")
    return Graph("g_doc_tok", docs + ids.count(), e)


def page_links(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]+)"'), F.lit(1))).alias("href")).distinct()


def page_link(spark: SparkSession, d: str) -> Graph:
    pages, links = table(spark, d, "pages").count(), page_links(spark, d)
    ids = global_rank(links.select("href").distinct(), [F.col("href")], "t")
    e = links.join(ids, "href").select((F.col("page_id") + 1).alias("src"), (F.col("t") + pages).alias("dst"), F.lit(1).cast("long").alias("w"))
    return Graph("g_page_link", pages + ids.count(), e)


def conv(spark: SparkSession, d: str) -> Graph:
    turns = global_rank(table(spark, d, "conversations").select("conv_id", "turn"), [F.col("conv_id"), F.col("turn")], "id")
    nxt = turns.select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("id").alias("nx"))
    return Graph.from_edges("g_conv", turns.count(), turns.join(nxt, ["conv_id", "turn"]).select(F.col("id").alias("src"), F.col("nx").alias("dst"), F.lit(1).alias("w")))


def knn(spark: SparkSession, d: str, k: int = 8, block: int = 1024) -> Graph:
    """k nearest by cosine, ties by id: a stated query set (all vectors, in blocks) against all vectors in blocks.

    Blocks meet by a join on a block number; a block's best k come back, so rows stay k times vectors
    times blocks. Similarities are rounded to 9 places, where ties are broken by id.
    """
    import numpy as np
    import pyarrow as pa

    v = table(spark, d, "embeddings").select(F.col("vec_id").cast("long").alias("id"), "embedding")
    n = v.count()
    blocks = max(1, -(-n // block))
    v = v.withColumn("b", F.pmod("id", F.lit(blocks)))
    left = v.withColumn("o", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long")))).select("id", "embedding", "b", "o")
    right = v.withColumn("p", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long")))).select("id", "embedding", F.col("p").alias("b"), F.col("b").alias("o"))

    def unit(t: pa.Table):
        x = np.array(t["embedding"].to_pylist(), dtype=np.float64)
        return t["id"].to_numpy(), x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)

    def near(l: pa.Table, r: pa.Table) -> pa.Table:
        if not l.num_rows or not r.num_rows:
            return pa.table({"id": pa.array([], pa.int64()), "nb": pa.array([], pa.int64()), "s": pa.array([], pa.float64())})
        (i, x), (j, y) = unit(l), unit(r)
        s = np.round(x @ y.T, 9)
        s[i[:, None] == j[None, :]] = -9
        keep = min(k, len(j))
        order = np.lexsort((np.broadcast_to(j, s.shape), -s), axis=1)[:, :keep]
        a, b, c = np.repeat(i, keep), j[order].ravel(), np.take_along_axis(s, order, 1).ravel()
        ok = c > -9
        return pa.table({"id": a[ok], "nb": b[ok], "s": c[ok]})

    some = left.groupBy("b", "o").cogroup(right.groupBy("b", "o")).applyInArrow(near, "id long, nb long, s double")
    from pyspark.sql import Window

    best = some.withColumn("k", F.row_number().over(Window.partitionBy("id").orderBy(F.desc("s"), "nb"))).where(F.col("k") <= k)
    return Graph.from_edges("g_knn", n, best.select((F.col("id") + 1).alias("src"), (F.col("nb") + 1).alias("dst"), F.lit(1).alias("w")))


GRAPHS = {"g_part_supp": part_supp, "g_cust_part": cust_part, "g_cust_order": cust_order, "g_copurchase": copurchase, "g_road": road, "g_user_next": user_next, "g_doc_tok": doc_tok, "g_page_link": page_link, "g_supp_co": supp_co, "g_conv": conv, "g_knn": knn}


def load(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    return GRAPHS[name](spark, sf_dir)


def _pairs(key: str) -> str:
    return f"SELECT a.k + 1 AS src, b.k + 1 AS dst, count(*) AS w FROM (SELECT DISTINCT l_orderkey o, {key} k FROM lineitem) a JOIN (SELECT DISTINCT l_orderkey o, {key} k FROM lineitem) b ON a.o = b.o AND a.k < b.k GROUP BY 1, 2"


_ROAD = """SELECT least(x, y) AS src, greatest(x, y) AS dst, min(w) AS w FROM (
    SELECT event_id + 1 x, nx + 1 y, date_diff('second', ts, nt) w FROM (SELECT event_id, ts, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) nx, lead(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) nt FROM events) q WHERE nx IS NOT NULL
    UNION ALL
    SELECT event_id + 1, nx + 1, date_diff('second', ts, nt) FROM (SELECT event_id, event_type, ts, lead(event_id) OVER (ORDER BY ts, event_id) nx, lead(ts) OVER (ORDER BY ts, event_id) nt FROM events) q WHERE nx IS NOT NULL AND event_type = 'purchase') z
  WHERE x <> y GROUP BY 1, 2"""

#: name: (edges, n)
SQL = {
    "g_part_supp": ("SELECT l_partkey + 1 AS src, l_suppkey + 1 + (SELECT count(*) FROM part) AS dst, CAST(sum(l_quantity) AS BIGINT) AS w FROM lineitem GROUP BY 1, 2", "SELECT (SELECT count(*) FROM part) + (SELECT count(*) FROM supplier) AS n"),
    "g_cust_part": ("SELECT o_custkey + 1 AS src, l_partkey + 1 + (SELECT count(*) FROM customer) AS dst, CAST(sum(l_quantity) AS BIGINT) AS w FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1, 2", "SELECT (SELECT count(*) FROM customer) + (SELECT count(*) FROM part) AS n"),
    "g_cust_order": ("SELECT o_custkey + 1 AS src, o_orderkey + 1 + (SELECT count(*) FROM customer) AS dst, CAST(round(o_totalprice * 100) AS BIGINT) AS w FROM orders", "SELECT (SELECT count(*) FROM customer) + (SELECT count(*) FROM orders) AS n"),
    "g_copurchase": (_pairs("l_partkey"), "SELECT count(*) AS n FROM part"),
    "g_supp_co": (_pairs("l_suppkey"), "SELECT count(*) AS n FROM supplier"),
    "g_road": (_ROAD, "SELECT count(*) AS n FROM events"),
    "g_user_next": ("SELECT least(x, y) AS src, greatest(x, y) AS dst, count(*) AS w FROM (SELECT user_id + 1 x, lead(user_id) OVER (ORDER BY ts, event_id) + 1 y FROM events) q WHERE y IS NOT NULL AND x <> y GROUP BY 1, 2", "SELECT max(user_id) + 1 AS n FROM events"),
    "g_doc_tok": ("SELECT doc_id + 1 AS src, t + (SELECT count(*) FROM documents) AS dst, count(*) AS w FROM (SELECT doc_id, unnest(string_split_regex(lower(text), '[^a-z]+')) AS tok FROM documents) q JOIN toks USING (tok) WHERE tok <> '' GROUP BY 1, 2", "SELECT (SELECT count(*) FROM documents) + (SELECT count(*) FROM toks) AS n"),
    "g_page_link": ("SELECT DISTINCT page_id + 1 AS src, t + (SELECT count(*) FROM pages) AS dst, CAST(1 AS BIGINT) AS w FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) AS href FROM pages) q JOIN hrefs USING (href)", "SELECT (SELECT count(*) FROM pages) + (SELECT count(*) FROM hrefs) AS n"),
    "g_conv": ("SELECT a.id AS src, b.id AS dst, CAST(1 AS BIGINT) AS w FROM turns a JOIN turns b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1", "SELECT count(*) AS n FROM conversations"),
}
_BEFORE = {
    "g_doc_tok": "toks AS (SELECT tok, row_number() OVER (ORDER BY tok) AS t FROM (SELECT DISTINCT unnest(string_split_regex(lower(text), '[^a-z]+')) AS tok FROM documents) z WHERE tok <> ''), ",
    "g_page_link": "hrefs AS (SELECT href, row_number() OVER (ORDER BY href) AS t FROM (SELECT DISTINCT unnest(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) AS href FROM pages) z), ",
    "g_conv": "turns AS (SELECT conv_id, turn, row_number() OVER (ORDER BY conv_id, turn) AS id FROM conversations), ",
}


def with_graph(name: str, more: str = "") -> str:
    """``WITH`` clause that defines edges, nv and cells (v, u, w) of a graph, and what else is given."""
    edges, n = SQL[name]
    return f"WITH RECURSIVE {_BEFORE.get(name, '')}edges AS MATERIALIZED ({edges}), nv AS ({n}), cells AS MATERIALIZED (SELECT src AS v, dst AS u, w FROM edges UNION ALL SELECT dst, src, w FROM edges){', ' + more if more else ' '}"
