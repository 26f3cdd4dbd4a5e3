"""Joins, aggregations, windows, set operators and top-k over graph tables, as plain DataFrame plans.

Range and as-of joins are equi-joins on a bucket with a residual condition, so that no side is paired with all of the other.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..graphs import derive

G = "g_part_supp"


def range_join(points: DataFrame, ranges: DataFrame, value: str, lo: str, hi: str, bucket: int) -> DataFrame:
    """points whose value lies in [lo, hi]: both sides meet in buckets of ``bucket`` values; a range is copied to each it covers."""
    p = points.withColumn("_b", F.floor(F.col(value) / bucket))
    r = ranges.withColumn("_b", F.explode(F.sequence(F.floor(F.col(lo) / bucket), F.floor(F.col(hi) / bucket))))
    return p.join(r, "_b").where(F.col(value).between(F.col(lo), F.col(hi))).drop("_b")


def asof_join(left: DataFrame, right: DataFrame, key: str, at: str, since: str, value: str) -> DataFrame:
    """Each left row with the last right value of its key at or before its time: one union and one window, no pairing."""
    both = left.select(key, F.col(at).alias("_t"), F.lit(1).alias("_s"), F.struct(*left.columns).alias("_l"), F.lit(None).cast(dict(right.dtypes)[value]).alias("_v"))
    other = right.select(key, F.col(since).alias("_t"), F.lit(0).alias("_s"), F.lit(None).cast(both.schema["_l"].dataType).alias("_l"), F.col(value).alias("_v"))
    last = F.last("_v", ignorenulls=True).over(Window.partitionBy(key).orderBy("_t", "_s").rowsBetween(Window.unboundedPreceding, 0))
    return both.union(other).withColumn(value, last).where("_s = 1").select("_l.*", value)


def interval_join(events: DataFrame, seconds: int) -> DataFrame:
    """Pairs of one user's events at most so many seconds apart (a before b): they meet in the second's bucket and the next."""
    e = events.select("event_id", "user_id", F.unix_timestamp(F.col("ts").cast("timestamp")).alias("s"), F.col("ts"))
    a = e.withColumn("b", F.explode(F.array(F.floor(F.col("s") / seconds), F.floor(F.col("s") / seconds) + 1)))
    b = e.withColumn("b", F.floor(F.col("s") / seconds)).select("user_id", "b", F.col("event_id").alias("next_id"), F.col("s").alias("s2"))
    j = a.join(b, ["user_id", "b"]).where((F.col("s2") - F.col("s")).between(0, seconds) & ((F.col("s2") > F.col("s")) | (F.col("next_id") > F.col("event_id"))))
    return j.select("event_id", "next_id").distinct()


def _t(name: str):
    return lambda s, d: derive.table(s, d, name)


lineitem, orders, customer, nation, region, events, part, supplier = map(_t, ("lineitem", "orders", "customer", "nation", "region", "events", "part", "supplier"))
Q: dict = {}
O: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        Q[name] = f
        if sql:
            O[name] = sql
        return f

    return add


@query("scan_parquet", "SELECT l_orderkey, l_partkey FROM lineitem WHERE l_quantity >= 45 AND l_shipdate >= TIMESTAMP '1995-06-01'")
def scan(s, d):
    return lineitem(s, d).where("l_quantity >= 45 AND l_shipdate >= timestamp_ntz'1995-06-01 00:00:00'").select("l_orderkey", "l_partkey")


@query("filter_edges", derive.with_graph(G) + "SELECT src, dst, w FROM edges WHERE w BETWEEN 20 AND 30 AND src IN (1, 2, 3, 5, 8, 13, 21)")
def filter_edges(s, d):
    return derive.load(s, d, G).edges.where(F.col("w").between(20, 30) & F.col("src").isin(1, 2, 3, 5, 8, 13, 21))


@query("edge_predicates", "SELECT c_custkey, c_mktsegment, CASE WHEN c_acctbal < 0 THEN 'low' WHEN c_acctbal < 5000 THEN 'mid' ELSE 'high' END AS band FROM customer WHERE regexp_matches(c_mktsegment, '^[A-M]')")
def edge_predicates(s, d):
    band = F.when(F.col("c_acctbal") < 0, "low").when(F.col("c_acctbal") < 5000, "mid").otherwise("high")
    return customer(s, d).where(F.col("c_mktsegment").rlike("^[A-M]")).select("c_custkey", "c_mktsegment", band.alias("band"))


@query("join_inner", "SELECT n_name, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def join_inner(s, d):
    return orders(s, d).join(customer(s, d), F.col("o_custkey") == F.col("c_custkey")).join(nation(s, d), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"))


@query("join_left", "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY c_custkey")
def join_left(s, d):
    n = orders(s, d).groupBy("o_custkey").agg(F.count("*").alias("n"))
    return customer(s, d).join(n, F.col("c_custkey") == F.col("o_custkey"), "left").select("c_custkey", F.coalesce("n", F.lit(0)).alias("n"))


@query("join_full", "SELECT c_nationkey, s_nationkey, c, n FROM (SELECT c_nationkey, count(*) AS c FROM customer WHERE c_custkey < 200 GROUP BY 1) a FULL JOIN (SELECT s_nationkey, count(*) AS n FROM supplier WHERE s_suppkey < 20 GROUP BY 1) b ON c_nationkey = s_nationkey")
def join_full(s, d):
    a = customer(s, d).where("c_custkey < 200").groupBy("c_nationkey").agg(F.count("*").alias("c"))
    b = supplier(s, d).where("s_suppkey < 20").groupBy("s_nationkey").agg(F.count("*").alias("n"))
    return a.join(b, F.col("c_nationkey") == F.col("s_nationkey"), "full")


@query("join_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 400000)")
def join_semi(s, d):
    return customer(s, d).join(orders(s, d).where("o_totalprice > 400000"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@query("join_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)")
def join_anti(s, d):
    return customer(s, d).join(orders(s, d).where("o_totalprice > 300000"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@query("join_range", "SELECT p_partkey, r.lo, r.hi FROM part JOIN (SELECT i * 150 AS lo, i * 150 + 249 AS hi FROM (SELECT unnest(range(0, 10)) AS i) t) r ON p_partkey BETWEEN r.lo AND r.hi")
def join_range(s, d):
    ranges = s.range(10).select((F.col("id") * 150).alias("lo"), (F.col("id") * 150 + 249).alias("hi"))
    return range_join(part(s, d).select("p_partkey"), ranges, "p_partkey", "lo", "hi", 256)


@query("join_theta", "SELECT a.s_suppkey AS x, b.s_suppkey AS y FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_acctbal < b.s_acctbal")
def join_theta(s, d):
    a = supplier(s, d).select(F.col("s_suppkey").alias("x"), "s_nationkey", F.col("s_acctbal").alias("p"))
    b = supplier(s, d).select(F.col("s_suppkey").alias("y"), "s_nationkey", F.col("s_acctbal").alias("q"))
    return a.join(b, "s_nationkey").where("p < q").select("x", "y")


@query("join_asof", "SELECT event_id, (SELECT max_by(p.event_id, struct_pack(t := p.ts, i := p.event_id)) FROM events p WHERE p.user_id = e.user_id AND p.event_type = 'purchase' AND p.ts <= e.ts) AS bought FROM events e WHERE event_type = 'click'")
def join_asof(s, d):
    e = events(s, d)
    left = e.where("event_type = 'click'").select("event_id", "user_id", "ts")
    right = e.where("event_type = 'purchase'").select("user_id", F.col("ts").alias("since"), F.col("event_id").alias("bought"))
    return asof_join(left, right, "user_id", "ts", "since", "bought").select("event_id", "bought")


@query("join_interval", "SELECT a.event_id, b.event_id AS next_id FROM events a JOIN events b ON a.user_id = b.user_id AND date_diff('second', date_trunc('second', a.ts), date_trunc('second', b.ts)) BETWEEN 0 AND 3600 AND (date_trunc('second', b.ts) > date_trunc('second', a.ts) OR b.event_id > a.event_id)")
def join_interval(s, d):
    return interval_join(events(s, d), 3600)


@query("agg_degree_hist", derive.with_graph(G) + "SELECT d, count(*) AS vertices FROM (SELECT v, count(*) AS d FROM cells GROUP BY v) q GROUP BY d")
def degree_hist(s, d):
    return derive.load(s, d, G).degrees().groupBy("d").agg(F.count("*").alias("vertices"))


@query("agg_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS supps FROM lineitem GROUP BY 1")
def agg_distinct(s, d):
    return lineitem(s, d).groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("supps"))


_GEO = "customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def geo(s, d):
    return customer(s, d).join(nation(s, d), F.col("c_nationkey") == F.col("n_nationkey")).join(region(s, d), F.col("n_regionkey") == F.col("r_regionkey"))


@query("agg_rollup", f"SELECT r_name, n_name, count(*) AS n FROM {_GEO} GROUP BY ROLLUP (r_name, n_name)")
def agg_rollup(s, d):
    return geo(s, d).rollup("r_name", "n_name").agg(F.count("*").alias("n"))


@query("agg_cube", f"SELECT r_name, c_mktsegment, count(*) AS n FROM {_GEO} GROUP BY CUBE (r_name, c_mktsegment)")
def agg_cube(s, d):
    return geo(s, d).cube("r_name", "c_mktsegment").agg(F.count("*").alias("n"))


@query("agg_grouping_sets", f"SELECT r_name, c_mktsegment, count(*) AS n FROM {_GEO} GROUP BY GROUPING SETS ((r_name), (c_mktsegment))")
def agg_sets(s, d):
    return geo(s, d).groupingSets([["r_name"], ["c_mktsegment"]], "r_name", "c_mktsegment").agg(F.count("*").alias("n"))


@query("agg_bitwise", "SELECT l_suppkey, bit_or(l_partkey) AS o, bit_and(l_partkey) AS a, bit_xor(l_partkey) AS x FROM lineitem GROUP BY 1")
def agg_bitwise(s, d):
    return lineitem(s, d).groupBy("l_suppkey").agg(F.bit_or("l_partkey").alias("o"), F.bit_and("l_partkey").alias("a"), F.bit_xor("l_partkey").alias("x"))


@query("agg_pivot", "SELECT l_returnflag, count(CASE WHEN l_linestatus = 'F' THEN 1 END) AS \"F\", count(CASE WHEN l_linestatus = 'O' THEN 1 END) AS \"O\" FROM lineitem GROUP BY 1")
def agg_pivot(s, d):
    return lineitem(s, d).groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.count(F.lit(1))).na.fill(0)


@query("agg_minby", "SELECT o_custkey, min_by(o_orderkey, struct_pack(p := o_totalprice, k := o_orderkey)) AS cheapest, max_by(o_orderkey, struct_pack(p := o_totalprice, k := o_orderkey)) AS dearest FROM orders GROUP BY 1")
def agg_minby(s, d):
    by = F.struct("o_totalprice", "o_orderkey")
    return orders(s, d).groupBy("o_custkey").agg(F.min_by("o_orderkey", by).alias("cheapest"), F.max_by("o_orderkey", by).alias("dearest"))


@query("agg_approx")
def agg_approx(s, d):
    """Distinct counts by sketch: within a few per cent."""
    return lineitem(s, d).groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"))


_W = "(PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey)"


@query("win_rank", f"SELECT o_orderkey, row_number() OVER {_W} AS rn, rank() OVER {_W} AS rk, dense_rank() OVER {_W} AS dr FROM orders")
def win_rank(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey")
    return orders(s, d).select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"))


@query("win_gaps", derive.with_graph("g_page_link") + "SELECT v, u, u - lag(u) OVER (PARTITION BY v ORDER BY u) AS gap, lead(u) OVER (PARTITION BY v ORDER BY u) AS nx FROM cells")
def win_gaps(s, d):
    w = Window.partitionBy("v").orderBy("u")
    return derive.load(s, d, "g_page_link").cells().select("v", "u", (F.col("u") - F.lag("u").over(w)).alias("gap"), F.lead("u").over(w).alias("nx"))


@query("win_prefix", "SELECT l_orderkey, l_linenumber, sum(l_quantity) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_quantity ROWS UNBOUNDED PRECEDING) AS q FROM lineitem")
def win_prefix(s, d):
    w = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_quantity").rowsBetween(Window.unboundedPreceding, 0)
    return lineitem(s, d).select("l_orderkey", "l_linenumber", F.sum("l_quantity").over(w).alias("q"))


@query("win_ntile", "SELECT c_custkey, ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey) AS quarter, round(percent_rank() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey), 9) AS pr, round(cume_dist() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey), 9) AS cd FROM customer")
def win_ntile(s, d):
    w = Window.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey")
    return customer(s, d).select("c_custkey", F.ntile(4).over(w).alias("quarter"), F.round(F.percent_rank().over(w), 9).alias("pr"), F.round(F.cume_dist().over(w), 9).alias("cd"))


@query("win_range", "SELECT p_partkey, count(*) OVER (PARTITION BY p_brand ORDER BY p_size RANGE BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS near FROM part")
def win_range(s, d):
    w = Window.partitionBy("p_brand").orderBy("p_size").rangeBetween(-2, 2)
    return part(s, d).select("p_partkey", F.count("*").over(w).alias("near"))


@query("topk_degree", derive.with_graph(G) + "SELECT v, count(*) AS d FROM cells GROUP BY v ORDER BY d DESC, v LIMIT 10")
def topk_degree(s, d):
    return derive.load(s, d, G).cells().groupBy("v").agg(F.count("*").alias("d")).orderBy(F.desc("d"), "v").limit(10)


@query("topk_per_group", "SELECT o_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS k FROM orders) q WHERE k <= 3")
def topk_group(s, d):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return orders(s, d).withColumn("k", F.row_number().over(w)).where("k <= 3").select("o_custkey", "o_orderkey")


@query("sort_limit_offset", "SELECT o_orderkey FROM orders ORDER BY o_totalprice, o_orderkey LIMIT 20 OFFSET 30")
def sort_limit(s, d):
    return orders(s, d).orderBy("o_totalprice", "o_orderkey").offset(30).limit(20).select("o_orderkey")


_A, _B = "SELECT DISTINCT l_partkey AS k FROM lineitem WHERE l_quantity > 48", "SELECT DISTINCT l_partkey AS k FROM lineitem WHERE l_discount > 0.09"


def _sets(s, d):
    l = lineitem(s, d)
    return l.where("l_quantity > 48").select(F.col("l_partkey").alias("k")).distinct(), l.where("l_discount > 0.09").select(F.col("l_partkey").alias("k")).distinct()


@query("set_union", f"{_A} UNION {_B}")
def set_union(s, d):
    a, b = _sets(s, d)
    return a.union(b).distinct()


@query("set_intersect", f"{_A} INTERSECT {_B}")
def set_intersect(s, d):
    a, b = _sets(s, d)
    return a.intersect(b)


@query("set_except", f"{_A} EXCEPT {_B}")
def set_except(s, d):
    a, b = _sets(s, d)
    return a.subtract(b)


QUERIES, ORACLES = Q, O
