"""Strings, dates, bits, arrays, maps and JSON on the given tables, with built-in functions."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..bits.width import bit_length, ceil_lg, varint_bits
from ..graphs import derive
from ..operators.relational import customer, events, lineitem, orders, part

QUERIES = {
    "fn_tokens": lambda s, d: derive.doc_tokens(s, d).select("doc_id", F.col("tok").alias("token"), F.col("w").alias("n")),
    "fn_hrefs": lambda s, d: derive.page_links(s, d),
    "fn_md5_hex": lambda s, d: part(s, d).select("p_partkey", F.md5("p_name").alias("m"), F.substring(F.md5(F.concat_ws(":", F.col("p_partkey").cast("string"), "p_brand")), 1, 8).alias("h"), F.upper("p_type").alias("t"), F.lpad(F.bin("p_size"), 8, "0").alias("b")),
    "fn_dates": lambda s, d: orders(s, d).select("o_orderkey", F.year("o_orderdate").cast("long").alias("y"), F.month("o_orderdate").cast("long").alias("m"), F.date_format("o_orderdate", "yyyy-MM-dd").alias("day"), F.datediff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date")).cast("long").alias("days")),
    "fn_intervals": lambda s, d: orders(s, d).select("o_orderkey", F.date_format(F.expr("o_orderdate + interval 90 days"), "yyyy-MM-dd").alias("due")),
    "fn_bits": lambda s, d: lineitem(s, d).select("l_orderkey", "l_linenumber", F.shiftleft("l_partkey", 3).alias("l"), F.shiftright("l_partkey", 2).alias("r"), F.col("l_partkey").bitwiseAND(F.col("l_suppkey")).alias("a"), F.col("l_partkey").bitwiseXOR(F.col("l_suppkey")).alias("x"), F.bit_count("l_partkey").cast("long").alias("c")),
    "fn_ceil_lg": lambda s, d: orders(s, d).select(F.col("o_orderkey").cast("long").alias("x")).select("x", F.expr(ceil_lg("x")).cast("long").alias("lg"), F.expr(bit_length("x")).cast("long").alias("bl"), F.expr(varint_bits("x")).cast("long").alias("vb")),
    "fn_arrays": lambda s, d: orders(s, d).groupBy("o_custkey").agg(F.sort_array(F.collect_list("o_orderkey")).alias("k")).select("o_custkey", F.size("k").cast("long").alias("n"), F.array_min("k").alias("lo"), F.array_max("k").alias("hi"), F.aggregate("k", F.lit(0).cast("long"), lambda a, x: a + x).alias("s"), F.size(F.filter("k", lambda x: x % 2 == 0)).cast("long").alias("even")),
    "fn_maps": lambda s, d: customer(s, d).groupBy("c_nationkey", "c_mktsegment").agg(F.count("*").alias("n")).groupBy("c_nationkey").agg(F.map_from_entries(F.collect_list(F.struct("c_mktsegment", "n"))).alias("m")).select("c_nationkey", F.coalesce(F.col("m")["BUILDING"], F.lit(0)).alias("building"), F.size("m").cast("long").alias("segments")),
    "fn_json": lambda s, d: events(s, d).select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k")),
}
ORACLES = {
    "fn_tokens": "SELECT doc_id, tok AS token, count(*) AS n FROM (SELECT doc_id, unnest(string_split_regex(lower(text), '[^a-z]+')) AS tok FROM documents) q WHERE tok <> '' GROUP BY 1, 2",
    "fn_hrefs": "SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) AS href FROM pages",
    "fn_md5_hex": "SELECT p_partkey, md5(p_name) AS m, substr(md5(p_partkey || ':' || p_brand), 1, 8) AS h, upper(p_type) AS t, lpad(bin(p_size), 8, '0') AS b FROM part",
    "fn_dates": "SELECT o_orderkey, CAST(year(o_orderdate) AS BIGINT) AS y, CAST(month(o_orderdate) AS BIGINT) AS m, strftime(o_orderdate, '%Y-%m-%d') AS day, date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS days FROM orders",
    "fn_intervals": "SELECT o_orderkey, strftime(o_orderdate + INTERVAL 90 DAY, '%Y-%m-%d') AS due FROM orders",
    "fn_bits": "SELECT l_orderkey, l_linenumber, l_partkey << 3 AS l, l_partkey >> 2 AS r, l_partkey & l_suppkey AS a, xor(l_partkey, l_suppkey) AS x, CAST(bit_count(l_partkey) AS BIGINT) AS c FROM lineitem",
    "fn_ceil_lg": f"SELECT x, CAST({ceil_lg('x')} AS BIGINT) AS lg, CAST({bit_length('x')} AS BIGINT) AS bl, CAST({varint_bits('x')} AS BIGINT) AS vb FROM (SELECT CAST(o_orderkey AS BIGINT) AS x FROM orders) t",
    "fn_arrays": "SELECT o_custkey, count(*) AS n, min(o_orderkey) AS lo, max(o_orderkey) AS hi, CAST(sum(o_orderkey) AS BIGINT) AS s, count(CASE WHEN o_orderkey % 2 = 0 THEN 1 END) AS even FROM orders GROUP BY 1",
    "fn_maps": "SELECT c_nationkey, count(CASE WHEN c_mktsegment = 'BUILDING' THEN 1 END) AS building, count(DISTINCT c_mktsegment) AS segments FROM customer GROUP BY 1",
    "fn_json": "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events",
}
