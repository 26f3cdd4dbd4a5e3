"""Permuters: bijections id -> new_id."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..core.ids import global_rank
from ..core.model import Graph
from ..graphs import derive


def identity(g: Graph) -> DataFrame:
    return g.vertices().select("id", F.col("id").alias("new_id"))


def degree_permuter(g: Graph) -> DataFrame:
    """The highest degrees get the smallest labels; ties by id."""
    return global_rank(g.degrees(), [F.col("d").desc(), F.col("id")], "new_id").select("id", "new_id")


def hash_permuter(g: Graph, seed: int = 1) -> DataFrame:
    """A reproducible random order."""
    keyed = g.vertices().withColumn("k", F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("id").cast("string"))))
    return global_rank(keyed, [F.col("k"), F.col("id")], "new_id").select("id", "new_id")


def apply_degree(g: Graph) -> Graph:
    return g.relabel(degree_permuter(g))


def is_bijection(perm: DataFrame) -> DataFrame:
    """n, distinct_ids, distinct_labels, least, greatest: equal counts and 1..n mean a bijection."""
    return perm.agg(F.count("*").alias("n"), F.countDistinct("id").alias("distinct_ids"), F.countDistinct("new_id").alias("distinct_labels"), F.min("new_id").alias("least"), F.max("new_id").alias("greatest"))


def _degree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return degree_permuter(derive.load(spark, sf_dir, "g_page_link"))


def _hash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hash_permuter(derive.load(spark, sf_dir, "g_user_next"))


def _bijection(spark: SparkSession, sf_dir: str) -> DataFrame:
    return is_bijection(degree_permuter(derive.load(spark, sf_dir, "g_part_supp")))


def _applied(spark: SparkSession, sf_dir: str) -> DataFrame:
    return apply_degree(derive.load(spark, sf_dir, "g_page_link")).edges


_D = "dg AS (SELECT v, count(*) AS d FROM cells GROUP BY v), pm AS (SELECT v AS id, row_number() OVER (ORDER BY d DESC, v) AS new_id FROM dg)"
QUERIES = {"dm_permuter": _degree, "perm_hash": _hash, "perm_bijection": _bijection, "relabel_apply": _applied}
ORACLES = {
    "dm_permuter": derive.with_graph("g_page_link", _D) + "SELECT id, new_id FROM pm",
    "perm_hash": derive.with_graph("g_user_next") + "SELECT id, row_number() OVER (ORDER BY md5('1:' || id), id) AS new_id FROM (SELECT unnest(range(1, (SELECT n FROM nv) + 1)) AS id) q",
    "perm_bijection": derive.with_graph("g_part_supp") + "SELECT n, n AS distinct_ids, n AS distinct_labels, CAST(1 AS BIGINT) AS least, n AS greatest FROM nv",
    "relabel_apply": derive.with_graph("g_page_link", _D) + "SELECT least(a.new_id, b.new_id) AS src, greatest(a.new_id, b.new_id) AS dst, w FROM edges JOIN pm a ON a.id = src JOIN pm b ON b.id = dst",
}
