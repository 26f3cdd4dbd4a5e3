"""Greedy relabelling for small largest neighbours, in data-parallel form.

The scan visits vertices by (degree, id) and hands the next label to each neighbour not seen yet, in id order. So a vertex's label
follows the rank of the first vertex of the scan that it neighbours, ties by its own id: one minimum per
vertex and two global ranks, no loop.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..core.ids import global_rank
from ..core.model import Graph
from ..graphs import derive


def greedy_relabel(g: Graph, include_self: bool = False) -> DataFrame:
    """(id, new_id) of all vertices; isolated ones come last, by id. include_self: a scanned vertex is labelled before its neighbours."""
    ranked = global_rank(g.degrees().where("d > 0"), [F.col("d"), F.col("id")], "rk").select(F.col("id").alias("v"), "rk")
    met = g.cells().join(ranked, "v").select("u", (F.col("rk") * 2 + 1).alias("k"))
    if include_self:
        met = met.union(ranked.select("v", F.col("rk") * 2))
    first = met.groupBy("u").agg(F.min("k").alias("k"))
    order = g.vertices().join(first, F.col("id") == F.col("u"), "left").select("id", F.coalesce("k", F.lit((1 << 63) - 1)).alias("k"))
    return global_rank(order, [F.col("k"), F.col("id")], "new_id").select("id", "new_id")


def ilp_objective(g: Graph, perm: DataFrame) -> DataFrame:
    """Sum over vertices of the largest new neighbour label by degree, as exact decimals rounded to 6 places a vertex."""
    c = g.cells().join(perm.select(F.col("id").alias("u"), "new_id"), "u")
    per = c.groupBy("v").agg(F.max("new_id").alias("mx"), F.count("*").alias("d"))
    return per.agg(F.sum(F.round(F.col("mx") * 1000000 / F.col("d")).cast("long")).alias("objective_x1e6"))


def ilp_solve_small(n: int, edges: list[tuple[int, int]], most: int = 9) -> tuple[float, list[int]]:
    """The exact optimum for up to ``most`` vertices, by trying all labellings: (objective, label of each vertex)."""
    from itertools import permutations

    if n > most:
        raise ValueError(f"exact search is for {most} vertices at most")
    near: dict[int, list[int]] = {v: [] for v in range(1, n + 1)}
    for a, b in edges:
        near[a].append(b)
        near[b].append(a)
    best = min((sum(max(p[u - 1] for u in x) / len(x) for x in near.values() if x), p) for p in permutations(range(1, n + 1)))
    return best[0], list(best[1])


def _greedy(spark: SparkSession, sf_dir: str) -> DataFrame:
    return greedy_relabel(derive.load(spark, sf_dir, "g_page_link"))


def _objective(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = derive.load(spark, sf_dir, "g_part_supp")
    same = g.vertices().select("id", F.col("id").alias("new_id"))
    return ilp_objective(g, same).withColumn("labels", F.lit("identity")).union(ilp_objective(g, greedy_relabel(g)).withColumn("labels", F.lit("greedy")))


_RANKS = "dg AS (SELECT v, count(*) AS d FROM cells GROUP BY v), rk AS (SELECT v, row_number() OVER (ORDER BY d, v) AS r FROM dg), mk AS (SELECT u, min(r) AS r FROM cells JOIN rk USING (v) GROUP BY u), pm AS (SELECT u AS id, row_number() OVER (ORDER BY r, u) AS new_id FROM mk)"
_SUM = "SELECT CAST(sum(CAST(round(mx * 1000000 / d) AS BIGINT)) AS BIGINT) AS objective_x1e6, '{}' AS labels FROM (SELECT v, CAST(max({}) AS DOUBLE) AS mx, count(*) AS d FROM cells JOIN pm ON pm.id = u GROUP BY v) q"
QUERIES = {"greedy_relabel": _greedy, "ilp_objective": _objective}
ORACLES = {
    "greedy_relabel": derive.with_graph("g_page_link", _RANKS) + "SELECT id, new_id FROM pm",
    "ilp_objective": derive.with_graph("g_part_supp", _RANKS) + _SUM.format("identity", "u") + " UNION ALL " + _SUM.format("greedy", "new_id"),
}
