"""Arrangement costs of labellings, exact small solvers and the difference-only form with its constraints."""

from __future__ import annotations

import math
from bisect import bisect_left
from itertools import permutations

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..core.model import Graph
from ..fine.sizes import DEGREE_SQL
from ..graphs import derive
from .permute import degree_permuter, identity

KINDS = ("mgapa", "mloggapa", "mlina", "mloga")


def labelled(g: Graph, perm: DataFrame) -> DataFrame:
    """Cells (v, u) under new labels."""
    a, b = perm.select(F.col("id").alias("v"), F.col("new_id").alias("pv")), perm.select(F.col("id").alias("u"), F.col("new_id").alias("pu"))
    return g.cells().join(a, "v").join(b, "u").select(F.col("pv").alias("v"), F.col("pu").alias("u"))


def _gap(c: DataFrame) -> DataFrame:
    """Differences of consecutive neighbours, the first to the vertex itself (magnitude)."""
    w = Window.partitionBy("v").orderBy("u")
    return c.select(F.coalesce(F.col("u") - F.lag("u").over(w), F.abs(F.col("u") - F.col("v"))).alias("x"))


def arrangement_cost(g: Graph, perm: DataFrame, kind: str) -> DataFrame:
    """cost of a labelling: sums of gaps or of distances to neighbours, or of their base-2 logarithms (rounded to 6 places)."""
    c = labelled(g, perm)
    x = _gap(c) if "gap" in kind else c.select(F.abs(F.col("u") - F.col("v")).alias("x"))
    total = F.round(F.sum(F.log2("x")), 6) if "log" in kind else F.sum("x")
    return x.agg(total.alias("cost"))


def pod_cost(g: Graph, perm: DataFrame) -> DataFrame:
    """The gap cost without absolute values inside lists: interior gaps telescope, so least and largest neighbour are enough."""
    per = labelled(g, perm).groupBy("v").agg(F.min("u").alias("lo"), F.max("u").alias("hi"))
    return per.agg(F.sum(F.abs(F.col("lo") - F.col("v")) + F.col("hi") - F.col("lo")).alias("cost"))


def pod_feasible(g: Graph, perm: DataFrame, chosen: DataFrame | None = None) -> DataFrame:
    """Violations of the constraints by a choice (v, i, j): the j-th given neighbour of v stands i-th in its new list.

    Without a choice, the one that sorts new labels is taken. Columns: rows_bad (an i without exactly one j),
    order_bad (new labels not increasing along i), n.
    """
    by_old, by_new = Window.partitionBy("v").orderBy("u"), Window.partitionBy("v").orderBy("pu")
    b = perm.select(F.col("id").alias("u"), F.col("new_id").alias("pu"))
    nb = g.cells().join(b, "u").select("v", "u", "pu").withColumn("j", F.row_number().over(by_old))
    if chosen is None:
        chosen = nb.withColumn("i", F.row_number().over(by_new)).select("v", "i", "j")
    per_row = chosen.groupBy("v", "i").agg(F.count("*").alias("c")).agg(F.sum(F.when(F.col("c") != 1, 1).otherwise(0)).cast("long").alias("rows_bad"))
    placed = chosen.join(nb.select("v", "j", "pu"), ["v", "j"]).withColumn("before", F.lag("pu").over(Window.partitionBy("v").orderBy("i")))
    order = placed.agg(F.sum(F.when(F.col("before") >= F.col("pu"), 1).otherwise(0)).cast("long").alias("order_bad"), F.count("*").alias("n"))
    return per_row.join(F.broadcast(order), F.lit(True))


def _differences(u: list[int], own: int, kind: str) -> list[int]:
    """Of a vertex labelled ``own`` with neighbours at ``u``, sorted."""
    if "gap" in kind:
        return [abs(u[0] - own), *(b - a for a, b in zip(u, u[1:]))] if u else []
    return [abs(a - own) for a in u]


def _cost(near: list[list[int]], label: list[int], kind: str) -> float:
    total = 0.0
    for v, nb in enumerate(near):
        u = sorted(label[x] for x in nb)
        if "gap" in kind:
            x = [abs(u[0] - label[v]), *(b - a for a, b in zip(u, u[1:]))] if u else []
        else:
            x = [abs(a - label[v]) for a in u]
        total += sum(np.log2(x)) if "log" in kind else sum(x)
    return float(total)


def _near(n: int, edges: list[tuple[int, int]]) -> list[list[int]]:
    near: list[list[int]] = [[] for _ in range(n)]
    for a, b in edges:
        near[a].append(b)
        near[b].append(a)
    return near


def odb_solve(n: int, edges: list[tuple[int, int]], kind: str = "mgapa") -> tuple[float, list[int]]:
    """(optimum, label 1..n of each vertex 0..n-1). Linear arrangement by dynamic programming over subsets (n <= 16): placing vertices one by
    one costs, at each place, the edges between those placed and the rest; other kinds by trying all (n <= 9)."""
    near = _near(n, edges)
    if kind == "mlina":
        if n > 16:
            raise ValueError("exact linear arrangement is for 16 vertices at most")
        mask = [sum(1 << u for u in x) for x in near]
        best, step = [0] + [1 << 60] * ((1 << n) - 1), [0] * (1 << n)
        for s in range(1 << n):
            cut = sum((mask[v] & ~s).bit_count() for v in range(n) if s >> v & 1)
            for v in range(n):
                if not s >> v & 1 and best[s] + cut < best[s | 1 << v]:
                    best[s | 1 << v], step[s | 1 << v] = best[s] + cut, v
        label, s = [0] * n, (1 << n) - 1
        for place in range(n, 0, -1):
            label[step[s]] = place
            s ^= 1 << step[s]
        return 2.0 * best[-1], label  # every edge is met from both ends
    if n > 9:
        raise ValueError("exact search is for 9 vertices at most")
    return min((_cost(near, list(p), kind), list(p)) for p in permutations(range(1, n + 1)))


def pod_solve(n: int, edges: list[tuple[int, int]]) -> tuple[float, list[int]]:
    """The optimum of the difference-only form: the gap optimum, found with the two-ends cost of each vertex."""
    if n > 9:
        raise ValueError("exact search is for 9 vertices at most")
    near = _near(n, edges)

    def cost(p) -> int:
        return sum(abs(min(u) - p[v]) + max(u) - min(u) for v, x in enumerate(near) if (u := [p[w] for w in x]))

    return min((float(cost(p)), list(p)) for p in permutations(range(1, n + 1)))


def local_search(n: int, edges: list[tuple[int, int]], kind: str = "mgapa", rounds: int = 4) -> list[int]:
    """Labels by swaps of neighbouring places while they help; for clusters beyond exact search."""
    near = _near(n, edges)
    order = sorted(range(n), key=lambda v: (len(near[v]), v))
    label = [0] * n
    for k, v in enumerate(order):
        label[v] = k + 1
    at = {label[v]: v for v in range(n)}
    lists = [sorted(label[x] for x in nb) for nb in near]
    size = math.log2 if "log" in kind else float

    def around(v: int, x: int) -> float:
        """What label ``x`` in the list of v takes part in."""
        if "gap" not in kind:
            return size(abs(x - label[v]))
        s = lists[v]
        i = bisect_left(s, x)
        return size(x - s[i - 1] if i else abs(x - label[v])) + (size(s[i + 1] - x) if i + 1 < len(s) else 0)

    def cost(a: int, b: int, others: tuple[set, set]) -> float:
        """All that a swap of a and b may change; lists with both hold the same labels after it."""
        own = sum(size(x) for v in (a, b) for x in _differences(lists[v], label[v], kind))
        return own + sum(around(v, label[w]) for w, o in zip((a, b), others) for v in o)

    def swap(a: int, b: int, others: tuple[set, set]) -> None:
        p, q = label[a], label[b]
        beside = a in near[b]
        for v in (*others[0], *([b] if beside else [])):
            lists[v][bisect_left(lists[v], p)] = q
        for v in (*others[1], *([a] if beside else [])):
            lists[v][bisect_left(lists[v], q)] = p
        label[a], label[b] = q, p

    for _ in range(rounds):
        better = False
        for p in range(1, n):
            a, b = at[p], at[p + 1]
            others = (set(near[a]) - set(near[b]) - {b}, set(near[b]) - set(near[a]) - {a})
            old = cost(a, b, others)
            swap(a, b, others)
            if cost(a, b, others) < old - 1e-12:
                at[p], at[p + 1], better = b, a, True
            else:
                swap(a, b, others)
        if not better:
            break
    return label


def _query(kind: str):
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        g = derive.load(spark, sf_dir, "g_page_link")
        a, b = arrangement_cost(g, identity(g), kind), arrangement_cost(g, degree_permuter(g), kind)
        return a.withColumn("labels", F.lit("identity")).union(b.withColumn("labels", F.lit("degree")))

    return query


def _pod(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = derive.load(spark, sf_dir, "g_part_supp")
    return pod_cost(g, identity(g))


def _feasible(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = derive.load(spark, sf_dir, "g_page_link")
    return pod_feasible(g, degree_permuter(g))


def _small(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exact optima for the first eight suppliers: those that share more orders than a pair of them does on average are neighbours."""
    x = derive.table(spark, sf_dir, "lineitem").where("l_suppkey < 8").select("l_orderkey", F.col("l_suppkey").cast("long").alias("a")).distinct()
    shared = x.join(x.withColumnRenamed("a", "b"), "l_orderkey").where("a < b").groupBy("a", "b").count().collect()  # 28 pairs at most
    mean = sum(r["count"] for r in shared) / max(len(shared), 1)
    e = sorted((r["a"], r["b"]) for r in shared if r["count"] >= mean)
    rows = [(k, *odb_solve(8, e, k)) for k in KINDS] + [("pod", *pod_solve(8, e))]
    return spark.createDataFrame([(k, round(c, 6), [int(x) for x in p]) for k, c, p in rows], "kind string, cost double, labels array<long>")


def _kind_sql(kind: str) -> str:
    x = "CASE WHEN lag(u) OVER (PARTITION BY v ORDER BY u) IS NULL THEN abs(u - v) ELSE u - lag(u) OVER (PARTITION BY v ORDER BY u) END" if "gap" in kind else "abs(u - v)"
    total = "round(sum(log2(x)), 6)" if "log" in kind else "CAST(sum(x) AS BIGINT)"
    return derive.with_graph("g_page_link", DEGREE_SQL) + " UNION ALL ".join(f"SELECT {total} AS cost, '{n}' AS labels FROM (SELECT {x} AS x FROM {t}) q{n}" for n, t in (("identity", "cells"), ("degree", "rc")))


QUERIES = {f"cost_{k}": _query(k) for k in KINDS} | {"pod_cost": _pod, "pod_feasible": _feasible, "odb_small": _small}
ORACLES = {f"cost_{k}": _kind_sql(k) for k in KINDS} | {
    "pod_cost": derive.with_graph("g_part_supp") + "SELECT CAST(sum(abs(lo - v) + hi - lo) AS BIGINT) AS cost FROM (SELECT v, min(u) AS lo, max(u) AS hi FROM cells GROUP BY v) q",
    "pod_feasible": derive.with_graph("g_page_link") + "SELECT CAST(0 AS BIGINT) AS rows_bad, CAST(0 AS BIGINT) AS order_bad, count(*) AS n FROM cells",
}
