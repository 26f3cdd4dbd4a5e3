"""Algorithms on compressed forms, sizes of whole schemes, access latency, build times, overheads."""

from __future__ import annotations

import math
import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..adjacency.arrange import arrangement_cost
from ..adjacency.bisect import brb_permuter, cmb_permuter, rb_permuter
from ..adjacency.permute import apply_degree, degree_permuter, identity
from ..adjacency.transform import GapVarint, PrefixGroups
from ..algos import traverse as T
from ..core.compressed import TRANSFORMERS, CompressedGraph
from ..core.model import Graph
from ..core.store import drop, written
from ..core.weighted import WeightedGraph
from ..fine.sizes import ALL
from ..graphs import derive
from ..graphs.generate import kron, planted
from ..measure.comm import timed
from ..offsets.access import build, chosen, layout, lg_binomial, select, size_rows

FINE = ("trad", "global", "global_gap", "local", "local_gap")
SCHEMES = ("gap_varint", "ref_interval")
#: Forms that results are compared on.
RESULTS = {"bfs": (*FINE, "ref_interval"), "tc": (*FINE, "ref_interval"), "cc": ("trad", "local_gap"), "sssp": ("trad", "global", "local"), "pr": ("trad", "local")}


def forms(g: Graph, names) -> dict[str, DataFrame]:
    """Cells by codec; ``trad`` is the plain array."""
    return {k: written(g.cells().select("v", "u"), "plain") if k == "trad" else CompressedGraph.build(g, TRANSFORMERS[k]).cells() for k in names}


def weighted_forms(g: Graph) -> dict[str, DataFrame]:
    """Weighted cells: plain, and packed beside identifiers with the graph's or each list's widths."""
    return {"trad": written(g.cells(), "plain"), "global": WeightedGraph.build(g, False).cells(), "local": WeightedGraph.build(g, True).cells()}


def run(algorithm: str, g: Graph, cells: DataFrame) -> DataFrame:
    """An algorithm's result as (id, x)."""
    if algorithm == "bfs":
        return T.bfs(cells, 1).select("id", F.col("dist").alias("x"))
    if algorithm == "pr":
        return T.pagerank(cells, g.n, g.vertices()).select("id", F.col("rank").alias("x"))
    if algorithm == "cc":
        return T.connected_components(cells, g.vertices()).select("id", F.col("comp").alias("x"))
    if algorithm == "tc":
        return T.triangle_counts(cells).select("id", F.col("triangles").alias("x"))
    if algorithm == "bc":
        return T.betweenness(cells, [1]).select("id", F.col("bc").alias("x"))
    return T.sssp(cells, 1).select("id", F.col("dist").alias("x"))


def algorithm_results(spark: SparkSession, sf_dir: str) -> DataFrame:
    """codec, algorithm, n, total: what each algorithm gives on each form of one graph (number and sum of its values)."""
    out = []
    g = derive.load(spark, sf_dir, "g_page_link")
    for codec, cells in forms(g, RESULTS["bfs"]).items():
        for a in ("bfs", "cc", "tc"):
            if codec not in RESULTS[a]:
                continue
            out.append(run(a, g, cells).agg(F.count("*").alias("n"), F.sum("x").cast("long").alias("total")).select(F.lit(codec).alias("codec"), F.lit(a).alias("algorithm"), "n", "total"))
    w = derive.load(spark, sf_dir, "g_part_supp")
    for codec, cells in weighted_forms(w).items():
        cells = written(cells, "cells")
        for a in ("sssp", "pr"):
            if codec not in RESULTS[a]:
                continue
            out.append(run(a, w, cells).agg(F.count("*").alias("n"), F.sum("x").cast("long").alias("total")).select(F.lit(codec).alias("codec"), F.lit(a).alias("algorithm"), "n", "total"))
    return T.union_all(out)


def algorithm_times(spark: SparkSession, sf_dir: str, codecs=FINE, algorithms=("bfs", "pr", "cc", "bc", "tc")) -> DataFrame:
    """graph, algorithm, codec, seconds, ratio: sparse and dense Kronecker graphs, each form decoded as it is read; ratio to the plain array.
    SSSP runs on the weighted forms of a table graph."""
    rows = []

    def note(g: Graph, a: str, codec: str, cells: DataFrame, base: dict) -> None:
        began = time.perf_counter()
        run(a, g, cells).agg(F.sum("x")).collect()
        took = time.perf_counter() - began
        base.setdefault(a, took)
        rows.append((g.name, a, codec, took, took / base[a]))

    for g in (kron(spark, 8, 4), kron(spark, 8, 16)):
        g = Graph(g.name, g.n, written(g.edges, "edges"))
        base: dict[str, float] = {}
        for codec, cells in forms(g, codecs).items():
            for a in algorithms:
                note(g, a, codec, cells, base)
    g, base = derive.load(spark, sf_dir, "g_part_supp"), {}
    for codec, cells in weighted_forms(g).items():
        note(g, "sssp", codec, cells, base)
    return spark.createDataFrame(rows, "graph string, algorithm string, codec string, seconds double, ratio double")


def time_ratio(spark: SparkSession, sf_dir: str) -> DataFrame:
    """algorithm, ratio: geometric mean over graphs of the time on degree labels with gaps to that on the reference encoder's form."""
    logs: dict[str, list[float]] = {}
    for name in ("g_page_link", "g_part_supp"):
        g = derive.load(spark, sf_dir, name)
        g = Graph(g.name, g.n, written(g.edges, "edges"))  # its tables are read once, and labels made once
        labelled = g.relabel(written(degree_permuter(g), "perm"))
        labelled = Graph(g.name, g.n, written(labelled.edges, "edges"))
        ours, theirs = CompressedGraph.build(labelled, GapVarint()).cells(), CompressedGraph.build(g, TRANSFORMERS["ref_interval"]).cells()
        drop(labelled.edges), drop(g.edges)
        for a in ("bfs", "pr", "tc"):
            took = []
            for cells in (ours, theirs):
                began = time.perf_counter()
                run(a, g, cells).agg(F.sum("x")).collect()
                took.append(time.perf_counter() - began)
            logs.setdefault(a, []).append(math.log(took[0] / took[1]))
    return spark.createDataFrame([(a, math.exp(sum(x) / len(x)), len(x)) for a, x in logs.items()], "algorithm string, ratio double, graphs long")


def scheme_graphs(g: Graph, levels: int = 3, rounds: int = 2) -> dict[str, tuple[Graph, object]]:
    """Each scheme's labels and transformer."""
    rb, brb = written(rb_permuter(g, rounds), "perm"), written(brb_permuter(g, levels, rounds), "perm")
    width = max(g.n - 1, 1).bit_length()
    return {
        "dmf": (apply_degree(g), TRANSFORMERS["full_varint"]), "dmd": (apply_degree(g), GapVarint()), "rb": (g.relabel(rb), GapVarint()),
        "brb": (g.relabel(brb), PrefixGroups(levels, width, True)), "ref_interval": (g, TRANSFORMERS["ref_interval"]), "local": (g, TRANSFORMERS["local"]),
    }


def scheme_sizes(spark: SparkSession, sf_dir: str, graphs=("g_user_next", "g_page_link")) -> DataFrame:
    """graph, scheme, bits (payloads and what stands beside them, as stored), trad_bits (32 a cell), percent."""
    rows = []
    for name in graphs:
        g = derive.load(spark, sf_dir, name)
        plain = 32 * 2 * g.edges.count()
        for scheme, (labelled, t) in scheme_graphs(g).items():
            b = CompressedGraph.build(labelled, t).bits().first()
            bits = int(b["payload_bits"] or 0) + int(b["side_bits"])
            rows.append((name, scheme, bits, plain, 100 * bits / plain if plain else 0.0))
    return spark.createDataFrame(rows, "graph string, scheme string, bits long, trad_bits long, percent double")


def preprocessing(spark: SparkSession, sf_dir: str, graphs=("g_user_next",)) -> DataFrame:
    """graph, form, build_s, ratio: seconds to make each form, to those of the plain array. BRB by number of cuts."""
    rows = []
    for name in graphs:
        g = derive.load(spark, sf_dir, name)
        g = Graph(g.name, g.n, written(g.edges, "edges"))

        def took(make) -> float:
            began = time.perf_counter()
            make()
            return time.perf_counter() - began

        plain = took(lambda: written(g.adjacency(), "array").count())
        rows.append((name, "plain array", plain, 1.0))
        makers = {"dmd": lambda: CompressedGraph.build(apply_degree(g), GapVarint()), "ref_interval": lambda: CompressedGraph.build(g, TRANSFORMERS["ref_interval"]), "rb": lambda: CompressedGraph.build(g.relabel(written(rb_permuter(g, 2), "perm")), GapVarint())}
        makers |= {f"brb {k}": (lambda k=k: CompressedGraph.build(g.relabel(written(brb_permuter(g, k, 2), "perm")), PrefixGroups(k, max(g.n - 1, 1).bit_length(), True))) for k in (1, 2, 3)}
        for form, make in makers.items():
            s = took(make)
            rows.append((name, form, s, s / plain))
    return spark.createDataFrame(rows, "graph string, form string, build_s double, ratio double")


def access_latency(spark: SparkSession, sf_dir: str, tasks=(1, 2, 4, 8), each: int = 1000) -> DataFrame:
    """form, op, tasks, us: microseconds a lookup when so many tasks ask for ``each`` chosen vertices each; lists, degrees and offsets."""
    rows = []
    g = derive.load(spark, sf_dir, "g_cust_part")
    asked = {t: written(chosen(g, each * t).repartition(t), "asked") for t in tasks}
    for name in ("global", "local", "gap_varint", "ref_interval"):
        cg = CompressedGraph.build(g, TRANSFORMERS[name])
        for op in ("neighbors", "degree"):
            for t, q in asked.items():
                rows.append((name, op, t, 1e6 * timed(getattr(cg, op)(q)) / (each * t)))
    off = written(layout(g), "layout")
    for kind in ("ptr64", "ptrlog", "plain", "interleaved", "entropy", "sparse", "zlib_blocked"):
        o = written(build(off, kind), "offsets")
        for t, q in asked.items():
            rows.append((kind, "offset", t, 1e6 * timed(select(o, kind, q)) / (each * t)))
    return spark.createDataFrame(rows, "form string, op string, tasks long, us double")


def overhead(spark: SparkSession, sf_dir: str) -> DataFrame:
    """graph, kind, bits, bound_bits: an offset structure's closed size beside the least bits of any; its overhead is their ratio less one."""
    out = []
    for k in ("g_part_supp", "g_road", "g_page_link"):
        g = derive.load(spark, sf_dir, k)
        bound = float(round(lg_binomial(2 * g.edges.count(), g.n)))
        out.append(size_rows(g).withColumn("bound_bits", F.lit(bound)).withColumn("overhead_percent", F.round(100 * (F.col("bits") / F.col("bound_bits") - 1), 3)))
    return T.union_all(out).drop("block_bits")


def all_offset_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """graph, kind, n, payload_bits, index_bits, stored_bits of every kind on every table graph, from the stored structures."""
    from ..offsets.kinds import KINDS

    out = []
    for k in ALL:
        off = written(layout(derive.load(spark, sf_dir, k)), "layout")
        for kind in KINDS:
            out.append(build(off, kind).groupBy().agg(*(F.sum(c).alias(c) for c in ("n", "payload_bits", "index_bits", "stored_bits"))).select(F.lit(k).alias("graph"), F.lit(kind).alias("kind"), "n", "payload_bits", "index_bits", "stored_bits"))
    return T.union_all(out)


def after_bisection(spark: SparkSession, sf_dir: str) -> DataFrame:
    """labels, kind, stored and payload bits of offsets of coded lists (a byte a place), under given, degree and bisection labels."""
    g, out = derive.load(spark, sf_dir, "g_page_link"), []
    for labels, x in {"given": g, "degree": apply_degree(g), "bisection": g.relabel(written(rb_permuter(g, 2), "perm"))}.items():
        cg = CompressedGraph.build(x, GapVarint())
        for kind in ("ptr64", "plain", "sparse", "entropy"):
            out.append(cg.offsets(kind).groupBy().agg(F.sum("payload_bits").alias("payload_bits"), F.sum("stored_bits").alias("stored_bits")).select(F.lit(labels).alias("labels"), F.lit(kind).alias("kind"), "payload_bits", "stored_bits"))
    return T.union_all(out)


def two_communities(spark: SparkSession, sf_dir: str, sizes=(8, 16, 32)) -> DataFrame:
    """n, labels, mgapa: sums of consecutive differences under given, degree, bisection and combined labels (exact or searched inside clusters) of
    graphs with two communities whose vertices are dealt in turns."""
    rows = []
    for half in sizes:
        p = planted(spark, [half, half], 0.6, 0.05)
        turn = p.vertices().select("id", F.expr(f"if(id <= {half}, 2 * id - 1, 2 * (id - {half}))").alias("new_id"))
        g = p.relabel(turn)
        g = Graph(f"two_{2 * half}", g.n, written(g.edges, "edges"))
        levels = max(1, (2 * half // 8).bit_length() - 1)
        perms = {"given": identity(g), "degree": degree_permuter(g), "bisection": rb_permuter(g, 4), "combined": cmb_permuter(g, levels, "pod", 4)}
        for labels, perm in perms.items():
            rows.append((2 * half, labels, int(arrangement_cost(g, written(perm, "perm"), "mgapa").first()["cost"] or 0)))
        drop(g.edges)
    return spark.createDataFrame(rows, "n long, labels string, mgapa long")


QUERIES = {
    "exp_algorithm_results": algorithm_results, "exp_algorithm_times": algorithm_times, "geomean_ratio": time_ratio, "exp_scheme_sizes": scheme_sizes, "exp_preprocessing": preprocessing, "exp_access_latency": access_latency,
    "succinctness_overhead": overhead, "exp_all_offset_sizes": all_offset_sizes, "exp_offsets_after_bisection": after_bisection, "exp_two_communities": two_communities,
}


def _totals() -> str:
    """Each algorithm's result, once for each form it runs on."""
    tri = derive.with_graph("g_page_link", "tr AS (SELECT a.src AS x, a.dst AS y, b.dst AS z FROM edges a JOIN edges b ON b.src = a.dst JOIN edges c ON c.src = a.src AND c.dst = b.dst)")
    each = {
        "bfs": (RESULTS["bfs"], T.bfs_sql("g_page_link").rsplit("SELECT id, dist FROM r", 1)[0] + "SELECT count(*) AS n, CAST(sum(dist) AS BIGINT) AS total FROM r"),
        "cc": (RESULTS["cc"], f"SELECT count(*) AS n, CAST(sum(comp) AS BIGINT) AS total FROM ({T._CC_SQL}) q"),
        "tc": (RESULTS["tc"], tri + "SELECT count(DISTINCT id) AS n, CAST(nullif(count(*), 0) AS BIGINT) AS total FROM (SELECT x AS id FROM tr UNION ALL SELECT y FROM tr UNION ALL SELECT z FROM tr) q"),
        "sssp": (RESULTS["sssp"], f"SELECT count(*) AS n, CAST(sum(dist) AS BIGINT) AS total FROM ({T._SSSP_SQL}) q"),
        "pr": (RESULTS["pr"], f"SELECT count(*) AS n, CAST(sum(rank) AS BIGINT) AS total FROM ({T._PR_SQL}) q"),
    }
    return " UNION ALL ".join(f"SELECT codec, '{a}' AS algorithm, n, total FROM ({sql}) s_{a}, (SELECT unnest([{', '.join(map(repr, names))}]) AS codec) c_{a}" for a, (names, sql) in each.items())


def _overhead_sql() -> str:
    from ..offsets.access import ORACLES as O
    from ..offsets.access import _sizes_sql

    sizes = _sizes_sql(("ptr32", "ptr64", "ptrlog", "bvpl", "bvsd"))
    return f"SELECT s.graph, s.kind, s.bits, b.bits AS bound_bits, round(100 * (s.bits / b.bits - 1), 3) AS overhead_percent FROM ({sizes}) s JOIN ({O['bound_offsets']}) b ON b.graph = s.graph"


ORACLES = {"exp_algorithm_results": _totals(), "succinctness_overhead": _overhead_sql()}
