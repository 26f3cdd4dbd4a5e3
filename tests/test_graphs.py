"""Graph invariants, fixtures of the survey, and plans."""

import numpy as np
import pytest
from conftest import SF
from pyspark.sql import functions as F

from packgraph.adjacency.arrange import local_search
from packgraph.adjacency.bisect import bisect, bisect_level, brb_permuter, cmb_permuter, cut_profile, rb_permuter, shadow_pointers, vertex_cut, whole
from packgraph.adjacency.permute import degree_permuter, is_bijection
from packgraph.algos.traverse import betweenness, bfs, connected_components, sssp, triangle_counts
from packgraph.core.compressed import TRANSFORMERS, CompressedGraph
from packgraph.core.ids import global_rank, prefix_sums
from packgraph.core.model import Graph
from packgraph.fine.relabel import greedy_relabel, ilp_objective
from packgraph.fine.sizes import CODECS, sizes
from packgraph.graphs import derive, generate
from packgraph.plans.inspect import problems, pushed_filters, read_columns
from packgraph.streaming.events import btree_insert

EDGES = [(1, 5), (1, 7), (5, 7), (3, 5), (3, 7), (2, 4), (2, 6), (4, 6), (6, 8), (4, 8), (7, 8)]


@pytest.fixture(scope="module")
def example(spark):
    return Graph.from_edges("example", 8, spark.createDataFrame([(b, a, 1) for a, b in EDGES] + [(1, 5, 1), (2, 2, 1)], "src long, dst long, w long"))


def test_worked_example(example):
    got = {r["codec"]: r["bits"] for r in sizes(example, {k: CODECS[k] for k in ("global", "local")}).collect()}
    assert got == {"global": 66, "local": 82}
    perm = greedy_relabel(example)
    assert [r["new_id"] for r in perm.orderBy("id").collect()] == [7, 5, 8, 3, 1, 4, 2, 6]
    assert ilp_objective(example, perm).first()[0] == 14_000_000
    assert [r["new_id"] for r in degree_permuter(example).orderBy("id").collect()] == [6, 7, 8, 2, 3, 4, 1, 5]


@pytest.mark.parametrize("name,n,m,local", [("g_cust_order", 16500, 15000, 419113), ("g_road", 10000, 11814, 334723), ("g_page_link", 556, 1404, 26582)])
def test_fixture_sizes(spark, name, n, m, local):
    g = derive.load(spark, SF, name)
    assert (g.n, g.edges.count()) == (n, m)
    assert sizes(g, {"local": CODECS["local"]}).first()["bits"] == local


def test_empty_and_tiny_graphs(spark):
    empty = Graph("empty", 3, spark.createDataFrame([], "src long, dst long, w long"))
    assert {r["bits"] for r in sizes(empty).collect()} == {0}
    assert is_bijection(greedy_relabel(empty)).first()["n"] == 3
    one = Graph("one", 2, spark.createDataFrame([(1, 2, 0)], "src long, dst long, w long"))
    for t in TRANSFORMERS.values():
        assert sorted(map(tuple, CompressedGraph.build(one, t).cells().collect())) == [(1, 2), (2, 1)]


def test_chunked_hub(spark):
    star = Graph("star", 300, spark.range(2, 301).select(F.lit(1).cast("long").alias("src"), F.col("id").alias("dst"), F.lit(1).cast("long").alias("w")))
    cg = CompressedGraph.build(star, TRANSFORMERS["local_gap"], 64)
    assert cg.rows.where("v = 1").count() == 5
    assert cg.cells().where("v = 1").count() == 299


def test_ranks_and_prefix_sums(spark):
    df = spark.range(1000).select((F.col("id") * 7919 % 1000).alias("k"), F.col("id"))
    got = {r["k"]: (r["rank"], r["off"]) for r in prefix_sums(global_rank(df, [F.col("k")]), [F.col("k")], "k").collect()}
    assert all(got[k] == (k + 1, k * (k - 1) // 2) for k in range(1000))


def test_bisection_invariants(spark):
    g = generate.planted(spark, [16, 16], 0.6, 0.05)
    cells = g.cells()
    level = bisect_level(cells, whole(g), 4)
    sides = {r["path"]: r["count"] for r in level.groupBy("path").count().collect()}
    assert sides == {"0": 16, "1": 16}
    assert level.orderBy("id").first()["path"] == "0"
    start = cut_profile(g, bisect(g, 1, 0)).first()["edge_cut"]
    assert cut_profile(g, level).first()["edge_cut"] <= start
    cut = shadow_pointers(g, level.withColumnRenamed("path", "side")).first()
    assert cut["vertex_cut"] <= cut["edge_cut"]
    for perm in (rb_permuter(g, 1), brb_permuter(g, 2, 1), cmb_permuter(g, 2, "odb", 1), cmb_permuter(g, 2, "dm", 1)):
        b = is_bijection(perm).first()
        assert (b["n"], b["distinct_ids"], b["distinct_labels"], b["least"], b["greatest"]) == (32, 32, 32, 1, 32)


def test_algorithms_on_the_example(example):
    cells = example.cells()
    assert {r["id"]: r["dist"] for r in bfs(cells, 1).collect()} == {1: 0, 5: 1, 7: 1, 3: 2, 8: 2, 6: 3, 4: 3, 2: 4}
    assert {r["id"]: r["dist"] for r in sssp(cells, 1, 1).collect()} == {1: 0, 5: 1, 7: 1, 3: 2, 8: 2, 6: 3, 4: 3, 2: 4}
    assert {r["comp"] for r in connected_components(cells, example.vertices()).collect()} == {1}
    assert sum(r["triangles"] for r in triangle_counts(cells).collect()) == 3 * 4


@pytest.mark.parametrize("most", [6_000_000, 60, 9])
def test_triangles_by_parts(spark, most, monkeypatch):
    """However many parts there are, every triangle is found once, and no wedges are joined."""
    from itertools import combinations

    from packgraph.algos import traverse

    rng = np.random.default_rng(3)
    pairs = {(1, k) for k in range(2, 61)} | {tuple(sorted(map(int, rng.choice(60, 2, replace=False) + 1))) for _ in range(400)}
    cells = Graph.from_edges("g", 60, spark.createDataFrame([(a, b, 1) for a, b in pairs], "src long, dst long, w long")).cells().repartition(3)
    want = {t for t in combinations(range(1, 61), 3) if all(p in pairs for p in combinations(t, 2))}
    monkeypatch.setattr(traverse.triangle_parts, "__defaults__", (most,))
    got = [tuple(r) for r in traverse.triangles(cells).collect()]
    assert len(got) == len(want) > 300 and set(got) == want
    total = traverse.triangle_total(cells)
    assert total.first()[0] == len(want) and "Join" not in total._jdf.queryExecution().toString()
    assert {r["id"]: r["triangles"] for r in triangle_counts(cells).collect()} == {v: n for v in range(1, 61) if (n := sum(v in t for t in want))}
    assert traverse.triangle_total(cells.where("false")).first()[0] == 0


def test_betweenness_of_all_sources(example):
    import itertools

    near = {v: {b if a == v else a for a, b in EDGES if v in (a, b)} for v in range(1, 9)}

    def paths(s, t):
        level, found = [[s]], []
        while not found and level:
            found = [p for p in level if p[-1] == t]
            level = [[*p, u] for p in level for u in near[p[-1]] if u not in p]
        return found

    want = dict.fromkeys(near, 0.0)
    for s, t in itertools.combinations(near, 2):
        p = paths(s, t)
        for v in near:
            want[v] += sum(v in x[1:-1] for x in p) / len(p)
    got = {r["id"]: r["bc"] for r in betweenness(example.cells(), list(range(1, 9))).collect()}
    assert all(abs(got.get(v, 0) - want[v]) < 1e-6 for v in near)


def test_plans(spark):
    from packgraph.operators.relational import QUERIES

    scan = QUERIES["scan_parquet"](spark, SF)
    assert any("l_quantity" in f for f in pushed_filters(scan))
    assert all("l_extendedprice" not in c for c in read_columns(scan))
    for name in ("join_range", "join_asof", "join_interval", "win_gaps", "agg_cube"):
        assert problems(QUERIES[name](spark, SF)) == []


def test_entry():
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())


def test_vertex_cut_covers_a_long_path(spark):
    """Ascending ids along a cut path: a round takes one vertex."""
    path = Graph("path", 91, spark.range(1, 91).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"), F.lit(1).cast("long").alias("w")))
    taken = {r["id"] for r in vertex_cut(path, path.vertices().select("id", (F.col("id") % 2).alias("side"))).collect()}
    assert all(k in taken or k + 1 in taken for k in range(1, 91))


def test_large_clusters_are_solved(spark):
    n = 420
    edges = [tuple(sorted((k * 37 % n, (k + 1) * 37 % n))) for k in range(n - 1)]
    g = Graph("far", n, spark.createDataFrame([(a + 1, b + 1, 1) for a, b in edges], "src long, dst long, w long"))
    got = [r["new_id"] for r in cmb_permuter(g, 0).orderBy("id").collect()]
    assert got == local_search(n, edges) != list(range(1, n + 1))


def test_bit_vectors_of_all_vertices(spark, con):
    from packgraph.functions.sql_surface import ORACLES, QUERIES

    for name, at in (("bv_rank", "r"), ("bv_select", "second")):
        for query, sql in ((name, ORACLES[name]), (f"{name}_all", ORACLES[name].replace("WHERE v <= 60", ""))):
            got = {(r["v"], r[at]) for r in QUERIES[query](spark, SF).collect()}
            assert got == set(con.execute(f"SELECT v, {at} FROM ({sql}) q").fetchall())


def test_all_events_are_inserted(spark):
    events = spark.read.parquet(f"{SF}/events.parquet").select("event_id", F.hour("ts").alias("h")).orderBy("event_id").collect()
    zero = 0
    for k, r in enumerate(events):
        zero += min(r["h"], k + 1) <= zero
    got = sorted(r["place"] for r in btree_insert(spark, SF).collect())
    assert got == [k for k in range(len(events) + 1) if k != zero]


def test_refinement(spark):
    """Queries that refine cut fewer edges than halves by id, and the cut of two mixed cliques is near the best of all halves."""
    import itertools

    from packgraph.registry import QUERIES

    edges = derive.load(spark, SF, "g_page_link").edges.collect()
    cuts = []
    for name in ("rb_level1", "rb_level1_refined"):
        side = {r["id"]: r["path"] for r in QUERIES[name](spark, SF).collect()}
        assert abs(2 * sum(x == "0" for x in side.values()) - len(side)) <= 1
        cuts.append(sum(side[e["src"]] != side[e["dst"]] for e in edges))
    assert cuts[1] < cuts[0]
    pairs = [(a, b) for a in range(1, 11) for b in range(a + 1, 11) if a % 2 == b % 2] + [(1, 2)]
    g = Graph("mixed", 10, spark.createDataFrame([(a, b, 1) for a, b in pairs], "src long, dst long, w long"))
    every = [sum((a in h) != (b in h) for a, b in pairs) for h in itertools.combinations(range(1, 11), 5)]
    start, got = (cut_profile(g, bisect(g, 1, k)).first()["edge_cut"] for k in (0, 4))
    assert min(every) <= got < start


def test_powerlaw_of_given_vertices(spark):
    """The same graph whether the vertices are counted or given."""
    ids = spark.range(1, 201).repartition(3)
    a, b = generate.powerlaw(spark, 200, 1500.0, 2.2).edges, generate.powerlaw(spark, 200, 1500.0, 2.2, ids=ids).edges
    assert a.count() > 200 and sorted(map(tuple, a.collect())) == sorted(map(tuple, b.collect()))


def test_size_experiments_keep_no_graph(spark, monkeypatch):
    """Each graph is written once, and goes with all that was made of it; a few rows are left."""
    from packgraph.core.store import tables
    from packgraph.exp import adjacency
    from packgraph.fine import sizes as fine

    for module, query in ((fine, fine.exp_greedy_gain), (adjacency, adjacency.exp_adj_sizes)):
        monkeypatch.setattr(module, "ALL", ("g_page_link",))
        before = set(tables())
        out = query(spark, "/root/testdata/sf0.001")
        assert not out.inputFiles() and set(tables()) == before
        got = {(r["codec"], r["labels"]) if "labels" in out.columns else r["codec"]: r for r in out.collect()}
    plain = {r["codec"]: r["bits"] for r in sizes(derive.load(spark, "/root/testdata/sf0.001", "g_page_link"), adjacency.ONLY).collect()}
    assert {k: got[k, "given"]["bits"] for k in adjacency.ONLY} == plain
