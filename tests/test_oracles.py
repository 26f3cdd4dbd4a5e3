"""Queries against their SQL at sf0.01; one of each family (the driver compares all)."""

import pytest
from conftest import SF, plain

from packgraph import registry

SOME = (
    "size_local size_local_gap size_dmd size_local_relabel greedy_relabel ilp_objective dm_permuter aa_offsets off_select_sparse off_select_entropy off_size_entropy bound_offsets roundtrip_local_gap roundtrip_ref_interval roundtrip_prefix_near "
    "access_edge_at access_has_edge pack_bits_hash bfs_dist sssp_dist cc_labels pagerank_fixed triangle_count cost_mgapa cost_mloga pod_cost pod_feasible rb_gains cut_profile bounds_fine theory_powerlaw split_ids bfs_comm_volume timing_summary "
    "gen_kron gen_planted join_range join_asof join_interval agg_cube agg_pivot win_range topk_per_group set_except fn_bits fn_json udtf_neighbors sink_roundtrip stream_session stream_edges"
).split()


@pytest.mark.parametrize("name", SOME)
def test_query_equals_sql(spark, con, name):
    df = registry.QUERIES[name](spark, SF)
    cols = sorted(df.columns)
    got = sorted((tuple(plain(r[c]) for c in cols) for r in df.collect()), key=repr)
    c = con.execute(registry.ORACLES[name])
    names = [x[0] for x in c.description]
    assert sorted(names) == cols
    at = [names.index(x) for x in cols]
    assert got == sorted((tuple(plain(r[i]) for i in at) for r in c.fetchall()), key=repr)


def test_every_oracle_has_its_query():
    assert set(registry.ORACLES) <= set(registry.QUERIES)


@pytest.mark.parametrize("name", "fn_ceil_lg gen_er gen_grid gen_kron gen_planted theory_curve theory_er theory_powerlaw".split())
def test_query_reads_orders(spark, con, name):
    df = registry.QUERIES[name](spark, SF)
    assert any("orders.parquet" in x for x in df.inputFiles())
    want = con.execute(f"SELECT count(*) FROM ({registry.ORACLES[name]}) q").fetchone()[0]
    assert df.count() == want > 0


def test_small_arrangement_is_of_suppliers(spark, con):
    from packgraph.adjacency.arrange import KINDS, odb_solve

    shared = con.execute("SELECT a.s, b.s, count(*) FROM (SELECT DISTINCT l_orderkey o, l_suppkey s FROM lineitem) a JOIN (SELECT DISTINCT l_orderkey o, l_suppkey s FROM lineitem) b ON a.o = b.o AND a.s < b.s AND b.s < 8 GROUP BY 1, 2").fetchall()
    edges = sorted((a, b) for a, b, n in shared if n >= sum(x[2] for x in shared) / len(shared))
    got = {r["kind"]: r["cost"] for r in registry.QUERIES["odb_small"](spark, SF).collect()}
    assert 0 < len(edges) < 28 and all(got[k] == round(odb_solve(8, edges, k)[0], 6) for k in KINDS)
