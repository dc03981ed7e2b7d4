import duckdb
import pytest

from egoweave import catalog

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
DIR = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", ["extract_hop2_members", "sketch_signatures", "pack_sketch_order", "app_lcc", "app_motif_feedback", "iter_components", "op_asof_join", "op_interval_join", "stream_sessions", "stream_join", "graph_ba_edges", "extract_chosen_strategy", "extract_projected", "extract_vertex_lists", "sketch_ten_hashes", "pack_quality_by_order", "pack_one_agglomerative_round", "pack_sampled_oversized", "work_bins_by_order", "work_bins_by_buckets", "app_constraint", "app_pattern_match_engine", "iter_pagerank_bins", "base_gas_biparallel", "base_triplet_ppr", "sql_ego_members", "engine_user_aggregate", "stream_late_rows", "stream_ego_counts", "stream_repack"])
def test_query_equals_sql(spark, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{DIR}/{t}.parquet'")
    df = catalog.QUERIES[name](spark, DIR)
    cols = sorted(df.columns)
    got = sorted(map(repr, (tuple(r) for r in df.select(*cols).collect())))
    want = sorted(map(repr, con.execute(f"select {', '.join(cols)} from ({catalog.SQL[name]})").fetchall()))
    assert got == want and got


@pytest.mark.parametrize("op", ["union", "intersection"])
def test_pairs_of_all_edges(spark, op):
    rows = duckdb.connect().execute(f"select l_orderkey, l_partkey from '{DIR}/lineitem.parquet' where l_returnflag = 'R'").fetchall()
    parts = {}
    for order, part in rows:
        parts.setdefault(order, set()).add(part)
    edges = {(a, b) for near in parts.values() for a in near for b in near if a < b}
    ball = {v: {v} for e in edges for v in e}
    for a, b in edges:
        ball[a].add(b)
        ball[b].add(a)
    want = sorted((a, b, v) for a, b in edges for v in (ball[a] | ball[b] if op == "union" else ball[a] & ball[b]))
    got = sorted(tuple(r) for r in catalog.QUERIES[f"extract_pair_{op}"](spark, DIR).select("a", "b", "v").collect())
    assert got == want and len(edges) > 100
