"""Registered queries against their SQL on the smallest tables, and the driver's contract."""

import duckdb
import pytest

import __spark_entry__ as entry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: One query of each family; the driver compares all of them.
SOME = """g_page_colink_edges g_user_coact_edges g_cust_part_edges g_conv_next_edges pt_stats_nation pt_shape_copart_strong tri_per_type_nation tri_kernel_copart_strong
tri_kernel_list_nation tri_bsp_pruned_nation tri_supersteps_nation tri_recall_nation tri_colour_nation tri_placement_nation tri_probes_nation transitivity_nation tri_msgs_copart_strong_hash8
tri_supersteps_components_conv_next tri_supersteps_halves_order_cite pt_meta_diameter_nation kw_labels_vertex_nation kw_labels_subgraph_nation kw_cut_nation kw_profile_nation kw_exchange_nation
kw_weighted_nation kw_run_never_met_nation bsp_votes_nation msf_subgraph_nation msf_filter_nation msf_trees_nation single_linkage_nation bfs_subgraph_from_0_nation pagerank_nation betweenness_nation
sc_edge_text_roundtrip sc_bucketed_sink sc_edgelist_source sc_graph_range pf_pred_mix jn_price_band_pairs jn_event_asof_prev_purchase jn_topk_per_vertex_lateral ag_cut_by_sg_rollup ag_meta_matrix
wn_rank_degree wn_rolling_7d_events so_tri_sets_equal sq_recursive_paths sq_graph_degree sf_array sf_window sf_variant sf_decimal_interval ux_gini_degree ux_neighbour_pairs ss_sliding_counts
ss_session_users ss_stream_stream ss_state_degree ss_restart ss_append_windows""".split()


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return con


def plain(row):
    return tuple(round(x, 5) if isinstance(x, float) else int(x) if isinstance(x, bool) else x for x in row)


@pytest.mark.parametrize("name", SOME)
def test_query_equals_sql(spark, sf, duck, name):
    df = entry.queries()[name](spark, sf)
    names = sorted(df.columns)
    got = sorted((plain(r) for r in df.select(*[f"`{c}`" for c in names]).collect()), key=repr)
    rel = duck.execute(entry.oracle_sql()[name])
    cols = [c[0] for c in rel.description]
    assert sorted(cols) == names
    want = sorted((plain(tuple(r[cols.index(c)] for c in names)) for r in rel.fetchall()), key=repr)
    assert got == want


def test_contract(spark):
    assert len(entry.entry(spark).columns) == 4
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_late_rows_are_dropped(spark, sf):
    r = entry.queries()["ss_late_dropped"](spark, sf).first()
    assert r.dropped > 0
