"""Queries of modes, files, table functions and streams against their SQL on the smallest tables."""

import pytest

import __spark_entry__ as entry
from oracle import connect, differences

NAMES = """g_rhg g_rdg g_topological p_sharded_conv p_sharded_once_emb_cos p_prefix_stable p_random_order_conv p_degree_order_conv
p_bfs_order_hierarchy c_counters c_queue_counters c_feasible s_adjacency s_adjacency_weighted s_edges_csv s_edges_json s_edges_orc
s_assignment s_assignment_text s_runs q_function_partition q_function_decode q_function_segments t_late_kept t_late_error
t_window_placements t_window_cut""".split()


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_its_sql(spark, sf, name):
    assert differences(entry.queries()[name](spark, sf), entry.oracle_sql()[name], connect(sf)) == ""


def test_extrapolation_has_a_forecast(spark, sf):
    from graphslice.plans.workloads import extrapolation

    rows = extrapolation(spark, sf, nodes=(200, 400)).collect()
    assert {r["metric"] for r in rows if r["algo"] == "forecast"} == {"runs", "bits", "seconds"}
    assert all(r["value"] > 0 for r in rows if r["algo"] == "forecast")
