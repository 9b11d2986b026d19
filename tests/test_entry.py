"""The registered queries against their SQL, on the smallest tables."""

import os

import pytest

import __spark_entry__ as entry
from conftest import rows

SF = "/root/testdata/sf0.001"
QUICK = [
    "graph_edges_cust_supp", "graph_edges_event_window", "graph_edges_page_path", "graph_edges_conv_turns", "graph_stats_copurchase", "codec_bytes_event_window", "codec_weighted_bytes_cust_supp", "codec_hub_chunks_cust_supp",
    "packet_offsets_cust_supp", "compression_report_event_chain", "lp_two_phase_r1_page_host", "lp_capped_r2_cust_supp", "two_hop_conv_turns", "contract_cust_supp", "gain_table_hybrid", "gain_table_delta_hybrid", "refine_lp_step_cust_supp",
    "rebalance_round_cust_supp", "fm_joint_gains", "fm_prefixes", "distributed_ghosts", "baseline_matching_round", "perf_profile", "rolling_geo_ratio", "speedup_curve", "rel_asof_join_events", "sql_functions", "stream_session",
]


def test_names():
    queries, oracles = entry.queries(), entry.oracle_sql()
    assert set(oracles) <= set(queries) and len(queries) > 150


@pytest.mark.skipif(not os.path.isdir(SF), reason="no tables")
@pytest.mark.parametrize("name", QUICK)
def test_query_and_sql(spark, duck, name):
    assert rows(entry.queries()[name](spark, SF).toPandas()) == rows(duck(SF, entry.oracle_sql()[name]))


@pytest.mark.skipif(not os.path.isdir(SF), reason="no tables")
def test_flagship(spark):
    found = entry.entry(spark).collect()
    assert len(found) == 4 and all(r["feasible"] for r in found)
