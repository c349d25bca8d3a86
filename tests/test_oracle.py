"""Registered queries against DuckDB on the smallest tables: one of each kind (the driver compares all of them)."""

import pytest
from conftest import normal

from graphwin import workloads
from graphwin.operators import relational
from graphwin.streaming import streams

PICKED = [
    "khop_direct_sum_copurchase_k2", "khop_mc_sum_copurchase_k2", "khop_emc_sum_copurchase_k2", "khop_overlay_sum_copurchase_k2", "khop_mc_waves_sum_copurchase_k2", "khop_mc_split_sum_copurchase_k2",
    "khop_direct_sum_relay_out_k2", "khop_direct_sum_relay_in_k2", "khop_direct_sum_relay_both_k1", "khop_propagate_min_copurchase_k3", "multi_function_copurchase_seq", "multi_function_copurchase_block",
    "khop_hist_brand_copurchase_k2_block", "khop_owner_subset_copurchase_k2", "khop_noself_count_copurchase_k2", "khop_topk_relay_k2", "khop_weblinks_k2_both", "khop_community_k2",
    "topo_direct_sum_eventbranch", "topo_block_sum_eventbranch", "topo_delta_jump_sum_eventbranch", "topo_delta_level_sum_dialogue", "topo_kinds_catalog", "topo_delta_jump_sum_eventchain",
    "index_cover_mc_copurchase_k2", "index_cover_delta_eventbranch", "delta_parent_eventbranch", "delta_diff_catalog", "minhash_explicit_relay_k2", "minhash_propagated_relay_k2", "jaccard_exact_copurchase_k2",
    "topo_levels_catalog_peeling", "topo_windows_by_level_catalog", "topo_levels_eventbranch", "update_insert_block_copurchase_k2", "update_delete_block_copurchase_k2", "sql_surface_khop", "graph_validate_catalog", "khop_mc_product_copurchase_k1", "khop_mc_var_double_copurchase_k2", "topo_delta_clashing_names",
    "jaccard_growth_copurchase", "expansion_bound_synthrand", "dag_stats_eventbranch", "delta_size_eventbranch", "delta_size_synthdag_d3", "topo_delta_sum_synthdag_d10", "topo_block_sum_synthdag_d3", "delta_ranges_catalog",
    "khop_mc_sum_synthrand_d80_k1", "khop_overlay_sum_weblinks_both_k1", "khop_emc_sum_copurchase_k4", "khop_similar_k1", "cluster_full_relay_k2", "cluster_estimated_relay_k2", "khop_owner_subset_block_copurchase_k2", "topo_owner_subset_delta_eventbranch",
]
STREAMS = ["st_tumbling", "st_session", "st_dedup", "st_stateful", "st_foreach_batch", "st_modes"]


@pytest.mark.parametrize("name", PICKED)
def test_window_query(spark, duck, tiny_dir, name):
    got = workloads.QUERIES[name](spark, tiny_dir)
    assert normal(got) == normal(duck.execute(workloads.ORACLES[name]))


@pytest.mark.parametrize("name", sorted(relational.ORACLES))
def test_relational_operator(spark, duck, tiny_dir, name):
    got = relational.QUERIES[name](spark, tiny_dir)
    assert normal(got) == normal(duck.execute(relational.ORACLES[name]))


@pytest.mark.parametrize("name", STREAMS)
def test_stream(spark, duck, tiny_dir, name):
    got = streams.QUERIES[name](spark, tiny_dir)
    assert normal(got) == normal(duck.execute(streams.ORACLES[name]))


def test_late_rows_are_dropped(spark, tiny_dir):
    n = streams.QUERIES["st_watermark_late"](spark, tiny_dir).toPandas()["n"].sum()
    assert 0 < n <= spark.read.parquet(f"{tiny_dir}/events.parquet").count()
