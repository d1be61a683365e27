"""Registered queries beside their SQL on the smallest tables, one of each family; all of them by scripts/compare.py."""

import pytest

import __spark_entry__ as entry
from tests.compare import same, views

FAMILIES = [
    "sort_lineitem_pivots", "sort_events_recursive_bitonic", "sort_customer_layered_bitonic", "sort_documents_text", "route_bins_recursive", "place_bins_by_nation", "transpose_part_matrix",
    "suffix_sum_order_lines", "send_receive_labels_missing", "pram_write_combine_max", "treemem_write_then_read", "list_rank_user_chains", "euler_tour_nations", "contract_affine_tree", "cc_page_hosts",
    "msf_nation_trade", "cc_supplier_part", "pivot_regions_layered", "pivot_loads", "sort_layered_pivots", "bitonic_merge_two_runs", "window_neighbours", "window_frames", "group_agg_more", "outer_join_nations", "range_join_price_bands",
    "theta_join_supplier_nation", "pivot_having_segments", "quantiles_orders", "expand_join_same_nation", "bounds_T1", "bounds_T2", "bounds_T3", "cost_cache_replay", "permute_uniformity", "view_randomised", "cube_segment_region", "asof_last_purchase", "rank_window_suite", "stream_state_balances", "cost_bitonic_counts", "view_equal_inputs",
]


@pytest.mark.parametrize("name", FAMILIES)
def test_family(spark, sf, name):
    same(entry.queries()[name](spark, sf), entry.oracle_sql()[name], views(sf))


def test_names():
    assert set(entry.oracle_sql()) <= set(entry.queries()) and len(entry.queries()) > 80


def test_entry(spark):
    df = entry.entry(spark)
    assert df.columns == ["l_returnflag", "l_linestatus", "n", "sum_qty", "sum_cents"] and df.count() > 0


def test_nothing_needs_the_training_data_operators():
    import pathlib

    import oblivspark

    for f in pathlib.Path(oblivspark.__file__).parent.rglob("*.py"):
        if "llm" not in f.parts:
            assert "llm" not in f.read_text(), f
