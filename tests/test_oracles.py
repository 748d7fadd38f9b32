"""Registered queries against their SQL on the smallest tables."""

import pytest

from tests.duck import same
from tilewright import queries as q

NAMES = [
    "universe_even", "universe_line", "grid_payload_span", "grid_quality_skew", "grid_assign_toy", "binary_tiles_even", "quad_tiles_skew", "strip_x_even", "strip_fresh_skew",
    "leastcut_tiles_skew_wide", "hilbert_tiles_even", "gray_tiles_even", "sorttile_tiles_skew", "sorttile_slab_even", "join_grid_even", "join_sorttile_skew", "join_distinct_even",
    "join_single_assign_packing", "join_one_sided_skew", "join_sweep_even", "join_subgrid_even", "join_dwithin_even", "self_join_span", "dup_pairs_grid", "realised_cost_skew",
    "cost_model_sweep", "window_query_even", "knn_even", "twolevel_join_skew", "sampled_hilbert_nearest_even", "sample_strip_skew", "refined_join_even", "stream_tile_load", "wkt_roundtrip",
    "sorttile_even_fill", "grid_nonsquare_even", "hilbert_order8_even", "twolevel_sorttile_tiles_even", "layouts_of_32", "sample_binary_even", "optimal_1d_toy", "hash_balance_skew",
    "alpha_per_tile_span", "join_difference_skew", "model_and_work_even", "session_load", "late_points", "latest_layout_even", "fullest_tiles_skew",
]


@pytest.mark.parametrize("name", NAMES)
def test_same_as_sql(spark, sf, name):
    same(spark, sf, q.QUERIES[name], q.ORACLES[name])


def test_every_query_has_sql():
    assert set(q.QUERIES) == set(q.ORACLES)
