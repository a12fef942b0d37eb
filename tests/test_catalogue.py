import pytest

import __spark_entry__ as entry
from tests.oracle import SF, same

QUICK = [
    "d1_location_match", "d1_product_match", "r2_hamming", "r3_qgram", "r5_edit", "r8_conjunction", "e2_bloom", "e3_grid", "e6_uniform", "b2_grid", "b3_sorted", "b4_lsh", "b6_multi", "n1_center",
    "n4_pmf", "n5_negligible", "n6_pad", "n8_suppress", "p1_padded", "p2_prune_product", "p5_chase_prune", "p7_suppressed", "p10_expanded_run", "p14_window", "p15_one_sided", "p16_symmetric",
    "p19_coin_flip_prune", "s1_thresholds", "s5_curve", "g4_retirement", "g5_block_cost", "w3_product", "m7_slope", "m10_expected", "m12_colocation", "m13_ratio", "m15_witness", "d6_constrained",
    "w12_names", "w14_texts", "w15_passages", "w17_talks", "join_asof", "join_interval", "join_range_bucketed", "join_skew_salted", "agg_cube", "win_range", "nearest_match", "udtf_ball",
    "stream_tumbling", "stream_session", "stream_dedup", "stream_join", "stream_late", "stream_daily_padded", "c3_hamming_terms", "sql_surface",
    "r4_phonetic", "p17_profile_search", "w10_one_sided_law", "w4_location", "sql_bloom", "sql_noise_pad", "stream_budget", "c3_squares", "agg_approx_distinct",
]


@pytest.mark.parametrize("name", QUICK)
def test_query_equals_sql(spark, name):
    same(spark, name, entry.queries(), entry.oracle_sql())


def test_every_sql_has_a_query_and_entry_runs(spark):
    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert entry.entry(spark).count() == 1 and SF == entry.SMOKE
