"""Queries against their SQL on the smallest tables."""

import importlib

import pytest

from oracle import duck, spark_rows
from serieslake.plans import catalog, relational
from serieslake.plans.registry import ORACLE, QUERIES

MORE = ["walk64_points", "parts64_series", "signal_windows", "user32_windows", "events_grid_fill", "prefix_sum_events", "znorm_stats", "paa8", "sax_words_walk64", "sax_words_signal256", "bucket_occupancy", "coarsen_words", "lb_matrix", "lb_word_word", "tightness_summary", "tree_nodes_parts64", "left_counts", "rightmost_size", "tree_totals_walk64", "nn1_walk64", "knn10_parts64", "nn1_signal256", "nn1_raw_vectors", "range_walk64", "self_nn", "alive_items_final_bsf", "parts_layout", "traversed_check", "helped_dedup", "sim_barrier_delay", "sim_help_failure", "src_f32_round_trip", "src_rejected_rows", "st_tumbling", "st_session", "st_ring_series", "st_append_replay", "w13_standing_queries", "approx_nn", "src_text_round_trip", "st_late_drop", "st_interval_join"]
NAMES = [q for q in QUERIES if q in ORACLE and q in relational.__dict__] + MORE


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_its_sql(spark, sf, name):
    got, want = spark_rows(QUERIES[name](spark, sf)), duck(sf, ORACLE[name])
    assert got[0] == want[0]
    assert got[1] == want[1]


def test_word_bounds_of_every_member(spark):
    sf = "/root/testdata/sf0.01"
    got, want = spark_rows(QUERIES["lb_word_word_matrix"](spark, sf)), duck(sf, ORACLE["lb_word_word_matrix"])
    assert got == want and len(got[1]) == QUERIES["lb_matrix"](spark, sf).count() > 40 * 100


def test_entry_module(spark):
    e = importlib.import_module("__spark_entry__")
    assert set(catalog.QUERIES) <= set(e.queries()) and set(e.oracle_sql()) <= set(e.queries())
    df = e.entry(spark)
    assert df.columns == ["query_id", "series_id", "dist", "rank"] and df.count() == 100
