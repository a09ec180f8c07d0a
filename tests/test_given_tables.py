"""Closed forms and drawn graphs follow the tables they are given."""

import pytest

import __spark_entry__

SMALL, LARGER = "/root/testdata/sf0.001", "/root/testdata/sf0.01"


@pytest.mark.parametrize("name", ["choose_r_table", "coin_table", "edges_trap", "exp_w13", "fetch_bound_grid", "fetch_ranks", "initial_share", "model_scores", "rem2_numbers", "tail_bounds", "thm4_bounds", "topk_bound_grid"])
def test_results_change_with_the_tables(spark, name):
    query = __spark_entry__.queries()[name]
    assert set(map(tuple, query(spark, SMALL).collect())) != set(map(tuple, query(spark, LARGER).collect()))
