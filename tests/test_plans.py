"""Physical plans: what is pushed down, what is broadcast, what is not exchanged."""

import pytest

from gradfold.plans import orders, relational, training  # noqa: F401
from gradfold.plans.registry import QUERIES
from gradfold.plans.training import lr_loss


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_filters_and_columns_reach_the_scan(spark, sf):
    text = plan(relational.project_filter(spark, sf))
    assert "PushedFilters: [IsNotNull(l_quantity)" in text and "l_comment" not in text and "l_tax" not in text.split("ReadSchema")[1]


def test_small_sides_are_broadcast(spark, sf):
    assert plan(relational.join_broadcast_nation(spark, sf)).count("BroadcastHashJoin") == 2


def test_losses_are_partial_aggregates(spark, sf):
    text = plan(lr_loss(spark, sf))
    assert "partial_sum" in text and "Python" not in text


def test_range_join_has_an_equi_key(spark, sf):
    assert "NestedLoop" not in plan(relational.join_range_price(spark, sf))


ON_TABLES = "catx_data catx_trace catx_closed_form catx_clustered_map catx_epochs catx_permutations epochs_to_tolerance merge_sparse_deltas overhead_formula_check prox_ball prox_box".split()


@pytest.mark.parametrize("name", ON_TABLES)
def test_examples_read_a_given_table(spark, sf, name):
    assert any(f.endswith(".parquet") for f in QUERIES[name](spark, sf).inputFiles())
