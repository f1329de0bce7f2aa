"""Least squares from windows that tasks sum up, against rows that the driver holds, and runs on long tables against SQL."""

import numpy as np
import pytest

from tests.oracle import same
from tidegate import registry
from tidegate.plans import experiments as x
from tidegate.plans import learners
from tidegate.sources import tables

SF = "/root/testdata/sf0.01"


@pytest.fixture
def long(monkeypatch):
    """Every table counts as too long for the driver."""
    monkeypatch.setattr(x, "HELD_ROWS", 0)


def rows_of(spark, sf=SF):
    return tables.tabular_rows(tables.load(spark, sf, "lineitem"))


@pytest.mark.parametrize("n, batch_rows", [(2500, 16), (333, 7), (8, 16)])
def test_windows_hold_the_drivers_rows(spark, long, n, batch_rows):
    """The same mini-batches as on the driver, also where the order's end is passed."""
    by_windows, held = x.tabular_learner(spark, SF), learners.RowLearner(rows_of(spark))
    assert type(by_windows).__name__ == "WindowLearner" and by_windows.rows == held.rows
    for w, i in ((0, 0), (11, 3), (5, 127), (2, 300)):
        for a, b in zip(by_windows.sums(w, i, n, batch_rows), held.sums(w, i, n, batch_rows), strict=True):
            assert a.shape == b.shape and np.allclose(a, b, rtol=1e-12, atol=1e-12)


def test_whole_table_is_a_window(spark, long):
    """An iteration on all rows begins and ends in the same range of the hash."""
    sf = "/root/testdata/sf0.001"
    by_windows, held = x.tabular_learner(spark, sf), learners.RowLearner(rows_of(spark, sf))
    for a, b in zip(by_windows.sums(3, 1, held.rows, 16), held.sums(3, 1, held.rows, 16), strict=True):
        assert np.allclose(a, b, rtol=1e-12, atol=1e-12)


def test_sums_that_are_done_are_dropped(spark, long, monkeypatch):
    """The driver's share of sums stays bounded, and what was dropped is read again."""
    one = x.tabular_learner(spark, SF)
    size = sum(a.nbytes for a in one.sums(0, 0, 160, 16))
    monkeypatch.setattr(learners, "HELD_BYTES", 12 * 40 * size)
    for i in range(0, 400, 4):
        for w in range(12):
            one.sums(w, i, 160, 16)
    assert sum(a.nbytes for s in one.known.values() for a in s) <= 12 * 41 * size
    assert np.allclose(one.sums(0, 0, 160, 16)[0], learners.RowLearner(rows_of(spark)).sums(0, 0, 160, 16)[0])


#: on tables over HELD_ROWS these runs took other rows, or a job an iteration
LONG_RUNS = [
    "b4_elastic_spread_run",
    "x6_stabilised_times",
    "x5_trajectory",
    "x15_merge_rules",
    "t1_gated_run",
    "r13_run_state",
    "b6_static_sizes_run",
    "b5_gradient_change_run",
    "b4_elastic_run",
    "b3_ssp_tight_run",
    "b3_ssp_run",
    "b2_asp_run",
    "b1_bsp_run",
    "x3_tabular_frameworks",
    "x17_accuracy_spread",
    "x16_communication",
    "x10_pushes_and_accuracy",
    "m16_three_seeds",
]


@pytest.mark.parametrize("name", LONG_RUNS)
def test_long_tables_match_sql(spark, long, name):
    same(registry.queries()[name](spark, SF), SF, registry.oracle_sql()[name])


def test_long_ablation_is_the_held_one(spark, monkeypatch):
    """x14 has no SQL: by windows its runs are those on held rows, half precision included."""
    held = registry.queries()["x14_ablation"](spark, SF).toPandas().sort_values("run_id").reset_index(drop=True)
    monkeypatch.setattr(x, "HELD_ROWS", 0)
    got = registry.queries()["x14_ablation"](spark, SF).toPandas().sort_values("run_id").reset_index(drop=True)
    assert got.equals(held)
