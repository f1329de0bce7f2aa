"""Sizes that the monitor finds act on what begins after the merge, and learners of long tables scan them once a job."""

from dataclasses import replace

import pytest

from tests.oracle import duck
from tidegate.plans import experiments as x
from tidegate.plans import learners
from tidegate.plans import replay_sql as sql
from tidegate.sources import tables

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("delta", [0.0, 0.1, 0.2])
def test_sizes_act_after_the_merge_that_finds_them(spark, delta):
    """An iteration that has begun keeps its size, though the merge comes before its end is known."""
    learner = x.tabular_learner(spark, SF)
    run = x.train(spark, learner, tables.fleet_rows(), replace(x.GRADIENT, delta=delta), x.scaled(learner, x.TABULAR))
    ends = {}
    for row in run.log:
        if row[4] == "iter":
            ends.setdefault(row[3], []).append(row[2])
    reported = max(v[0] for v in ends.values())
    found = min(row[2] for row in run.log if row[4] == "push" and row[2] >= reported)
    first = {a[1]: a[3:5] for a in run.allocations if a[2] == 1}
    changed = [(a[1], a[2], ends[a[1]][a[2] - 1] - a[5]) for a in run.allocations if a[3:5] != first[a[1]]]
    assert changed and all(begun >= found - 1e-9 for _, _, begun in changed), [c for c in changed if c[2] < found][:3]


def test_resized_run_is_its_replay(spark):
    """A run whose monitor finds sizes while another worker has begun but not ended, against SQL: where that worker's clock goes, and so the merges."""
    learner = x.tabular_learner(spark, "/root/testdata/sf0.01")
    run = x.compare(spark, learner, (replace(x.GRADIENT, delta=0.2),), x.scaled(learner, x.TABULAR))
    got = x.summary(spark, run, workload="lineitem").toPandas()
    want = duck("/root/testdata/sf0.01", sql.gated_rows([("gradient", 0.0, 0.0, True, 0.2)], sql.RESIZED))
    for c in ("iterations", "calls", "bytes", "minutes", "accuracy"):
        assert got[c].tolist() == want[c].tolist(), c


def test_long_tables_are_scanned_once_a_job(spark, monkeypatch):
    """Means and deviations are taken once for a learner, not by a scan of each of its jobs."""
    monkeypatch.setattr(x, "HELD_ROWS", 0)
    learner = x.tabular_learner(spark, SF)
    assert isinstance(learner, learners.WindowLearner)
    assert learner.train._jdf.queryExecution().executedPlan().toString().count("FileScan") == 1


def test_given_means_make_the_same_rows(spark):
    lines = tables.load(spark, SF, "lineitem")
    order = ["key", "x1", "x2", "x3"]
    a, b = (df.toPandas().sort_values(order).reset_index(drop=True) for df in (tables.tabular_rows(lines), tables.tabular_rows(lines, tables.tabular_stats(lines).first())))
    assert a["key"].equals(b["key"]) and a["split"].equals(b["split"])
    assert (a[["x1", "x2", "x3", "y"]] - b[["x1", "x2", "x3", "y"]]).abs().max().max() < 1e-12
    none = tables.tabular_rows(lines.limit(0), tables.tabular_stats(lines.limit(0)).first())
    assert none.count() == 0
