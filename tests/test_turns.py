"""Segments that run at once, in tasks and together, against one after another on the driver."""

from dataclasses import replace

import numpy as np

from tidegate.plans import experiments as x
from tidegate.plans.learners import HeldLearner, Segment, segment_gate
from tidegate.plans.trainer import BSP, GATED, train
from tidegate.sources import tables

SF = "/root/testdata/sf0.001"


def test_turns_in_tasks(spark, monkeypatch):
    """A long turn of a network is trained by a task a segment, with the driver's results; runs go side by side."""
    learner = x.image_learner(spark, SF, "small_cnn")
    made = lambda: [Segment(w, np.zeros_like(learner.w_init), 60, 16, epochs=2, length=14, gate=segment_gate(GATED[0].gate)) for w in range(3)]
    alone = [learner.trained(s) for s in made()]
    monkeypatch.setattr(HeldLearner, "TASK_S", 0.0)
    for a, b in zip(alone, learner.run(made()), strict=True):
        assert np.allclose(a.acc, b.acc, atol=1e-9) and np.allclose(a.losses, b.losses) and a.fired == b.fired and a.trained == b.trained
    assert learner.shared is not None
    cfg = replace(x.scaled(learner, x.SMALL, 1 / 12), max_merges=3, pushes_per_round=2)
    both = x.compare(spark, learner, (BSP, GATED[0]), cfg)
    monkeypatch.setattr(HeldLearner, "TASK_S", float("inf"))
    for got, policy in zip(both, (BSP, GATED[0]), strict=True):
        want = train(spark, learner, tables.fleet_rows(), policy, cfg)
        assert got.log == want.log and np.allclose(got.params, want.params, atol=1e-9)
    learner.close()


def test_segments_abreast(spark):
    """Steps of all workers at once give each worker's own, with gates that fire at different times, sizes that differ, momentum and half precision."""
    learner = x.image_learner(spark, SF)
    for precision, momentum in (("mixed", 0.0), ("fp16", 0.5), ("fp32", 0.9)):
        made = lambda: [Segment(w, np.zeros_like(learner.w_init), 40 + 5 * (w % 2), 16, epochs=2, length=12 + w, gate=segment_gate(GATED[0].gate) if w else None, momentum=momentum, precision=precision) for w in range(5)]  # noqa: B023, E731
        for a, b in zip([learner.trained(s) for s in made()], learner.together(made()), strict=True):
            assert a.worker_id == b.worker_id and a.iteration == b.iteration and a.fired == b.fired and a.trained == b.trained and a.gate == b.gate
            assert np.allclose(a.acc, b.acc, atol=1e-6) and np.allclose(a.losses, b.losses, atol=1e-6) and np.allclose(a.velocity, b.velocity, atol=1e-6)


def test_runs_in_tasks(spark):
    """A barrier's whole run in a task is the driver's, row by row."""
    learner = x.image_learner(spark, SF)
    cfg = replace(x.scaled(learner, x.SMALL, 1 / 12), max_merges=4, pushes_per_round=3, epochs=2)
    policies = (BSP, x.EBSP, x.ASP, x.SSP, GATED[0])
    for got, policy in zip(x.compare(spark, learner, policies, cfg), policies, strict=True):
        want = train(spark, learner, tables.fleet_rows(), policy, cfg)
        assert learner.shared is not None and got.log == want.log and got.stopped == want.stopped and np.allclose(got.params, want.params, atol=1e-9)
    learner.close()
