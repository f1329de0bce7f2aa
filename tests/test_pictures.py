"""Pictures: what their steps cost, and that a table's length decides nothing."""

from dataclasses import replace

import numpy as np

from tidegate.operators.compress import carried, from_half, to_half
from tidegate.plans import experiments as x
from tidegate.plans import learners
from tidegate.plans.learners import HeldLearner, Segment, Softmax, StoredLearner

SF = "/root/testdata/sf0.001"


def test_halves_are_numpys():
    """Every half, what lies between two and next to it, and what no half holds; several vectors keep their shape."""
    halves = np.arange(1 << 16, dtype=np.uint16).view(np.float16).astype(np.float64)
    of = np.sort(halves[np.isfinite(halves)])
    between = (of[1:] + of[:-1]) / 2
    far = np.array([np.nan, np.inf, -np.inf, 1e300, -7e4, 5e-324, 0.0])
    for v in (np.concatenate((halves, between, np.nextafter(between, 1e9), np.nextafter(between, -1e9), far)), between[np.abs(between) < 3e4], np.zeros(0)):
        assert np.array_equal(carried(v, "mixed"), from_half(to_half(v)).astype(np.float64), equal_nan=True)
    assert carried(np.ones((3, 4)), "mixed").shape == (3, 4)


def test_batches_are_made_once(spark, monkeypatch):
    """The epochs of an iteration share its mini-batches, unless these are long."""
    learner, made = x.image_learner(spark, SF), []
    plain = Softmax.batches
    monkeypatch.setattr(Softmax, "batches", lambda self, *a: made.append(1) or plain(self, *a))
    segments = lambda: [Segment(w, np.zeros_like(learner.w_init), 40, 16, epochs=5, length=1) for w in range(3)]
    kept = learner.together(segments())
    assert len(made) == 3
    monkeypatch.setattr(learners, "HELD_BYTES", 0)
    anew = learner.together(segments())
    assert len(made) == 3 + 15 and all(np.array_equal(a.acc, b.acc) for a, b in zip(kept, anew, strict=True))


def test_length_decides_nothing(spark, monkeypatch):
    """Tables too long for the driver give the runs that shorter ones give: the same rows, losses over the whole test split, gates and pushes;
    pictures under softmax and a network, and documents with skewed labels under momentum. Rows of an iteration may pass the table's end."""
    cases = [
        (lambda: x.image_learner(spark, SF), x.SMALL, "mixed", (x.BSP, x.GATED[0])),
        (lambda: x.image_learner(spark, SF, "small_cnn"), x.SMALL, "fp32", (x.SSP, x.GATED[1])),
        (lambda: x.text_learner(spark, SF), replace(x.LARGE, n0=30), "fp32", (x.BSP, x.GATED[2])),
    ]
    for made, cfg, precision, policies in cases:
        with monkeypatch.context() as m:
            held = made()
            m.setattr(learners, "HELD_BYTES", 1000)
            m.setattr(StoredLearner, "SLOT_ROWS", 8)
            m.setattr(StoredLearner, "RANGES", 3)
            stored = made()
        assert type(held) is HeldLearner and type(stored) is StoredLearner and stored.slots >= 8
        assert stored.rows == held.rows and stored.row_bytes == held.row_bytes
        cfg = replace(cfg, n0=30, epochs=2, max_segment=6, max_merges=2, pushes_per_round=4, resize_every=4, precision=precision)
        for got, want in zip(x.compare(spark, stored, policies, cfg), x.compare(spark, held, policies, cfg), strict=True):
            assert got.log == want.log and got.stopped == want.stopped and [a[:6] for a in got.allocations] == [a[:6] for a in want.allocations]
            assert np.allclose([t[4:] for t in got.trajectory], [t[4:] for t in want.trajectory], atol=1e-7) and np.allclose(got.params, want.params, atol=1e-7)
            assert len(got.trajectory) > 1 and np.allclose((got.loss, got.accuracy), (want.loss, want.accuracy), atol=1e-7)
        held.close()
        stored.close()
