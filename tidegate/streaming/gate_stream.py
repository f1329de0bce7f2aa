"""The gate over a stream of losses: state a worker, each decision once."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from tidegate.operators.gate import GateParams, GateState

STATE = "queue array<double>, cut double, quiet long, relaxed long, last long"
DECISION = "worker_id int, iter long, loss double, z double, z_cut double, next_cut double, push boolean"


def _fold(p: GateParams, rows: pd.DataFrame, state: GroupState) -> list[tuple]:
    queue, gate, last = [], GateState(p), 0
    if state.exists:
        q, cut, quiet, relaxed, last = state.get
        queue, gate = list(q), GateState(p, cut, quiet, relaxed)
    out = []
    for r in rows.itertuples():
        if r.iter <= last or r.loss != r.loss:  # sent again, or no loss
            continue
        used = gate.cut
        push, z = gate.observe(queue, float(r.loss))
        last = int(r.iter)
        out.append((int(r.iter), float(r.loss), z, used, gate.cut, push))
    state.update((queue, gate.cut, gate.quiet, gate.relaxed, last))
    return out


def gate_stream(losses: DataFrame, p: GateParams = GateParams()) -> DataFrame:
    """Decisions on a stream of (worker_id, iter, loss). Rows of one batch are put in order of iter; an iter at or before
    the worker's last one is a duplicate. The state is the queue of losses, the cut and the counts."""

    def run(key, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        rows = pd.concat(list(batches)).sort_values("iter")
        got = _fold(p.validate(), rows, state)
        frame = pd.DataFrame(got, columns=["iter", "loss", "z", "z_cut", "next_cut", "push"])
        frame.insert(0, "worker_id", int(key[0]))
        frame["z"] = frame["z"].astype(float)
        if len(frame):
            yield frame

    return losses.select("worker_id", "iter", "loss").groupBy("worker_id").applyInPandasWithState(run, DECISION, STATE, "append", GroupStateTimeout.NoTimeout)


def gate_over_events(events: DataFrame, p: GateParams = GateParams()) -> DataFrame:
    """The same on raw events (worker_id, event_id, ts, value): iterations are numbered by (ts, event_id) in the state, and the
    loss is that of the converging series."""
    import math

    def run(key, batches, state: GroupState):
        rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
        at = state.get[4] if state.exists else 0
        rows["iter"] = range(at + 1, at + 1 + len(rows))
        rows["loss"] = [0.1 + 2.2 * math.exp(-i / 40.0) + 0.002 * v for i, v in zip(rows["iter"], rows["value"], strict=True)]
        frame = pd.DataFrame(_fold(p, rows, state), columns=["iter", "loss", "z", "z_cut", "next_cut", "push"])
        frame.insert(0, "worker_id", int(key[0]))
        frame["z"] = frame["z"].astype(float)
        if len(frame):
            yield frame

    return events.groupBy("worker_id").applyInPandasWithState(run, DECISION, STATE, "append", GroupStateTimeout.NoTimeout)
