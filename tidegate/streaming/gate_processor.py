"""The gate as a stateful processor: state in the session's RocksDB state store, for very many workers or long histories."""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import contextmanager

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.types import StructType

from tidegate.operators.gate import GateParams, GateState
from tidegate.streaming.gate_stream import DECISION, STATE

PROVIDER = "spark.sql.streaming.stateStore.providerClass"
ROCKSDB = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


class GateProcessor(StatefulProcessor):
    """One value of state a worker: queue, cut, quiet run, relaxations, last iteration."""

    def __init__(self, p: GateParams):
        self.p = p

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.state = handle.getValueState("gate", STATE)

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        queue, gate, last = [], GateState(self.p), 0
        if self.state.exists():
            q, cut, quiet, relaxed, last = self.state.get()
            queue, gate = list(q), GateState(self.p, cut, quiet, relaxed)
        out = []
        for r in pd.concat(list(rows)).sort_values("iter").itertuples():
            if r.iter <= last or r.loss != r.loss:
                continue
            used = gate.cut
            push, z = gate.observe(queue, float(r.loss))
            last = int(r.iter)
            out.append((int(key[0]), last, float(r.loss), z, used, gate.cut, push))
        self.state.update((queue, gate.cut, gate.quiet, gate.relaxed, last))
        if out:
            frame = pd.DataFrame(out, columns=["worker_id", "iter", "loss", "z", "z_cut", "next_cut", "push"])
            frame["z"] = frame["z"].astype(float)
            yield frame

    def close(self) -> None:
        pass


@contextmanager
def rocksdb_state(spark: SparkSession):
    """Streams that start in here keep their state in RocksDB; the session's setting is put back after."""
    before = spark.conf.get(PROVIDER, None)
    spark.conf.set(PROVIDER, ROCKSDB)
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(PROVIDER)
        else:
            spark.conf.set(PROVIDER, before)


def gate_by_processor(losses: DataFrame, p: GateParams = GateParams()) -> DataFrame:
    """gate_stream() on the processor; start it within rocksdb_state()."""
    schema = StructType.fromDDL(DECISION)
    return losses.select("worker_id", "iter", "loss").groupBy("worker_id").transformWithStateInPandas(GateProcessor(p.validate()), schema, "Append", "None")
