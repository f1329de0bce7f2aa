"""Silent workers and late rows in event time."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout


def silent_workers(reports: DataFrame, silence_s: int, watermark: str = "1 hour") -> DataFrame:
    """An alarm (worker_id, last_us) for each time that a worker has sent nothing for `silence_s` seconds of event time.

    A timer in event time stands at the last report plus the silence; a later report moves it, and raises the alarm itself
    where it comes after the time and before the timer has fired.
    """

    def run(key, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            (last,) = state.get
            state.remove()
            yield pd.DataFrame({"worker_id": [int(key[0])], "last_us": [last]})
            return
        last, quiet = state.get[0] if state.exists else None, []
        for us in sorted(int(u) for b in batches for u in b["us"]):
            if last is not None and us - last > silence_s * 1_000_000:
                quiet.append(last)
            last = us if last is None else max(last, us)
        state.update((last,))
        state.setTimeoutTimestamp(max(last // 1000 + silence_s * 1000, state.getCurrentWatermarkMs() + 1))
        if quiet:
            yield pd.DataFrame({"worker_id": int(key[0]), "last_us": quiet})

    timed = reports.withWatermark("ts", watermark).select("worker_id", "ts", F.unix_micros("ts").alias("us"))
    return timed.groupBy("worker_id").applyInPandasWithState(run, "worker_id int, last_us long", "last long", "append", GroupStateTimeout.EventTimeTimeout)


def tick_counts(events: DataFrame, hours: int = 6, watermark: str = "1 hour") -> DataFrame:
    """Rows of each tick, once the watermark has passed its end; what comes later is dropped and counted by Spark's progress."""
    w = events.withWatermark("ts", watermark).groupBy(F.window("ts", f"{hours} hours").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return w.select(F.col("w.start").alias("start"), "n")


def dropped_rows(query) -> int:
    """Rows that a finished query dropped behind its watermark."""
    return sum(int(op.get("numRowsDroppedByWatermark", 0)) for p in query.recentProgress for op in p["stateOperators"])
