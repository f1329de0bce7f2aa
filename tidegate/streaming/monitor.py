"""Timings as a stream: every batch brings a new allocation."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tidegate.operators import sizing


def monitor_stream(timings: DataFrame, caps: DataFrame, total_rows: int, out: str, checkpoint: str, resize: str = "outliers"):
    """Starts a stream that writes, for each batch of timings (worker_id, iter, n_rows, batch_rows, epochs, t_train), an
    allocation to `out`/batch=N. A batch that runs again overwrites its own folder."""

    def each(df: DataFrame, batch: int) -> None:
        if not df.isEmpty():
            sizing.reallocate(df, caps, total_rows, resize).write.mode("overwrite").parquet(f"{out}/batch={batch}")

    return timings.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def latest_allocation(spark: SparkSession, out: str) -> DataFrame:
    """The newest allocation of each worker."""
    rows = spark.read.parquet(out)
    return rows.groupBy("worker_id").agg(F.max_by(F.struct("status", "n_rows", "batch_rows", "t_pred"), "batch").alias("r")).select("worker_id", "r.*")
