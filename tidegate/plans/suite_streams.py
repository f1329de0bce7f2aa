"""Registered queries of streams: each runs what is there to its end and is held against the batch result."""

from __future__ import annotations

import os
import uuid

from pyspark.sql import functions as F

from tidegate.registry import query
from tidegate.sources import tables
from tidegate.streaming import gate_stream, monitor


def drained(spark, df, mode: str = "append"):
    """Rows that a stream writes, by way of files (append) or memory (complete, update)."""
    base = f"{_shared(spark)}/stream-{uuid.uuid4().hex}"
    if mode == "append":
        q = tables.start(df, "parquet", f"{base}/checkpoint", f"{base}/out")
        q.awaitTermination()
        return spark.read.schema(df.schema).parquet(f"{base}/out")
    name = "s" + uuid.uuid4().hex
    q = tables.start(df, "memory", None, name=name, mode=mode)
    q.awaitTermination()
    return spark.table(name)


_shared = tables.shared_dir


SECONDS = "epoch_us(ts) // 1000000"


@query("r81_tumbling_window", f"SELECT CAST(user_id % 12 AS INTEGER) AS worker_id, ({SECONDS}) // 21600 AS tick, count(*) AS n, round(avg(value), 6) AS loss FROM events GROUP BY 1, 2")
def _(spark, sf):
    s = tables.events_stream(spark, sf).withWatermark("ts", "1 hour").withColumn("worker_id", F.pmod("user_id", F.lit(12)).cast("int"))
    w = s.groupBy("worker_id", F.window("ts", "6 hours").alias("w")).agg(F.count(F.lit(1)).alias("n"), F.avg("value").alias("loss"))
    out = drained(spark, w.select("worker_id", F.col("w.start").alias("start"), "n", "loss"), "complete")
    return out.select("worker_id", F.floor(F.unix_micros("start") / 21600000000).alias("tick"), "n", F.round("loss", 6).alias("loss"))


@query("r82_sliding_window", f"SELECT ({SECONDS}) // 21600 - k AS tick, event_type, count(*) AS n FROM events, (VALUES (0), (1)) o(k) GROUP BY 1, 2")
def _(spark, sf):
    s = tables.events_stream(spark, sf).withWatermark("ts", "1 hour")
    w = s.groupBy(F.window("ts", "12 hours", "6 hours").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    out = drained(spark, w.select(F.col("w.start").alias("start"), "event_type", "n"), "complete")
    return out.select(F.floor(F.unix_micros("start") / 21600000000).alias("tick"), "event_type", "n")


@query("r83_session_window", f"""WITH e AS (SELECT user_id % 12 AS w, epoch_us(ts) AS t FROM events), g AS (SELECT w, t, CASE WHEN t - lag(t) OVER (PARTITION BY w ORDER BY t) < 3600000000 THEN 0 ELSE 1 END AS new FROM e),
s AS (SELECT w, t, sum(new) OVER (PARTITION BY w ORDER BY t ROWS UNBOUNDED PRECEDING) AS k FROM g)
SELECT CAST(w AS INTEGER) AS worker_id, min(t) AS start_us, count(*) AS n FROM s GROUP BY w, k""")
def _(spark, sf):
    s = tables.events_stream(spark, sf).withWatermark("ts", "1 hour").withColumn("worker_id", F.pmod("user_id", F.lit(12)).cast("int"))
    w = s.groupBy(F.session_window("ts", "1 hour").alias("w"), "worker_id").agg(F.count(F.lit(1)).alias("n"))
    out = drained(spark, w.select("worker_id", F.col("w.start").alias("start"), "n"), "complete")
    return out.select("worker_id", F.unix_micros("start").alias("start_us"), "n")


@query("r84_stream_dedup", "SELECT count(DISTINCT event_id) AS n FROM events")
def _(spark, sf):
    s = tables.events_stream(spark, sf).withWatermark("ts", "1 hour").withColumn("again", F.explode(F.array(F.lit(1), F.lit(2))))
    return drained(spark, s.dropDuplicatesWithinWatermark(["event_id"]).select("event_id")).agg(F.count(F.lit(1)).alias("n"))


@query("r88_update_mode", "SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def _(spark, sf):
    s = tables.events_stream(spark, sf).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))
    return drained(spark, s, "update").groupBy("event_type").agg(F.max("n").alias("n"))


@query("r34_stream_static_join", "SELECT CASE WHEN user_id % 12 < 2 THEN 'B1ms' WHEN user_id % 12 < 5 THEN 'F2s_v2' WHEN user_id % 12 < 8 THEN 'DS2_v2' WHEN user_id % 12 < 10 THEN 'E2ds_v4' ELSE 'F4s_v2' END AS family, count(*) AS n FROM events GROUP BY 1")
def _(spark, sf):
    s = tables.events_stream(spark, sf).withColumn("worker_id", F.pmod("user_id", F.lit(12)).cast("int"))
    named = s.join(F.broadcast(tables.fleet(spark).select("worker_id", "family")), "worker_id")  # twelve rows
    return drained(spark, named.select("event_id", "family")).groupBy("family").agg(F.count(F.lit(1)).alias("n"))


@query("r35_stream_stream_join", "SELECT count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'click' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 30 MINUTE")
def _(spark, sf):
    view = tables.events_stream(spark, sf).where("event_type = 'view'").withWatermark("ts", "1 hour").select(F.col("user_id").alias("u"), F.col("ts").alias("t"))
    click = tables.events_stream(spark, sf).where("event_type = 'click'").withWatermark("ts", "1 hour").select("user_id", "ts", "event_id")
    j = view.join(click, F.expr("u = user_id AND ts >= t AND ts <= t + INTERVAL 30 MINUTES"))
    return drained(spark, j.select("event_id")).agg(F.count(F.lit(1)).alias("n"))


def _gate_oracle() -> str:
    from tidegate.operators.gate import GateParams
    from tidegate.plans.suite_gate import adaptive_sql

    return adaptive_sql(GateParams()) + " SELECT worker_id, count(*) AS iterations, count(*) FILTER (push) AS pushes, round(arg_max(cut, iter), 6) AS z_cut FROM g GROUP BY 1"


@query("g7_gate_stream", _gate_oracle())
def _(spark, sf):
    s = tables.events_stream(spark, sf).select(F.pmod("user_id", F.lit(12)).cast("int").alias("worker_id"), "event_id", "ts", "value")
    out = drained(spark, gate_stream.gate_over_events(s))
    return out.groupBy("worker_id").agg(F.count(F.lit(1)).alias("iterations"), F.count_if("push").alias("pushes"), F.round(F.max_by("next_cut", "iter"), 6).alias("z_cut"))


def _monitor_sql() -> str:
    from tidegate.plans.suite_sizing import BOUNDS, TOTAL, batch_sql, most_rows

    fleet = ", ".join(f"({w[0]}, {w[4]}::DOUBLE)" for w in tables.fleet_rows())
    return f"""WITH f(worker_id, k) AS (VALUES {fleet}), o AS (SELECT worker_id, k, k * (2500::DOUBLE / 16) AS t FROM f), {BOUNDS}
SELECT worker_id, CASE WHEN t > hi THEN 'straggler' WHEN t < lo THEN 'underused' ELSE 'normal' END AS status, CAST(CASE WHEN t > hi OR t < lo THEN {most_rows('bs')} ELSE 2500 END AS BIGINT) AS n_rows
FROM (SELECT *, CASE WHEN k * ({TOTAL}::DOUBLE / 16) >= target THEN 16 ELSE least(16, {batch_sql(str(TOTAL))}) END AS bs FROM o, b)"""


@query("s12_monitor_stream", _monitor_sql())
def _(spark, sf):
    base = f"{_shared(spark)}/stream-{uuid.uuid4().hex}"
    tables.timings(tables.fleet(spark), iters=4).withColumn("ts", F.timestamp_seconds(F.col("iter"))).repartition(2).write.parquet(f"{base}/in")
    stream = spark.readStream.schema(spark.read.parquet(f"{base}/in").schema).parquet(f"{base}/in")
    caps = tables.fleet(spark).select("worker_id", F.lit(60_000).cast("long").alias("cap_rows"))
    monitor.monitor_stream(stream, caps, 60_000, f"{base}/out", f"{base}/checkpoint").awaitTermination()
    return monitor.latest_allocation(spark, f"{base}/out").select("worker_id", "status", "n_rows")


@query("r9_rate_source", "SELECT CAST(event_id % 12 AS INTEGER) AS worker_id, event_id // 12 AS iter, round(0.1::DOUBLE + 2.2::DOUBLE * exp(-event_id / 480.0::DOUBLE), 6) AS loss FROM events")
def _(spark, sf):
    """Losses as they come in, at the rate of events."""
    return drained(spark, tables.losses_from(spark, "events", sf_dir=sf).select("worker_id", "iter", "loss")).withColumn("loss", F.round("loss", 6))


@query("r89_foreach_batch", "SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def _(spark, sf):
    base = f"{_shared(spark)}/stream-{uuid.uuid4().hex}"
    each = lambda df, batch: df.write.mode("overwrite").parquet(os.path.join(base, "out", f"batch={batch}"))  # noqa: E731  a batch run again overwrites itself
    tables.start(tables.events_stream(spark, sf).select("event_id", "event_type"), "foreachBatch", f"{base}/checkpoint", each=each).awaitTermination()
    return spark.read.parquet(f"{base}/out").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


@query("r12_stream_sinks", "SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def _(spark, sf):
    s = tables.events_stream(spark, sf).select("event_id", "event_type")
    count = lambda df: df.groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))
    rows = count(drained(spark, s)).unionByName(drained(spark, count(s), "complete"))  # files take rows; memory, which is the driver's, counts
    return rows.groupBy("event_type").agg((F.sum("n") / 2).cast("long").alias("n"))


def late_files(spark, sf, files: int = 6) -> str:
    """events as files in order of time, with every 50th row two files late (a batch drops what is behind the watermark of
    the batch before it); returns their folder."""
    base = f"{_shared(spark)}/late-{uuid.uuid4().hex}"
    e = tables.load(spark, sf, "events", ["event_id", "ts", "user_id", "value"])
    top = e.agg(F.max("event_id")).first()[0] or 0
    part = F.least(F.floor(F.col("event_id") * files / (top + 1)) + 2 * (F.col("event_id") % 50 == 7).cast("int"), F.lit(files - 1))
    for k in range(files):
        e.where(part == k).coalesce(1).write.mode("append").parquet(f"{base}/in")
    return base


def late_stream(spark, base: str):
    raw = spark.readStream.schema("event_id long, ts timestamp_ntz, user_id long, value double").option("maxFilesPerTrigger", 1).parquet(f"{base}/in")
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


#: a row is dropped if its window ended an hour or more before the newest row of two batches ago; windows still open at the end stay unsaid
LATE = """top AS (SELECT max(event_id) + 1 AS n FROM events), f AS (SELECT epoch_us(ts) AS us, least(event_id * 6 // n + CASE WHEN event_id % 50 = 7 THEN 2 ELSE 0 END, 5) AS part FROM events, top),
m AS (SELECT p AS part, (SELECT max(us) FROM f WHERE f.part <= p - 2) AS seen FROM range(6) r(p)),
w AS (SELECT us // 21600000000 AS tick, (us // 21600000000 + 1) * 21600000000 + 3600000000 AS safe, seen FROM f JOIN m ON f.part = m.part),
k AS (SELECT tick, seen IS NOT NULL AND safe <= seen AS late FROM w WHERE safe <= (SELECT max(us) FROM f))"""


@query("r80_watermark_append", f"WITH {LATE} SELECT tick, count(*) AS n FROM k WHERE NOT late GROUP BY 1")
def _(spark, sf):
    from tidegate.streaming.alarms import tick_counts

    rows = drained(spark, tick_counts(late_stream(spark, late_files(spark, sf))))
    return rows.groupBy(F.floor(F.unix_micros("start") / 21600000000).alias("tick")).agg(F.sum("n").alias("n"))  # a window may be said twice


@query("r87_late_rows", f"WITH {LATE} SELECT CAST(count(*) FILTER (NOT late) AS BIGINT) AS kept, count(*) FILTER (late) > 0 AS dropped FROM k")
def _(spark, sf):
    from tidegate.streaming.alarms import dropped_rows, tick_counts

    base = late_files(spark, sf)
    q = tables.start(tick_counts(late_stream(spark, base)), "parquet", f"{base}/checkpoint", f"{base}/out")
    q.awaitTermination()
    kept = spark.read.schema("start timestamp, n long").parquet(f"{base}/out").agg(F.sum("n").alias("kept"))
    return kept.withColumn("dropped", F.lit(dropped_rows(q) > 0))  # Spark counts partial sums, not rows


@query("r86_silent_worker_alarm")
def _(spark, sf):
    from tidegate.streaming.alarms import silent_workers

    s = late_stream(spark, late_files(spark, sf)).withColumn("worker_id", F.pmod("user_id", F.lit(12)).cast("int"))
    return drained(spark, silent_workers(s, 2 * 3600))


@query("g7_gate_processor", _gate_oracle())
def _(spark, sf):
    """The series' losses as files, through the stateful processor."""
    from tidegate.plans.suite_gate import losses
    from tidegate.streaming.gate_processor import gate_by_processor, rocksdb_state

    base = f"{_shared(spark)}/stream-{uuid.uuid4().hex}"
    losses(spark, sf).select("worker_id", "iter", "loss").repartitionByRange(3, "iter").write.parquet(f"{base}/in")
    stream = spark.readStream.schema("worker_id int, iter long, loss double").parquet(f"{base}/in")
    with rocksdb_state(spark):
        out = drained(spark, gate_by_processor(stream))
    return out.groupBy("worker_id").agg(F.count(F.lit(1)).alias("iterations"), F.count_if("push").alias("pushes"), F.round(F.max_by("next_cut", "iter"), 6).alias("z_cut"))
