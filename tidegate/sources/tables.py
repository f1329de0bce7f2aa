"""Scans, derived inputs, streams and sinks."""

from __future__ import annotations

import tempfile

from pyspark.sql import Column, DataFrame, Row, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from tidegate import schema
from tidegate.functions.scalar import arithmetic_hash

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None, where: Column | str | None = None) -> DataFrame:
    """A table's scan; columns and filter reach the Parquet reader."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    if where is not None:
        df = df.where(where)
    return df if columns is None else df.select(*columns)


def with_split(df: DataFrame, key: Column) -> DataFrame:
    """15 rows of 100 are held out, by the key alone."""
    return df.withColumn("split", F.when(F.pmod(key, F.lit(20)) >= 17, "test").otherwise("train"))


def image_rows(df: DataFrame) -> DataFrame:
    """embeddings as 8x8 pictures: key, features, label (the largest of ten sums of six coordinates), split."""
    sums = F.array(*[F.aggregate(F.slice("embedding", 6 * k + 1, 6), F.lit(0.0), lambda s, x: s + x.cast("double")) for k in range(10)])
    rows = df.withColumn("_s", sums).select(F.col("vec_id").alias("key"), F.col("embedding").alias("features"), (F.array_position("_s", F.array_max("_s")) - 1).cast("int").alias("label"))
    return with_split(rows, F.col("key"))


LETTERS = "abcdefghijklmnopqrstuvwxyzäöüßéèêçñíóúá"
LANGS = ("de", "en", "es", "fr")


def text_rows(df: DataFrame) -> DataFrame:
    """documents as letter shares: key, features, label (language), source, split."""
    low, n = F.lower("text"), F.greatest(F.length("text"), F.lit(1))
    share = F.array(*[((F.length(low) - F.length(F.translate(low, c, ""))) * 10.0 / n).cast("float") for c in LETTERS])
    label = F.array_position(F.array(*[F.lit(x) for x in LANGS]), F.col("lang")) - 1
    return with_split(df.select(F.col("doc_id").alias("key"), share.alias("features"), label.cast("int").alias("label"), "source"), F.col("key"))


LINE_KEY = "l_orderkey * 7 + l_partkey * 31 + l_suppkey * 131 + l_linenumber * 1031"


RAW = {"x1": "l_quantity", "x2": "l_extendedprice", "x3": "l_discount"}


def tabular_stats(df: DataFrame) -> DataFrame:
    """One row: mean and deviation of each of lineitem's columns."""
    return df.agg(*[f(c).alias(f"{n}{k}") for k, c in RAW.items() for n, f in (("m", F.avg), ("s", F.stddev_pop))])


def tabular_rows(df: DataFrame, stats: Row | None = None) -> DataFrame:
    """lineitem as three standardised columns and a linear target with hashed noise: key, x1, x2, x3, y, split. Each scan takes the
    means and deviations first, by a scan of its own, unless they are given as tabular_stats() found them."""
    of = F.col if stats is None else lambda c: F.lit(stats[c]).cast("double")
    unit = [F.coalesce(F.try_divide(F.col(c) - of(f"m{k}"), of(f"s{k}")), F.lit(0.0)).alias(k) for k, c in RAW.items()]
    keyed = df.select(F.expr(LINE_KEY).alias("key"), *RAW.values())
    keyed = (keyed.crossJoin(F.broadcast(tabular_stats(df))) if stats is None else keyed).select("key", *unit)
    noise = arithmetic_hash(F.col("key")) / 2147483648.0 - 1
    return with_split(keyed.withColumn("y", 2 + 0.3 * F.col("x1") - 0.5 * F.col("x2") + 0.1 * F.col("x3") + 0.1 * noise), F.col("key"))


def loss_series(df: DataFrame, workers: int = 12) -> DataFrame:
    """events as losses that fall towards 0.1: worker_id, iter, ts, event_id, loss."""
    w = Window.partitionBy("worker_id").orderBy("ts", "event_id")
    rows = df.select(F.pmod("user_id", F.lit(workers)).cast("int").alias("worker_id"), "ts", "event_id", "value")
    rows = rows.withColumn("iter", F.row_number().over(w).cast("long"))
    return rows.select("worker_id", "iter", "ts", "event_id", (0.1 + 2.2 * F.exp(-F.col("iter") / 40.0) + 0.002 * F.col("value")).alias("loss"))


def tick_series(df: DataFrame, hours: int = 6, workers: int = 12) -> DataFrame:
    """Mean event value of a worker in each tick."""
    ts = df.select(F.pmod("user_id", F.lit(workers)).cast("int").alias("worker_id"), F.col("ts").cast("timestamp").alias("ts"), "value")
    return ts.groupBy("worker_id", F.window("ts", f"{hours} hours").start.alias("tick")).agg(F.avg("value").alias("loss"), F.count(F.lit(1)).alias("n"))


#: the twelve workers of the evaluation: family, how many, cores, GB; seconds a mini-batch are ours
FAMILIES = (("B1ms", 2, 1, 2, 0.048), ("F2s_v2", 3, 2, 4, 0.014), ("DS2_v2", 3, 2, 7, 0.010), ("E2ds_v4", 2, 2, 16, 0.013), ("F4s_v2", 2, 4, 8, 0.011))


def fleet_rows() -> list[tuple]:
    rows = [f for f in FAMILIES for _ in range(f[1])]
    return [(i, f[0], f[2], f[3], f[4]) for i, f in enumerate(rows)]


def fleet(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(fleet_rows(), schema.ddl(schema.WORKERS))


#: SQL of the workers that event_fleet() finds: f(worker_id, k, gb)
EVENT_FLEET = "f(worker_id, k, gb) AS (SELECT CAST(u AS INTEGER), 0.001::DOUBLE * (10 + v % 40), CAST(pow(2, 1 + v % 4) AS INTEGER) FROM (SELECT user_id % 12 AS u, abs(coalesce(sum(CAST(floor(value) AS BIGINT)), 0)) AS v FROM events GROUP BY 1))"


def event_fleet(events: DataFrame) -> DataFrame:
    """The workers that events name (user_id modulo 12), with 10 to 49 ms a mini-batch and 2 to 16 GB by the sum of their values."""
    v = F.abs(F.coalesce(F.sum(F.floor("value")), F.lit(0)))
    found = events.groupBy(F.pmod("user_id", F.lit(12)).cast("int").alias("worker_id")).agg(v.alias("_v"))
    return found.select("worker_id", (0.001 * (10 + F.col("_v") % 40)).alias("sec_per_batch"), F.pow(F.lit(2.0), 1 + F.col("_v") % 4).cast("int").alias("mem_gb"))


def big_fleet(suppliers: DataFrame) -> DataFrame:
    """suppliers as workers of many speeds."""
    speed = 0.001 * (1 + F.pmod("s_suppkey", F.lit(97)))
    return suppliers.select(F.col("s_suppkey").cast("int").alias("worker_id"), F.concat(F.lit("N"), F.col("s_nationkey")).alias("family"), F.lit(2).alias("cores"), F.lit(8).alias("mem_gb"), speed.alias("sec_per_batch"))


GRID = [(z, r) for z in (-0.9, -1.3, -1.6) for r in (0.01, 0.05, 0.1, 0.15)]


def param_grid(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(GRID, "z_cut double, relax double")


def timings(workers: DataFrame, iters: int = 10, n_rows: int = 2500, batch_rows: int = 16, epochs: int = 1, slow_worker: int | None = None, slow_from: int = 5, slow_by: float = 1.5) -> DataFrame:
    """Observed times under the time model, with one worker that slows down if wished."""
    slow = F.when((F.col("worker_id") == F.lit(slow_worker)) & (F.col("iter") >= slow_from), slow_by).otherwise(1.0)
    rows = workers.select("worker_id", "family", "sec_per_batch", F.explode(F.sequence(F.lit(1).cast("long"), F.lit(iters).cast("long"))).alias("iter"))
    t = F.col("sec_per_batch") * slow * epochs * n_rows / batch_rows
    return rows.select("worker_id", "family", "iter", F.lit(n_rows).cast("long").alias("n_rows"), F.lit(batch_rows).alias("batch_rows"), F.lit(epochs).alias("epochs"), t.alias("t_train"))


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or the context's checkpoint folder. Where neither is set, a
    local session gets a temporary one, and a cluster an error: a folder of one machine would lose or split what is written."""
    context = spark.sparkContext
    found = spark.conf.get("spark.checkpoint.dir", None) or context.getCheckpointDir()
    if not found:
        if not context.master.startswith("local") or context.master.startswith("local-cluster"):
            raise RuntimeError("spark.checkpoint.dir names no folder that driver and executors share")
        context.setCheckpointDir(tempfile.mkdtemp(prefix="tidegate-"))
        found = context.getCheckpointDir()
    return found.rstrip("/")


# ---- streams and sinks -------------------------------------------------------------------------------------------


def events_stream(spark: SparkSession, sf_dir: str, max_files: int = 1, path: str | None = None) -> DataFrame:
    """events as a stream of files; ts as a timestamp, which watermarks need."""
    kind: StructType = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    reader = spark.readStream.schema(kind).option("maxFilesPerTrigger", max_files)
    raw = reader.parquet(path) if path else reader.option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def _rated(raw: DataFrame) -> DataFrame:
    return raw.select(F.pmod("value", F.lit(12)).cast("int").alias("worker_id"), F.floor(F.col("value") / 12).alias("iter"), F.col("timestamp").alias("ts"), (0.1 + 2.2 * F.exp(-F.col("value") / 480.0)).alias("loss"))


def losses_from(spark: SparkSession, kind: str, **options) -> DataFrame:
    """A live loss stream (worker_id, iter, ts, loss) from "rate" or "kafka" (whose connector must be on the class path), or from the
    "events" of the tables in `sf_dir`, whose ids count as a rate source's values do."""
    if kind == "events":
        raw = events_stream(spark, options["sf_dir"]).select(F.col("event_id").alias("value"), F.col("ts").alias("timestamp"))
        return _rated(raw)
    raw = spark.readStream.format(kind).options(**{k: str(v) for k, v in options.items()}).load()
    if kind == "rate":
        return _rated(raw)
    body = F.from_json(F.col("value").cast("string"), "worker_id int, iter long, loss double")
    return raw.select(body.alias("b"), F.col("timestamp").alias("ts")).select("b.worker_id", "b.iter", "ts", "b.loss")


def save(df: DataFrame, path: str, form: str = "parquet", partition_by: list[str] | None = None, mode: str = "overwrite") -> None:
    writer = df.write.mode(mode).format(form)
    if form == "csv":
        writer = writer.option("header", True)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def save_bucketed(df: DataFrame, name: str, key: str, buckets: int) -> None:
    """A table bucketed and sorted by key, so that joins on it need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)


def start(df: DataFrame, sink: str, checkpoint: str | None = None, path: str | None = None, name: str | None = None, mode: str = "append", each=None):
    """Starts a stream into memory, Parquet or foreachBatch, over what there is."""
    writer = df.writeStream.outputMode(mode).trigger(availableNow=True)
    if checkpoint:
        writer = writer.option("checkpointLocation", checkpoint)
    if sink == "foreachBatch":
        return writer.foreachBatch(each).start()
    if sink == "memory":
        return writer.format("memory").queryName(name).start()
    return writer.format(sink).start(path)
