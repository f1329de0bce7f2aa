"""Measures over run logs (run_id, seq, vtime, worker_id, kind, bytes, global_version) and trajectories.

Kinds of log rows: iter, model_init, model_request, data, push, report, benchmark, peers. All are aggregates or windows over log keys.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

CALLS = ("model_init", "model_request", "data", "push", "report", "benchmark", "peers")


def _is(kind: str) -> Column:
    return F.count_if(F.col("kind") == kind)


def total_iterations(log: DataFrame) -> DataFrame:
    """Local iterations summed over a run's workers."""
    return log.where("kind = 'iter'").groupBy("run_id").agg(F.count(F.lit(1)).alias("iterations"))


def time_to_converge(log: DataFrame) -> DataFrame:
    """Virtual minutes to the run's last merged push."""
    return log.where("kind = 'push'").groupBy("run_id").agg((F.max("vtime") / 60).alias("minutes"))


def independence(log: DataFrame, by: tuple[str, ...] = ("run_id", "worker_id")) -> DataFrame:
    """Local iterations for each request of the global model; null where there was none."""
    return log.groupBy(*by).agg(_is("iter").alias("iterations"), _is("model_request").alias("requests")).withColumn("independence", F.try_divide("iterations", "requests"))


def mean_independence(log: DataFrame, average: str = "workers") -> DataFrame:
    """A run's independence: mean of its workers' ratios, or "pooled" ratio of sums."""
    if average == "pooled":
        return independence(log, ("run_id",)).select("run_id", "independence")
    return independence(log).groupBy("run_id").agg(F.avg("independence").alias("independence"))


def independence_rollup(log: DataFrame, families: DataFrame) -> DataFrame:
    """Independence by family and worker, by family, and over all."""
    named = log.join(F.broadcast(families.select("worker_id", "family")), "worker_id")  # a row a worker
    sums = named.rollup("family", "worker_id").agg(_is("iter").alias("iterations"), _is("model_request").alias("requests"), F.grouping_id().cast("int").alias("level"))
    return sums.withColumn("independence", F.try_divide("iterations", "requests"))


def api_calls(log: DataFrame) -> DataFrame:
    """Calls and bytes of each kind."""
    return log.where(F.col("kind").isin(*CALLS)).groupBy("run_id", "kind").agg(F.count(F.lit(1)).alias("calls"), F.sum("bytes").alias("bytes"))


def total_calls(log: DataFrame) -> DataFrame:
    return log.groupBy("run_id").agg(F.count_if(F.col("kind").isin(*CALLS)).alias("calls"))


def bytes_moved(log: DataFrame) -> DataFrame:
    """Bytes as counted, and if parameters had gone in half precision."""
    params = F.col("kind").isin("push", "model_request")
    return log.groupBy("run_id").agg(F.sum("bytes").alias("bytes"), F.sum(F.when(params, F.col("bytes") / 2).otherwise(F.col("bytes"))).alias("bytes_half"))


def speedup(runs: DataFrame, base: str, by: str = "workload") -> DataFrame:
    """Minutes of the base run over each run's, in a workload. runs: workload, run_id, minutes."""
    of_base = F.max(F.when(F.col("run_id") == base, F.col("minutes"))).over(Window.partitionBy(by))
    return runs.withColumn("speedup", F.try_divide(of_base, F.col("minutes")))


def comm_reduction(calls: DataFrame, reference: str) -> DataFrame:
    """Percent of calls saved against the reference run. calls: run_id, calls."""
    ref = calls.where(F.col("run_id") == reference).select(F.col("calls").alias("ref_calls"))
    return calls.crossJoin(F.broadcast(ref)).select("run_id", "calls", (100 * (1 - F.col("calls") / F.col("ref_calls"))).alias("reduction_pct"))  # one row


def accuracy_delta(runs: DataFrame, base: str, by: str = "workload") -> DataFrame:
    """Accuracy minus the base run's, in points."""
    of_base = F.max(F.when(F.col("run_id") == base, F.col("accuracy"))).over(Window.partitionBy(by))
    return runs.withColumn("accuracy_delta", 100 * (F.col("accuracy") - of_base))


def train_times(log: DataFrame) -> DataFrame:
    """Time between a worker's successive iterations."""
    w = Window.partitionBy("run_id", "worker_id").orderBy("vtime", "seq")
    return log.where("kind = 'iter'").withColumn("gap", F.col("vtime") - F.lag("vtime").over(w)).select("run_id", "worker_id", "seq", "vtime", "gap")


def update_gaps(log: DataFrame) -> DataFrame:
    """Time between successive pushes of a run."""
    w = Window.partitionBy("run_id").orderBy("vtime", "seq")
    return log.where("kind = 'push'").withColumn("gap", F.col("vtime") - F.lag("vtime").over(w)).select("run_id", "worker_id", "seq", "vtime", "gap")


def wait_times(log: DataFrame) -> DataFrame:
    """Waiting of each worker in a round: from its push to the last push of the same version."""
    w = Window.partitionBy("run_id", "global_version")
    return log.where("kind = 'push'").withColumn("wait", F.max("vtime").over(w) - F.col("vtime")).select("run_id", "global_version", "worker_id", "wait")


def time_spread(obs: DataFrame, by: str = "iter") -> DataFrame:
    """Mean, deviation, their ratio, and the share of times within the box-plot bounds."""
    q = obs.groupBy(by).agg(F.avg("t_train").alias("mean_t"), F.stddev_pop("t_train").alias("sd_t"), F.percentile("t_train", F.array(F.lit(0.25), F.lit(0.75))).alias("_q"))
    q = q.withColumns({"lo": F.col("_q")[0] - 1.5 * (F.col("_q")[1] - F.col("_q")[0]), "hi": F.col("_q")[1] + 1.5 * (F.col("_q")[1] - F.col("_q")[0])}).drop("_q")
    inside = obs.join(q, by).groupBy(by).agg(F.avg(F.col("t_train").between(F.col("lo"), F.col("hi")).cast("double")).alias("share_inside"))
    return q.join(inside, by).select(by, "mean_t", "sd_t", F.try_divide("sd_t", "mean_t").alias("cv"), "share_inside")


def size_trace(obs: DataFrame, worker_id: int) -> DataFrame:
    """Rows, batch size and time of one worker by iteration."""
    return obs.where(F.col("worker_id") == worker_id).select("iter", "n_rows", "batch_rows", "t_train")


def push_frequency(log: DataFrame) -> DataFrame:
    """Pushes of each run, and as a share of its iterations."""
    return log.groupBy("run_id").agg(_is("push").alias("pushes"), _is("iter").alias("iterations")).withColumn("share", F.try_divide("pushes", "iterations"))


def accuracy_steps(trajectory: DataFrame) -> DataFrame:
    """Change of the global model's accuracy at each merge."""
    w = Window.partitionBy("run_id").orderBy("global_version")
    return trajectory.withColumn("step", F.col("accuracy") - F.lag("accuracy").over(w)).select("run_id", "global_version", "worker_id", "accuracy", "step")


def mean_of_runs(results: DataFrame, config: str, values: list[str]) -> DataFrame:
    """Means over a configuration's runs, and how many there were."""
    return results.groupBy(config).agg(F.count(F.lit(1)).alias("runs"), *[F.avg(v).alias(v) for v in values])


def data_share(log: DataFrame, families: DataFrame) -> DataFrame:
    """Share of the data that each family of workers was sent."""
    named = log.where("kind = 'data'").join(F.broadcast(families.select("worker_id", "family")), "worker_id")  # a row a worker
    sums = named.groupBy("run_id", "family").agg(F.sum("bytes").alias("bytes"))
    return sums.withColumn("share", F.col("bytes") / F.sum("bytes").over(Window.partitionBy("run_id")))


def staleness(log: DataFrame) -> DataFrame:
    """Versions between a worker's last fetch of the model and its push."""
    w = Window.partitionBy("run_id", "worker_id").orderBy("vtime", "seq").rowsBetween(Window.unboundedPreceding, -1)
    fetched = F.last(F.when(F.col("kind") == "model_request", F.col("global_version")), ignorenulls=True).over(w)
    return log.withColumn("fetched", fetched).where("kind = 'push'").select("run_id", "seq", "worker_id", "global_version", (F.col("global_version") - F.col("fetched")).alias("staleness"))
