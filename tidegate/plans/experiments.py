"""The evaluation's workloads on the given tables, and tables of what the runs measured."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from dataclasses import replace

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tidegate.plans import learners, metrics
from tidegate.plans.learners import CNN_110K, CNN_990K, HELD_ROWS, Cnn, HeldLearner, LeastSquares, Mlp, RowLearner, Softmax, SparkLearner, StoredLearner, WindowLearner
from tidegate.plans.trainer import ASP, BSP, EBSP, GATED, GRADIENT, SSP, Policy, RunResult, TrainConfig, train
from tidegate.sources import tables

ALL = (BSP, ASP, SSP, EBSP, *GATED)
#: published settings of the two models
SMALL = TrainConfig(lr=0.1, patience=25)
LARGE = TrainConfig(lr=0.001, momentum=0.9, patience=10)
#: least squares: a rate at which it takes tens of iterations, as the published models do. A push is the whole way of 150 mini-batches
#: or so, a quarter of what is left: without a gate, twelve of them at once would go three times too far, so each is damped
TABULAR = TrainConfig(lr=0.002, patience=25, min_delta=1e-7, async_scale=1 / 12, apply_sizes="next_iteration", one_by_one=True)
#: the same without the damping, as published
UNDAMPED = replace(TABULAR, async_scale=1.0)
#: sizes as they were dealt first, whatever the workers' speeds
STATIC = replace(TABULAR, sizing=False)


def with_quiet(policies: tuple[Policy, ...], quiet_limit: int) -> tuple[Policy, ...]:
    return tuple(replace(p, gate=replace(p.gate, quiet_limit=quiet_limit)) for p in policies)


def tabular_learner(spark: SparkSession, sf: str, seed: int = 42, held: int | None = None) -> RowLearner | SparkLearner:
    """Least squares on lineitem: on the driver while it has at most HELD_ROWS training rows, else from windows that tasks sum up, with
    the same results. With `held`, more training rows than that are dealt to the workers and trained in tasks."""
    cols = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount"]
    lines = tables.load(spark, sf, "lineitem", cols)
    rows = tables.tabular_rows(lines, tables.tabular_stats(lines).first())
    count = rows.where("split = 'train'").count()
    if held is not None and count > held:
        features = F.array(*[F.col(c).cast("float") for c in ("x1", "x2", "x3")]).alias("features")
        return SparkLearner(rows.select("key", features, F.col("y").alias("label"), "split"), LeastSquares(3), len(tables.fleet_rows()), seed)
    return RowLearner(rows, seed=seed) if count <= HELD_ROWS else WindowLearner(rows, seed=seed, workers=len(tables.fleet_rows()))


IMAGE_MODELS = {"softmax": lambda: Softmax(64, 10), "cnn": lambda: CNN_110K, "small_cnn": lambda: Cnn(8, 10, (8,)), "deep_cnn": lambda: CNN_990K, "mlp": lambda: Mlp(64, 10)}


def _learner(rows: DataFrame, width: int, model, seed: int, skew: str | None = None, held: int | None = None) -> HeldLearner | SparkLearner:
    """On the driver while rows of `width` features take at most HELD_BYTES, else from windows that tasks read, with the same results. With
    `held`, rows of more bytes than that are dealt to the workers and trained in tasks."""
    size, workers = rows.count() * (8 * width + 8), len(tables.fleet_rows())
    if held is not None and size > held:
        return SparkLearner(rows, model, workers, seed, skew=skew)
    return (HeldLearner if size <= learners.HELD_BYTES else StoredLearner)(rows, model, workers, seed, skew)


def image_learner(spark: SparkSession, sf: str, model: str = "softmax", seed: int = 42, held: int | None = None) -> HeldLearner | SparkLearner:
    rows = tables.image_rows(tables.load(spark, sf, "embeddings", ["vec_id", "embedding"]))
    return _learner(rows, 64, IMAGE_MODELS[model](), seed, held=held)


def text_learner(spark: SparkSession, sf: str, model: str = "mlp", seed: int = 42, skewed: bool = True, held: int | None = None) -> HeldLearner | SparkLearner:
    """Languages of documents by letter shares. "wide": a network of 990,004 parameters, as the larger published model has."""
    rows = tables.text_rows(tables.load(spark, sf, "documents", ["doc_id", "text", "lang", "source"])).where("label is not null")
    d = len(tables.LETTERS)
    made = {"mlp": lambda: Mlp(d, 4), "wide": lambda: Mlp(d, 4, 22_500), "softmax": lambda: Softmax(d, 4)}[model]()
    return _learner(rows.select("key", "features", "label", "split"), d, made, seed, "label" if skewed else None, held)


def compare(spark: SparkSession, learner, policies=ALL, cfg: TrainConfig = SMALL, workers: list[tuple] | None = None, tag: str = "") -> list[RunResult]:
    """A run a policy, side by side where the learner allows it; one that never resizes, and whose segments one task trains, is a task."""
    fleet = workers or tables.fleet_rows()
    one = lambda p: train(spark, learner, fleet, p, cfg, p.name + tag)
    if not getattr(learner, "side_by_side", False):
        return [one(p) for p in policies]
    if learner.abreast:
        shared = learner.share()
        task = lambda p: train(None, shared.value, fleet, p, cfg, p.name + tag)
        here, one = one, lambda p: here(p) if p.kind in ("gated", "gradient") else spark.sparkContext.parallelize([p], 1).map(task).first()
    with ThreadPoolExecutor(len(policies)) as threads:
        return [f.result() for f in [threads.submit(inheritable_thread_target(spark)(one), p) for p in policies]]


def logs(spark: SparkSession, runs: list[RunResult]) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Log, trajectory and iterations of several runs in one table each."""
    whole = RunResult("all", [r for x in runs for r in x.log], [r for x in runs for r in x.trajectory], [r for x in runs for r in x.allocations])
    return whole.frames(spark)


def summary(spark: SparkSession, runs: list[RunResult], base: str = "bsp", workload: str = "w") -> DataFrame:
    """A row a run: iterations, minutes, independence, accuracy, calls, these against the base run, and what ended it."""
    log, _, _ = logs(spark, runs)
    acc = spark.createDataFrame([(r.run_id, float(r.accuracy), float(r.loss), r.stopped) for r in runs], "run_id string, accuracy double, loss double, stopped string")
    t = acc
    for measure in (metrics.total_iterations(log), metrics.time_to_converge(log), metrics.mean_independence(log), metrics.total_calls(log), metrics.bytes_moved(log).select("run_id", "bytes")):
        t = t.join(measure, "run_id", "left")  # a run without a push has no time to converge
    t = t.withColumns({"workload": F.lit(workload), "minutes": F.round("minutes", 4), "accuracy": F.round("accuracy", 6)})
    t = metrics.accuracy_delta(metrics.speedup(t, base), base)
    return t.select("workload", "run_id", "iterations", "minutes", F.round("independence", 4).alias("independence"), "accuracy", F.round("loss", 6).alias("loss"), "calls", "bytes", F.round("speedup", 4).alias("speedup"), F.round("accuracy_delta", 4).alias("accuracy_delta"), "stopped")


def scaled(learner, cfg: TrainConfig, share: float = 0.05) -> TrainConfig:
    """cfg with a first allocation of 2500 rows, or of a share of the table where that is less."""
    return replace(cfg, n0=int(max(16, min(2500, share * learner.rows))))


__all__ = ["ALL", "ASP", "BSP", "EBSP", "GATED", "GRADIENT", "LARGE", "SMALL", "SSP", "STATIC", "TABULAR", "UNDAMPED", "compare", "image_learner", "logs", "scaled", "summary", "tabular_learner", "text_learner", "with_quiet"]
