"""The gate: a worker pushes when its newest held-out loss is a statistical improvement over its last losses."""

from __future__ import annotations

import warnings
from dataclasses import dataclass
from functools import reduce
from operator import add

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tidegate.functions.scalar import z_score

ORDER = ("ts", "event_id")


@dataclass(frozen=True)
class GateParams:
    """history: losses looked back on (None: all). z_cut: push at or below. relax, quiet_limit: z_cut shrinks by `relax`
    after that many iterations without a push. relax_mode "every" further quiet iteration, "once" a quiet run, or "restart"
    of the count. include_current: the newest loss counts in its own mean. min_history: losses needed before a push."""

    history: int | None = 10
    z_cut: float = -1.3
    relax: float = 0.1
    quiet_limit: int = 5
    include_current: bool = False
    sigma: str = "pop"
    min_history: int | None = None
    count_warmup: bool = True
    relax_mode: str = "every"
    reset_on_push: bool = False

    @property
    def needed(self) -> int:
        return self.min_history if self.min_history is not None else self.history or 2

    def validate(self) -> GateParams:
        """self, or ValueError; a warning where a value is outside what is advised."""
        if not -3 <= self.z_cut <= 0:
            raise ValueError(f"z_cut {self.z_cut} is outside [-3, 0]")
        if not 0 <= self.relax < 1 or self.quiet_limit < 1 or (self.history is not None and self.history < 2) or self.needed < 2:
            raise ValueError("relax must be in [0, 1), quiet_limit at least 1, history and min_history at least 2")
        if self.sigma not in ("pop", "sample") or self.relax_mode not in ("every", "once", "restart"):
            raise ValueError("sigma is pop or sample; relax_mode is every, once or restart")
        if not 0.01 <= self.relax <= 0.15:
            warnings.warn(f"relax {self.relax} is outside the advised [0.01, 0.15]", stacklevel=2)
        return self


def _window(order=ORDER):
    return Window.partitionBy("worker_id").orderBy(*order)


def _frame(p: GateParams, order):
    last = 0 if p.include_current else -1
    first = Window.unboundedPreceding if p.history is None else last - p.history + 1
    return _window(order).rowsBetween(first, last)


def loss_history(losses: DataFrame, history: int = 10, order=ORDER) -> DataFrame:
    """losses with `queue`, the last `history` losses before each."""
    return losses.withColumn("queue", F.collect_list("loss").over(_window(order).rowsBetween(-history, -1)))


def rolling_stats(losses: DataFrame, p: GateParams = GateParams(), order=ORDER) -> DataFrame:
    """losses (null ones left out) with n, mu, sigma and z; z is null before `min_history` losses and where sigma is 0.

    All come from one window: one exchange and one sort.
    """
    w = _frame(p, order)
    spread = F.stddev_pop if p.sigma == "pop" else F.stddev_samp
    out = losses.where(F.col("loss").isNotNull())
    out = out.withColumns({"n": F.count("loss").over(w), "mu": F.avg("loss").over(w), "sigma": spread("loss").over(w), "_lo": F.min("loss").over(w), "_hi": F.max("loss").over(w)})
    # equal losses have no spread, whatever rounding makes of it
    sigma = F.when(F.col("_lo") == F.col("_hi"), 0.0).otherwise(F.col("sigma"))
    ready = F.col("n") >= p.needed
    out = out.withColumn("sigma", F.when(ready, sigma)).withColumn("mu", F.when(ready, F.col("mu"))).drop("_lo", "_hi")
    return out.withColumn("z", F.when(F.col("sigma") > 0, z_score(F.col("loss"), F.col("mu"), F.col("sigma"))))


def numbered(losses: DataFrame, chunk: Column, order=ORDER, out: str = "iter") -> DataFrame:
    """losses with each worker's rows numbered in order, where `chunk` rises with the order: rows are numbered within (worker,
    chunk) and chunks' counts are added up, so that a worker of any length is spread over its chunks."""
    local = losses.withColumn("_chunk", chunk).withColumn("_n", F.row_number().over(Window.partitionBy("worker_id", "_chunk").orderBy(*order)))
    counts = local.groupBy("worker_id", "_chunk").agg(F.count(F.lit(1)).alias("_rows"))
    before = Window.partitionBy("worker_id").orderBy("_chunk").rowsBetween(Window.unboundedPreceding, -1)  # a row a chunk
    bases = counts.select("worker_id", "_chunk", F.coalesce(F.sum("_rows").over(before), F.lit(0)).alias("_base"))
    return local.join(bases, ["worker_id", "_chunk"]).withColumn(out, F.col("_base") + F.col("_n")).drop("_chunk", "_n", "_base")


def rolling_stats_chunked(losses: DataFrame, p: GateParams = GateParams(), rows: int = 100_000) -> DataFrame:
    """rolling_stats for very long series (worker_id, iter without gaps, loss never null): windows run over pieces of `rows` iterations, to
    each of which the last `history` rows of the piece before are copied."""
    if p.history is None:
        raise ValueError("a whole history has no pieces; use rolling_stats")
    piece = F.floor((F.col("iter") - 1) / rows)
    edge = (F.col("iter") - 1) % rows >= rows - p.history
    cut = losses.withColumn("_home", piece).withColumn("_piece", F.explode(F.when(edge, F.array(piece, piece + 1)).otherwise(F.array(piece))))
    stats = rolling_stats(cut.withColumnRenamed("worker_id", "_worker").withColumn("worker_id", F.struct("_worker", "_piece")), p, ("iter",))
    return stats.where("_home = _piece").drop("worker_id", "_home", "_piece").withColumnRenamed("_worker", "worker_id")


def gate_fixed(losses: DataFrame, p: GateParams = GateParams(), order=ORDER) -> DataFrame:
    """rolling_stats with `push`: z at or below a cut that never moves. history None looks back on everything."""
    return rolling_stats(losses, p, order).withColumn("push", F.coalesce((F.col("z") <= p.z_cut) & (F.col("z") < 0), (F.col("sigma") == 0) & (F.col("loss") < F.col("mu")), F.lit(False)))


def gate_every(losses: DataFrame) -> DataFrame:
    """No gate: every iteration pushes."""
    return losses.withColumn("push", F.lit(True))


def gate_adaptive(losses: DataFrame, p: GateParams = GateParams(), order=ORDER) -> DataFrame:
    """Final state of each worker: iterations, pushes, relaxations, z_cut and quiet_run. A fold over its ordered z."""
    p.validate()
    stats = rolling_stats(losses, p, order)
    fires = lambda s, r: F.coalesce((r["z"] <= s["z_cut"]) & (r["z"] < 0), (r["sigma"] == 0) & (r["loss"] < r["mu"]), F.lit(False))

    def step(s, r):
        fired = fires(s, r)
        counts = F.lit(True) if p.count_warmup else r["sigma"].isNotNull()
        quiet = F.when(fired, 0).when(counts, s["quiet_run"] + 1).otherwise(s["quiet_run"])
        due = (quiet == p.quiet_limit) if p.relax_mode == "once" else (quiet >= p.quiet_limit)
        relaxes = due & ~fired & counts
        cut = F.when(fired & F.lit(p.reset_on_push), p.z_cut).otherwise(s["z_cut"])
        return F.struct(
            F.when(relaxes, cut * (1 - p.relax)).otherwise(cut).alias("z_cut"),
            (F.when(relaxes, 0).otherwise(quiet) if p.relax_mode == "restart" else quiet).cast("long").alias("quiet_run"),
            (s["pushes"] + fired.cast("long")).alias("pushes"),
            (s["relaxed"] + relaxes.cast("long")).alias("relaxed"),
        )

    zero = F.struct(F.lit(float(p.z_cut)).alias("z_cut"), F.lit(0).cast("long").alias("quiet_run"), F.lit(0).cast("long").alias("pushes"), F.lit(0).cast("long").alias("relaxed"))
    rows = stats.groupBy("worker_id").agg(F.sort_array(F.collect_list(F.struct("iter", "z", "sigma", "mu", "loss"))).alias("rows"))
    return rows.select("worker_id", F.size("rows").cast("long").alias("iterations"), F.aggregate("rows", zero, step).alias("s")).select("worker_id", "iterations", "s.*")


class GateState:
    """One worker's gate, iteration by iteration."""

    __slots__ = ("cut", "p", "quiet", "relaxed")

    def __init__(self, p: GateParams, cut: float | None = None, quiet: int = 0, relaxed: int = 0):
        self.p, self.cut, self.quiet, self.relaxed = p, p.z_cut if cut is None else cut, quiet, relaxed

    def decide(self, z: float | None, sigma: float | None, mu: float | None, loss: float) -> tuple[bool, float]:
        """Whether this iteration pushes, and the cut that it was held against."""
        p, used = self.p, self.cut
        if z is not None:
            fired = z <= used and z < 0
        else:
            fired = sigma == 0 and loss < mu
        if fired:
            self.quiet = 0
            if p.reset_on_push:
                self.cut = p.z_cut
        elif p.count_warmup or sigma is not None:
            self.quiet += 1
            if self.quiet == p.quiet_limit if p.relax_mode == "once" else self.quiet >= p.quiet_limit:
                self.cut *= 1 - p.relax
                self.relaxed += 1
                if p.relax_mode == "restart":
                    self.quiet = 0
        return fired, used

    def observe(self, queue: list[float], loss: float) -> tuple[bool, float | None]:
        """Decides on a loss from the queue of those before it; the queue takes the loss in. Returns push and z."""
        p = self.p
        seen = [*queue, loss] if p.include_current else queue
        seen = seen if p.history is None else seen[-p.history :]
        mu = sigma = z = None
        if len(seen) >= p.needed:
            n = len(seen)
            mu = reduce(add, seen, 0.0) / n  # summed one by one, as windows and SQL do: sum() makes up for rounding, on which equal losses' pushes hang
            sigma = 0.0 if min(seen) == max(seen) else (sum((x - mu) ** 2 for x in seen) / (n if p.sigma == "pop" else n - 1)) ** 0.5
            z = (loss - mu) / sigma if sigma else None
        fired, _ = self.decide(z, sigma, mu, loss)
        queue.append(loss)
        if p.history is not None:
            del queue[: -p.history]
        return fired, z


DECISION = "worker_id int, iter long, loss double, mu double, sigma double, z double, z_cut double, quiet_run long, push boolean"


def gate_adaptive_arrow(losses: DataFrame, p: GateParams = GateParams(), order=ORDER) -> DataFrame:
    """Decision of each iteration: mu, sigma, z, the cut it was held against, the quiet run after it, and push.

    The statistics stay in the window; only the sequential cut runs in Python, over Arrow columns.
    """
    p.validate()

    def run(group: pa.Table) -> pa.Table:
        t = group.sort_by("iter")
        s, push, cut, quiet = GateState(p), [], [], []
        for z, sigma, mu, loss in zip(*(t.column(c).to_pylist() for c in ("z", "sigma", "mu", "loss")), strict=True):
            fired, used = s.decide(z, sigma, mu, loss)
            push.append(fired)
            cut.append(used)
            quiet.append(s.quiet)
        t = t.append_column("z_cut", pa.array(cut, pa.float64())).append_column("quiet_run", pa.array(quiet, pa.int64())).append_column("push", pa.array(push, pa.bool_()))
        return t.select(["worker_id", "iter", "loss", "mu", "sigma", "z", "z_cut", "quiet_run", "push"])

    stats = rolling_stats(losses, p, order).select("worker_id", "iter", "loss", "mu", "sigma", "z")
    return stats.groupBy("worker_id").applyInArrow(run, DECISION)


def gate_diagnostics(losses: DataFrame, order=ORDER) -> DataFrame:
    """How far each series is from the gate's assumptions: lag-1 correlation, drift a step, skewness and kurtosis."""
    w = _window(order)
    steps = losses.withColumn("_before", F.lag("loss").over(w))
    return steps.groupBy("worker_id").agg(
        F.count("loss").alias("n"), F.corr("loss", "_before").alias("loss_autocorr"), F.avg(F.col("loss") - F.col("_before")).alias("drift"), F.skewness("loss").alias("skewness"), F.kurtosis("loss").alias("kurtosis")
    )


def gate_gradient_change(norms: DataFrame, delta: float, order=ORDER) -> DataFrame:
    """Baseline gate: push where the squared gradient norm changes by a share of delta or more. norms has `norm2`."""
    before = F.lag("norm2").over(_window(order))
    change = F.try_divide(F.abs(F.col("norm2") - before), before)
    return norms.withColumn("change", change).withColumn("push", F.coalesce(change >= delta, F.lit(False)))
