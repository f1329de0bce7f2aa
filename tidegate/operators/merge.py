"""Loss-weighted merging at the server, its baselines, and training from sufficient statistics."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tidegate.functions.scalar import loss_weighted_mix


def accumulate(acc: np.ndarray, step_grad: np.ndarray) -> np.ndarray:
    """A worker's summed gradient since the common start, one step on."""
    return acc + step_grad


@dataclass
class ServerState:
    """The server: parameters are w_init - lr * acc, and loss is their held-out loss.

    merge() weighs the pushed and its own accumulated gradient by the reciprocals of their losses, or with `log1p` of the logarithms of
    one plus them, which tells large losses less apart. The pushed model's loss is measured by `evaluate` (loss_source "server")
    or taken from the worker ("worker").
    """

    w_init: np.ndarray
    lr: float
    evaluate: Callable[[np.ndarray], float]
    loss_source: str = "server"
    eps: float = 1e-12
    log1p: bool = False
    acc: np.ndarray | None = None
    loss: float = float("nan")
    version: int = 0
    evaluations: int = field(default=0)

    def _measure(self, acc: np.ndarray) -> float:
        self.evaluations += 1
        return float(self.evaluate(self.w_init - self.lr * acc))

    @property
    def params(self) -> np.ndarray:
        return self.w_init if self.acc is None else self.w_init - self.lr * self.acc

    def first(self, acc: np.ndarray) -> None:
        self.acc, self.version = acc.copy(), 1
        self.loss = self._measure(self.acc)

    def merge(self, acc: np.ndarray, worker_loss: float | None = None) -> tuple[float, float]:
        """Mixes a pushed accumulator in; returns the weights (server, worker), which sum to 1."""
        if self.acc is None:
            self.first(acc)
            return 0.0, 1.0
        theirs = worker_loss if self.loss_source == "worker" and worker_loss is not None else self._measure(acc)
        mine, other = (1 / max(np.log1p(x) if self.log1p else x, self.eps) for x in (self.loss, theirs))
        if not np.isfinite(other):
            other = 0.0
        if not np.isfinite(mine):
            mine = 0.0
        total = mine + other
        if not total:
            return 1.0, 0.0
        self.acc = (mine * self.acc + other * acc) / total
        self.loss, self.version = self._measure(self.acc), self.version + 1
        return mine / total, other / total


@dataclass
class AsyncSGD:
    """Baseline: every pushed gradient is applied in full when it comes."""

    w_init: np.ndarray
    lr: float
    acc: np.ndarray | None = None
    version: int = 0

    def apply(self, grad: np.ndarray) -> None:
        self.acc = grad.copy() if self.acc is None else self.acc + grad
        self.version += 1

    @property
    def params(self) -> np.ndarray:
        return self.w_init if self.acc is None else self.w_init - self.lr * self.acc


@dataclass
class SyncSGD(AsyncSGD):
    """Baseline: one step with the mean of all workers' gradients, weighted by their rows."""

    def step(self, grads: list[tuple[np.ndarray, int]]) -> None:
        total = sum(n for _, n in grads)
        if total:
            self.apply(sum(g * (n / total) for g, n in grads))


def mix_columns(df: DataFrame, a: str, b: str, loss_a: str, loss_b: str, out: str = "mixed") -> DataFrame:
    """The merge on array columns."""
    return df.withColumn(out, loss_weighted_mix(F.col(a), F.col(b), F.col(loss_a), F.col(loss_b)))


def mean_vector(df: DataFrame, by: str, vector: Column) -> DataFrame:
    """Element-wise mean of arrays in groups: by, pos, mean. Partial sums go over the network, not vectors."""
    return df.select(by, F.posexplode(vector).alias("pos", "x")).groupBy(by, "pos").agg(F.avg(F.col("x").cast("double")).alias("mean"))


def gram_stats(df: DataFrame, features: list[str], target: str, by: list[Column]) -> DataFrame:
    """n, X'X, X'y and y'y of each group, a constant feature first: what least squares needs, in one scan."""
    x = [F.lit(1.0), *[F.col(c) for c in features]]
    d = len(x)
    sums = {f"g{i}{j}": F.sum(x[i] * x[j]) for i in range(d) for j in range(i, d)} | {f"b{i}": F.sum(x[i] * F.col(target)) for i in range(d)}
    return df.groupBy(*by).agg(F.count(F.lit(1)).alias("n"), F.sum(F.col(target) * F.col(target)).alias("yy"), *[v.alias(k) for k, v in sums.items()])


class Gram:
    """Least squares on sums: loss and gradient of the mean half squared error."""

    def __init__(self, n: float, yy: float, g: np.ndarray, b: np.ndarray):
        self.n, self.yy, self.g, self.b = n, yy, g, b

    @classmethod
    def of_row(cls, row, d: int) -> Gram:
        g = np.zeros((d, d))
        for i in range(d):
            for j in range(i, d):
                g[i, j] = g[j, i] = row[f"g{i}{j}"]
        return cls(row["n"], row["yy"], g, np.array([row[f"b{i}"] for i in range(d)]))

    def __add__(self, o: Gram) -> Gram:
        return Gram(self.n + o.n, self.yy + o.yy, self.g + o.g, self.b + o.b)

    def loss(self, p: np.ndarray) -> float:
        return float((self.yy - 2 * p @ self.b + p @ self.g @ p) / (2 * self.n))

    def gradient(self, p: np.ndarray) -> np.ndarray:
        return (self.g @ p - self.b) / self.n
