"""What workers train: least squares on rows that the driver holds, while they are few, and models trained by Spark tasks on
dealt rows of tables of any size.

A learner answers segments: local iterations of several workers, each from its own parameters, until the worker's policy
fires or the segment's length is reached. Segments do not see each other, so all of them run at once. A segment says how
many rows each of its iterations was trained on, and that is what the virtual clock charges.
"""

from __future__ import annotations

import pickle
import threading
import uuid
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tidegate.operators import sizing
from tidegate.operators.compress import carried
from tidegate.operators.gate import GateParams, GateState
from tidegate.operators.merge import Gram, gram_stats
from tidegate.plans.prefetch import Prefetcher
from tidegate.sources.tables import shared_dir


@dataclass
class Segment:
    """A worker's state on entry, and what became of it on return."""

    worker_id: int
    acc: np.ndarray
    n_rows: int
    batch_rows: int
    epochs: int = 1
    iteration: int = 0
    length: int = 1
    gate: tuple | None = None  # (GateParams, cut, quiet, relaxed)
    queue: list = field(default_factory=list)
    delta: float | None = None  # gradient-change gate
    norm2: float | None = None
    lr: float = 0.1
    momentum: float = 0.0
    precision: str = "fp32"
    velocity: np.ndarray | None = None
    # results
    losses: list = field(default_factory=list)
    zs: list = field(default_factory=list)
    trained: list = field(default_factory=list)
    fired: bool = False


def run_segment(s: Segment, w_init: np.ndarray, steps, loss_of) -> Segment:
    """Trains on: steps(iteration, n_rows, batch_rows) yields an epoch's mini-batches as (rows, gradient function), loss_of gives
    the held-out loss. With precision "fp16" or "mixed" parameters are rounded to half precision before a gradient is taken;
    "fp16" rounds the gradient too, times a loss scale that keeps small values."""
    state = GateState(s.gate[0], *s.gate[1:]) if s.gate else None
    acc = s.acc.copy()
    velocity = np.zeros_like(acc) if s.velocity is None else s.velocity
    for _ in range(s.length):
        before = acc
        acc, velocity, rows = iterated(s, before, velocity, w_init, steps(s.iteration, s.n_rows, s.batch_rows))
        looked(s, state, before, acc, rows, loss_of(w_init - s.lr * acc))
        if s.fired:
            break
    s.acc, s.velocity = acc, velocity
    return s


def iterated(s: Segment, acc: np.ndarray, velocity: np.ndarray, w_init: np.ndarray, batches) -> tuple[np.ndarray, np.ndarray, int]:
    """An iteration from `acc`, over an epoch's `batches` as often as there are epochs: where it leads, and its rows."""
    rows, batches = 0, list(batches)
    for _ in range(s.epochs):
        for n, gradient in batches:
            g = gradient(carried(w_init - s.lr * acc, s.precision))
            g = carried(g * LOSS_SCALE, s.precision) / LOSS_SCALE if s.precision == "fp16" else g
            velocity = s.momentum * velocity + g if s.momentum else g
            acc = acc + velocity
            rows += n
    return acc, velocity, rows


def looked(s: Segment, state: GateState | None, before: np.ndarray, acc: np.ndarray, rows: int, loss: float) -> None:
    """Notes an iteration that led from `before` to `acc` on so many rows of all epochs, and says whether the policy fires."""
    s.iteration += 1
    s.trained.append(rows // max(1, s.epochs))
    loss = float(loss)
    s.losses.append(loss)
    z = None
    if state is not None:
        s.fired, z = state.observe(s.queue, loss)
        s.gate = (s.gate[0], state.cut, state.quiet, state.relaxed)
    elif s.delta is not None:
        norm2 = float(((acc - before) ** 2).sum())
        s.fired = s.norm2 is not None and s.norm2 > 0 and abs(norm2 - s.norm2) / s.norm2 >= s.delta
        s.norm2 = norm2
    else:
        s.fired = True
    s.zs.append(z)


def run_abreast(segments: list[Segment], w_init: np.ndarray, places, model, x: np.ndarray, y: np.ndarray, loss_of) -> None:
    """run_segment() for segments of one size, step by step for all of them at once; places(segment) are an iteration's rows."""
    first = segments[0]
    for s in segments:
        s.velocity = np.zeros_like(s.acc) if s.velocity is None else s.velocity
    states = [GateState(s.gate[0], *s.gate[1:]) if s.gate else None for s in segments]
    live = list(range(len(segments)))
    ends = [s.iteration + s.length for s in segments]
    while live:
        at = np.stack([places(segments[k]) for k in live])
        before, velocity = (np.stack([getattr(segments[k], name) for k in live]) for name in ("acc", "velocity"))
        acc = before.copy()
        parts = [at[:, a : a + first.batch_rows] for a in range(0, at.shape[1], first.batch_rows)]
        keep = first.epochs > 1 and at.size * x.shape[1] * 16 <= HELD_BYTES // 2
        made = [model.batches(x[part], y[part]) for part in parts] if keep else None  # else made anew in each epoch
        for _ in range(first.epochs):
            for batch in made or (model.batches(x[part], y[part]) for part in parts):
                point = acc * -first.lr
                point += w_init
                g = model.gradients(carried(point, first.precision), *batch)
                g = carried(g * LOSS_SCALE, first.precision) / LOSS_SCALE if first.precision == "fp16" else g
                velocity = first.momentum * velocity + g if first.momentum else g
                acc += velocity
        for row, k in enumerate(live):
            s = segments[k]
            s.acc, s.velocity = acc[row].copy(), velocity[row].copy()
            looked(s, states[k], before[row], s.acc, first.epochs * at.shape[1], loss_of(w_init - s.lr * s.acc))
        live = [k for k in live if not segments[k].fired and segments[k].iteration < ends[k]]


LOSS_SCALE = 1024.0
HELD_ROWS = 4_000_000  # rows of four numbers that the driver holds at most
HELD_BYTES = 128 << 20  # and of others; longer tables are trained by tasks
BUCKETS = 1 << 20  # of rows whose order labels skew


def first_place(worker_id: int, iteration: int, seed: int, rows: int) -> int:
    """Where in the hashed order of rows an iteration of a worker begins: arithmetic that SQL can repeat."""
    return ((worker_id * 7919 + iteration * 104729 + seed) % 1000003 * 2654435761) % 4294967296 % rows


def reached(begins: np.ndarray, first: int, n: int) -> tuple[int, list[tuple[int, int]]]:
    """Of n rows in order from place `first`, and on from the start where the end is passed: how many rows of their first slot come before
    them, and their slots as (slot, turn), turn 1 those from the start. Slot k has the places from begins[k] to begins[k + 1]."""
    rows, at = int(begins[-1]), lambda v: int(np.searchsorted(begins, v, "right")) - 1
    turns = enumerate(((first, min(first + n, rows)), (0, first + n - rows)))
    return first - int(begins[at(first)]), [(slot, turn) for turn, (a, z) in turns if a < z for slot in range(at(a), at(z - 1) + 1)]


def slotted(df: DataFrame, slot, slots: int, least: int) -> np.ndarray:
    """Where each slot of df's rows begins, slot(n) being a row's of n: of so many slots, or fewer, where these would have less than `least` rows on average."""
    held = df.groupBy(slot(slots).alias("_slot")).count().toArrow()  # at most `slots` rows
    counts = np.zeros(slots, np.int64)
    counts[held.column("_slot").to_numpy()] = held.column("count").to_numpy()
    while len(counts) > 1 and counts.sum() < len(counts) * least:
        counts = counts.reshape(-1, 2).sum(1)
    return np.concatenate(([0], np.cumsum(counts)))


def batch_sums(x: np.ndarray, y: np.ndarray, batch_rows: int) -> tuple[np.ndarray, np.ndarray]:
    """Means of X'X and X'y of each mini-batch, in order; the last one may be shorter."""
    n, whole = len(y), len(y) // batch_rows
    cut = whole * batch_rows
    xs, ys = x[:cut].reshape(whole, batch_rows, x.shape[1]), y[:cut].reshape(whole, batch_rows)
    g, b = np.einsum("kni,knj->kij", xs, xs) / batch_rows, np.einsum("kni,kn->ki", xs, ys) / batch_rows
    if cut < n:
        g, b = np.concatenate((g, (x[cut:].T @ x[cut:] / (n - cut))[None])), np.concatenate((b, (x[cut:].T @ y[cut:] / (n - cut))[None]))
    return g, b


class RowLearner:
    """Least squares on at most HELD_ROWS training rows, in an order by hash of key. An iteration of a worker takes as many
    neighbouring rows as it is allotted, from a place that worker and iteration give, in mini-batches of neighbours; a
    mini-batch's gradient is taken from its sums. Held-out loss and score are those of the whole test split, by its sums."""

    def __init__(self, rows: DataFrame, features=("x1", "x2", "x3"), target: str = "y", seed: int = 42):
        from tidegate.functions.scalar import arithmetic_hash

        d = len(features) + 1
        order = [arithmetic_hash(F.col("key") * 13 + seed).alias("_h"), "key", *features, target]
        got = rows.where("split = 'train'").select(*order).toArrow().sort_by([(c, "ascending") for c in ("_h", "key", *features)])
        self.x = np.stack([np.ones(got.num_rows), *(got.column(c).to_numpy() for c in features)], axis=1)
        self.y = got.column(target).to_numpy()
        held_out = gram_stats(rows.where("split = 'test'"), list(features), target, [F.lit(1).alias("one")]).first()
        self.test = Gram.of_row(held_out, d) if held_out else Gram(got.num_rows, float(self.y @ self.y), self.x.T @ self.x, self.x.T @ self.y)
        self.rows, self.seed = got.num_rows, seed
        self.w_init = np.zeros(d)
        self.row_bytes = 8 * d

    def sums(self, worker_id: int, iteration: int, n: int, batch_rows: int) -> tuple[np.ndarray, np.ndarray]:
        at = (first_place(worker_id, iteration, self.seed, self.rows) + np.arange(n)) % self.rows
        return batch_sums(self.x[at], self.y[at], batch_rows)

    def steps(self, worker_id: int):
        def run(iteration, n_rows, batch_rows):
            n = min(n_rows, self.rows)
            g, b = self.sums(worker_id, iteration, n, batch_rows)
            for k in range(len(b)):
                yield min(batch_rows, n - k * batch_rows), lambda p, k=k: g[k] @ p - b[k]

        return run

    def run(self, segments: list[Segment]) -> list[Segment]:
        return [run_segment(s, self.w_init, self.steps(s.worker_id), self.test.loss) for s in segments]

    def evaluate(self, params: np.ndarray) -> tuple[float, float]:
        """Held-out loss, and the share of variance explained in place of an accuracy."""
        loss = self.test.loss(params)
        mean = self.test.b[0] / self.test.n
        total = self.test.yy / self.test.n - mean**2
        return loss, float(1 - 2 * loss / total) if total > 0 else 0.0

    def close(self) -> None:
        pass


class WindowLearner(RowLearner):
    """RowLearner for any number of training rows, with its order, places, mini-batches and results. The driver holds how many rows
    each of SLOTS ranges of the hash has (fewer, where these would have less than SLOT_ROWS on average), which tells the ranges that an iteration's rows lie in, and mini-batches' sums. A job takes
    them from one scan for many iterations of all workers, those to come; a group of a task is the rows of a few iterations and
    their ranges' others. Sums of more than HELD_BYTES are dropped, those of iterations long done first, and read again if a run starts over."""

    SLOTS, SLOT_ROWS, AHEAD, GROUP_ROWS = 1 << 16, 256, 128, 50_000

    def __init__(self, rows: DataFrame, features=("x1", "x2", "x3"), target: str = "y", seed: int = 42, workers: int = 12):
        from tidegate.functions.scalar import arithmetic_hash

        d = len(features) + 1
        train = rows.where("split = 'train'").select(arithmetic_hash(F.col("key") * 13 + seed).alias("_h"), "key", *features, target)
        slot = lambda n: F.floor(F.col("_h") / ((1 << 32) // n)).cast("int")
        self.begins = slotted(train, slot, self.SLOTS, self.SLOT_ROWS)
        self.train = train.withColumn("_slot", slot(len(self.begins) - 1))
        self.rows, self.seed, self.features, self.target = int(self.begins[-1]), seed, list(features), target
        one = lambda df: gram_stats(df, list(features), target, [F.lit(1).alias("one")]).first()
        self.test = Gram.of_row(one(rows.where("split = 'test'")) or one(train), d)
        self.w_init, self.row_bytes = np.zeros(d), 8 * d
        self.at: dict[int, tuple[int, int, int]] = {w: (0, 0, 0) for w in range(workers)}  # iteration, rows and mini-batch of each worker
        self.known: dict[tuple, tuple[np.ndarray, np.ndarray]] = {}
        self.jobs = 0

    def sums(self, worker_id: int, iteration: int, n: int, batch_rows: int) -> tuple[np.ndarray, np.ndarray]:
        self.at[worker_id] = iteration, n, batch_rows
        if (worker_id, iteration, n, batch_rows) not in self.known:
            self._read(n, batch_rows)
        return self.known[worker_id, iteration, n, batch_rows]

    def _read(self, n: int, batch_rows: int) -> None:
        """Sums of all workers' next iterations, of the sizes that they have; one that has not begun is taken to have this one."""
        size = 8 * (n // batch_rows + 1) * len(self.w_init) * (len(self.w_init) + 1)
        ahead = max(1, min(self.AHEAD, HELD_BYTES // 2 // (size * len(self.at))))
        wanted = []
        for w, (i, n_w, b_w) in self.at.items():
            now = (n_w, b_w) if n_w else (n, batch_rows)
            wanted += [k for k in ((w, j, *now) for j in range(i, i + ahead)) if k not in self.known]
        total = sum(g.nbytes + b.nbytes for g, b in self.known.values()) + size * len(wanted)
        for k in sorted(self.known, key=lambda k: k[1] - self.at[k[0]][0]):  # the longest done first
            if total <= HELD_BYTES or k[1] >= self.at[k[0]][0] and k[2:] == self.at[k[0]][1:]:
                break
            total -= sum(a.nbytes for a in self.known.pop(k))
        self.known |= self.windows(wanted)
        self.jobs += 1

    def windows(self, wanted: list[tuple[int, int, int, int]]) -> dict[tuple, tuple[np.ndarray, np.ndarray]]:
        """Mini-batches' sums of iterations (worker, iteration, rows, mini-batch), by one job."""
        places, takes = [], []
        for k, (w, i, n, batch_rows) in enumerate(wanted):
            skip, slots = reached(self.begins, first_place(w, i, self.seed, self.rows), n)
            takes.append((skip, n, batch_rows))
            places += [(slot, k, turn) for slot, turn in slots]
        features, target, d = self.features, self.target, len(self.w_init)

        def summed(table: pa.Table) -> pa.Table:
            t = table.sort_by([(c, "ascending") for c in ("_window", "_turn", "_h", "key", *features)])
            of, x, y = t.column("_window").to_numpy(), np.stack([np.ones(t.num_rows), *(t.column(c).to_numpy() for c in features)], axis=1), t.column(target).to_numpy()
            ids, out = np.unique(of), []
            for k, start in zip(ids, np.searchsorted(of, ids), strict=True):
                skip, n, batch_rows = takes[k]
                g, b = batch_sums(x[start + skip : start + skip + n], y[start + skip : start + skip + n], batch_rows)
                out.append(g.tobytes() + b.tobytes())
            return pa.table({"_window": pa.array(ids, pa.int32()), "sums": pa.array(out, pa.binary())})

        spark = self.train.sparkSession
        at = spark.createDataFrame(pa.table({c: pa.array(v, pa.int32()) for c, v in zip(("_slot", "_window", "_turn"), zip(*places, strict=True), strict=True)}))
        few = max(1, self.GROUP_ROWS // max(n for _, n, _ in takes))
        parts = max(1, min(spark.sparkContext.defaultParallelism, len(takes) // few))
        rows = self.train.join(F.broadcast(at), "_slot").drop("_slot").withColumn("_group", F.floor(F.col("_window") / few)).repartition(parts, "_group")  # a few slots a window
        got = rows.groupBy("_group").applyInArrow(summed, "_window int, sums binary").toArrow()
        out = {}
        for k, raw in zip(got.column("_window").to_pylist(), got.column("sums").to_pylist(), strict=True):
            flat = np.frombuffer(raw)
            steps = len(flat) // (d * (d + 1))
            out[wanted[k]] = flat[: steps * d * d].reshape(steps, d, d), flat[steps * d * d :].reshape(steps, d)
        return out


# ---- models ------------------------------------------------------------------------------------------------------


class LeastSquares:
    """Least squares with a constant; its score is the share of variance explained."""

    target = np.float64

    def __init__(self, d: int):
        self.d, self.size = d, d + 1

    def init(self, seed: int) -> np.ndarray:
        return np.zeros(self.size)

    def gradient(self, p: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        off = x @ p[1:] + p[0] - y
        return np.concatenate(([off.mean()], x.T @ off / len(y)))

    def sums(self, p: np.ndarray, x: np.ndarray, y: np.ndarray) -> tuple[float, float, float]:
        """Sums of losses, and what the score is made of: of squared targets and of targets."""
        off = x @ p[1:] + p[0] - y
        return float(off @ off) / 2, float(y @ y), float(y.sum())

    @staticmethod
    def score(n: float, loss: float, a: float, b: float) -> float:
        total = a / n - (b / n) ** 2
        return 1 - 2 * loss / n / total if total > 0 else 0.0


class _Classes:
    """What classifiers share: labels are whole numbers, the score is the accuracy."""

    target = np.int64

    def sums(self, p: np.ndarray, x: np.ndarray, y: np.ndarray) -> tuple[float, float, float]:
        """Sums of losses, and what the score is made of: right answers."""
        q = self.probabilities(p, x)
        return float(-np.log(np.maximum(q[np.arange(len(y)), y], 1e-12)).sum()), float((q.argmax(1) == y).sum()), 0.0

    @staticmethod
    def score(n: float, loss: float, a: float, b: float) -> float:
        return a / n


class Softmax(_Classes):
    """Softmax regression."""

    def __init__(self, d: int, k: int):
        self.d, self.k = d, k
        self.size = (d + 1) * k

    def init(self, seed: int) -> np.ndarray:
        return np.zeros(self.size)

    def probabilities(self, p: np.ndarray, x: np.ndarray) -> np.ndarray:
        w = p.reshape(self.d + 1, self.k)
        q = w[:-1].T @ x.T + w[-1][:, None]  # classes first, as in gradients()
        q -= q.max(0)
        np.exp(q, out=q)
        q /= q.sum(0)
        return q.T

    def gradient(self, p: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        q = self.probabilities(p, x)
        q[np.arange(len(y)), y] -= 1
        q /= len(y)
        return np.concatenate((x.T @ q, q.sum(0)[None, :])).ravel()

    def batches(self, x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Mini-batches of several models as gradients() takes them: rows with a constant, the same by columns, and ones where a class is a
        row's label."""
        rows = np.concatenate((x, np.ones((*y.shape, 1))), axis=2)
        return rows, np.ascontiguousarray(rows.transpose(0, 2, 1)), (np.arange(self.k)[:, None, None] == y).astype(np.float64)

    def gradients(self, p: np.ndarray, rows: np.ndarray, columns: np.ndarray, right: np.ndarray) -> np.ndarray:
        """gradient() of several models, each on a mini-batch of its own from batches(). Classes come first: numpy sums few long rows
        sooner than many short ones."""
        q = np.empty_like(right)
        np.matmul(p.reshape(len(p), self.d + 1, self.k).transpose(0, 2, 1), columns, out=q.transpose(1, 0, 2))
        q -= q.max(0)
        np.exp(q, out=q)
        q /= q.sum(0)
        q -= right
        q /= rows.shape[1]
        return (rows.transpose(0, 2, 1) @ q.transpose(1, 2, 0)).reshape(p.shape)


class Mlp(_Classes):
    """One hidden layer of rectified units."""

    def __init__(self, d: int, k: int, hidden: int = 32):
        self.d, self.k, self.hidden = d, k, hidden
        self.size = (d + 1) * hidden + (hidden + 1) * k

    def init(self, seed: int) -> np.ndarray:
        r = np.random.default_rng(seed)
        a = np.concatenate((r.normal(0, (2 / self.d) ** 0.5, (self.d, self.hidden)), np.zeros((1, self.hidden))))
        b = np.concatenate((r.normal(0, (1 / self.hidden) ** 0.5, (self.hidden, self.k)), np.zeros((1, self.k))))
        return np.concatenate((a.ravel(), b.ravel()))

    def _parts(self, p):
        cut = (self.d + 1) * self.hidden
        return p[:cut].reshape(self.d + 1, self.hidden), p[cut:].reshape(self.hidden + 1, self.k)

    def probabilities(self, p, x):
        a, b = self._parts(p)
        return _softmax(np.maximum(x @ a[:-1] + a[-1], 0) @ b[:-1] + b[-1])

    def gradient(self, p, x, y):
        a, b = self._parts(p)
        h = np.maximum(x @ a[:-1] + a[-1], 0)
        q = _softmax(h @ b[:-1] + b[-1])
        q[np.arange(len(y)), y] -= 1
        q /= len(y)
        back = (q @ b[:-1].T) * (h > 0)
        return np.concatenate([np.concatenate((x.T @ back, back.sum(0)[None])).ravel(), np.concatenate((h.T @ q, q.sum(0)[None])).ravel()])


class Cnn(_Classes):
    """Convolutions of 3x3 with rectified units, means of 2x2, and a dense layer; more than one stage makes it deep."""

    def __init__(self, side: int = 8, k: int = 10, filters: tuple[int, ...] = (8,), hidden: int = 0):
        self.side, self.k, self.filters, self.hidden = side, k, filters, hidden
        self.shapes, channels, s = [], 1, side
        for f in filters:
            self.shapes.append((9 * channels + 1, f))
            channels, s = f, s // 2
        flat = s * s * channels
        if hidden:
            self.shapes.append((flat + 1, hidden))
            flat = hidden
        self.shapes.append((flat + 1, k))
        self.size = sum(a * b for a, b in self.shapes)

    def init(self, seed: int) -> np.ndarray:
        r = np.random.default_rng(seed)
        return np.concatenate([np.concatenate((r.normal(0, (2 / a) ** 0.5, (a - 1, b)), np.zeros((1, b)))).ravel() for a, b in self.shapes])

    def _parts(self, p):
        out, at = [], 0
        for a, b in self.shapes:
            out.append(p[at : at + a * b].reshape(a, b))
            at += a * b
        return out

    @staticmethod
    def _patches(x: np.ndarray) -> np.ndarray:
        """A row a place: its 3x3 neighbours."""
        n, s, _, c = x.shape
        padded = np.zeros((n, s + 2, s + 2, c), x.dtype)
        padded[:, 1:-1, 1:-1] = x
        return np.concatenate([padded[:, i : i + s, j : j + s] for i in range(3) for j in range(3)], axis=3).reshape(n * s * s, 9 * c)

    def _forward(self, p, x):
        parts, kept = self._parts(p), []
        n, h = len(x), x.reshape(len(x), self.side, self.side, 1)
        for w in parts[: len(self.filters)]:
            s, f = h.shape[1], w.shape[1]
            cols = self._patches(h)
            out = cols @ w[:-1]
            out += w[-1]
            np.maximum(out, 0, out=out)
            at = out.reshape(n, s // 2, 2, s // 2, 2, f)
            kept.append((cols, at > 0, h.shape))
            h = (at[:, :, 0, :, 0] + at[:, :, 0, :, 1] + at[:, :, 1, :, 0] + at[:, :, 1, :, 1]) / 4
        flat, shape = h.reshape(n, -1), h.shape
        dense = [flat]
        for w in parts[len(self.filters) : -1]:
            dense.append(np.maximum(dense[-1] @ w[:-1] + w[-1], 0))
        return parts, kept, dense, shape, _softmax(dense[-1] @ parts[-1][:-1] + parts[-1][-1])

    def probabilities(self, p, x):
        """By some rows at a time, whose places' neighbours a cache holds."""
        return np.concatenate([self._forward(p, x[a : a + 128])[-1] for a in range(0, max(1, len(x)), 128)])

    def gradient(self, p, x, y):
        parts, kept, dense, shape, q = self._forward(p, x)
        q[np.arange(len(y)), y] -= 1
        back = q / len(y)
        grads = []
        for k, h in enumerate(reversed(dense)):
            w = parts[len(parts) - 1 - k]
            grads.append(np.concatenate((h.T @ back, back.sum(0)[None])))
            back = back @ w[:-1].T
            if k < len(dense) - 1:
                back = back * (h > 0)
        back = back.reshape(shape)
        for k in range(len(self.filters) - 1, -1, -1):
            cols, alive, before = kept[k]
            up = ((back / 4)[:, :, None, :, None, :] * alive).reshape(len(cols), -1)
            grads.append(np.concatenate((cols.T @ up, up.sum(0)[None])))
            if k:
                n, s, _, c = before
                wide = (up @ parts[k][:-1].T).reshape(n, s, s, 9 * c)
                spread = np.zeros((n, s + 2, s + 2, c))
                for at in range(9):
                    i, j = divmod(at, 3)
                    spread[:, i : i + s, j : j + s] += wide[..., at * c : (at + 1) * c]
                back = spread[:, 1:-1, 1:-1]
        return np.concatenate([g.ravel() for g in reversed(grads)])


#: the published models' sizes, 110,033 and 989,756 parameters, reached by width
CNN_110K = Cnn(8, 10, (16, 32), 757)
CNN_990K = Cnn(8, 10, (64, 128), 1750)


def _softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(1, keepdims=True))
    return e / e.sum(1, keepdims=True)


def mean_loss(model, p: np.ndarray, x: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Mean loss and score."""
    loss, a, b = model.sums(p, x, y)
    return loss / len(y), float(model.score(len(y), loss, a, b))


def _matrix(table, model) -> tuple[np.ndarray, np.ndarray]:
    x = table.column("features")
    x = x.combine_chunks() if isinstance(x, pa.ChunkedArray) else x
    return x.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(table.num_rows, -1), table.column("label").to_numpy(zero_copy_only=False).astype(model.target)


class HeldLearner:
    """A model on rows that the driver holds, as RowLearner does for least squares: an iteration of a worker takes neighbouring rows
    of an order by bucket and hash, IID from a place that worker and iteration give; with `skew`, labels have buckets of their own and a worker
    begins in its own part of them, a little further at each iteration. Losses are those of the whole test split. Segments that run at
    once are trained by a task each, to which the rows are broadcast, where that takes longer than a job; a model whose steps take less
    time than a call of numpy takes the steps of all of them at once, in one task. Runs may do so side by side."""

    side_by_side = True  # no state is left from one run's segments to another's
    TASK_S = 0.1  # of a turn: seconds from which a job is worth it

    def __init__(self, rows: DataFrame, model, workers: int = 12, seed: int = 42, skew: str | None = None):
        tagged, order = self._ordered(rows, model, workers, seed, skew)
        self.x, self.y = self._held(tagged, [(c, "ascending") for c in order])
        self.tx, self.ty = self._held(rows.where("split = 'test'").select("key", "features", "label"), [("key", "ascending")])
        self.w_init, self.rows, self.row_bytes = model.init(seed), len(self.y), 4 * self.x.shape[1]
        self.step_s = 1e-4 + 1e-8 * model.size  # about what a mini-batch takes
        self.abreast = hasattr(model, "gradients")
        self.shared = None
        self.sharing = threading.Lock()

    def _ordered(self, rows: DataFrame, model, workers: int, seed: int, skew: str | None) -> tuple[DataFrame, list[str]]:
        """Training rows, and the columns that they are in order of."""
        from tidegate.functions.scalar import arithmetic_hash

        self.spark, self.model, self.seed, self.workers, self.skewed = rows.sparkSession, model, seed, workers, skew is not None
        tagged = sizing.with_buckets(rows.where("split = 'train'"), F.col("key"), BUCKETS, seed, None if skew is None else F.col(skew))
        order = ["bucket"] * self.skewed + ["_h", "key", "_same"]
        return tagged.select("bucket", arithmetic_hash(F.col("key") * 13 + seed).alias("_h"), "key", F.xxhash64("features", "label").alias("_same"), "features", "label"), order

    def __getstate__(self) -> dict:
        """What tasks need."""
        return self.__dict__ | {"spark": None, "shared": None, "sharing": None}

    def _held(self, df: DataFrame, order: list) -> tuple[np.ndarray, np.ndarray]:
        table = df.toArrow().sort_by(order)
        return _matrix(table, self.model) if table.num_rows else (np.zeros((0, 1)), np.zeros(0, self.model.target))

    def first(self, worker_id: int, iteration: int, n: int) -> int:
        if not self.skewed:
            return first_place(worker_id, iteration, self.seed, self.rows)
        return (worker_id * self.rows // self.workers + iteration * (n // 3 + 1)) % self.rows

    def places(self, worker_id: int, iteration: int, n: int) -> np.ndarray:
        at = (self.first(worker_id, iteration, n) + np.arange(n)) % self.rows
        return np.random.default_rng((self.seed, worker_id, iteration)).permutation(at) if self.skewed else at

    def steps(self, worker_id: int):
        def run(iteration, n_rows, batch_rows):
            n = min(n_rows, self.rows)
            at = self.places(worker_id, iteration, n)
            for a in range(0, n, batch_rows):
                part = at[a : a + batch_rows]
                yield len(part), lambda p, part=part: self.model.gradient(p, self.x[part], self.y[part])

        return run

    def trained(self, s: Segment) -> Segment:
        np.empty(31 << 17)  # once the C library has freed 31 MB it keeps freed pages, else each vector of a model's length asks for new ones
        return run_segment(s, self.w_init, self.steps(s.worker_id), lambda p: self.evaluate(p)[0])

    def together(self, segments: list[Segment]) -> list[Segment]:
        """The segments, trained here: abreast those of one size, where the model can."""
        if not self.abreast:
            return [self.trained(s) for s in segments]
        sizes: dict[tuple, list[Segment]] = {}
        for s in segments:
            sizes.setdefault((s.n_rows, s.batch_rows, s.epochs, s.lr, s.momentum, s.precision), []).append(s)
        for (n, *_), of in sizes.items():
            run_abreast(of, self.w_init, lambda s, n=min(n, self.rows): self.places(s.worker_id, s.iteration, n), self.model, self.x, self.y, lambda p: self.evaluate(p)[0])
        return segments

    def run(self, segments: list[Segment]) -> list[Segment]:
        if self.spark is None or self.step_s * sum(s.epochs * min(s.n_rows, self.rows) / s.batch_rows for s in segments) < self.TASK_S:
            return self.together(segments)
        shared = self.share()

        def train(part: list[Segment]) -> list[Segment]:
            for done in (out := shared.value.together(part)):
                if done.fired or not done.momentum:  # nobody asks for it, and it is as long as the model
                    done.velocity = None
            return out

        parts = [segments] if self.abreast else [[s] for s in segments]
        return [s for part in self.spark.sparkContext.parallelize(parts, len(parts)).map(train).collect() for s in part]  # a segment a worker

    def share(self):
        """The learner as tasks have it."""
        with self.sharing:
            self.shared = self.shared or self.spark.sparkContext.broadcast(self)
        return self.shared

    def evaluate(self, params: np.ndarray) -> tuple[float, float]:
        return mean_loss(self.model, params, self.tx, self.ty)

    def close(self) -> None:
        if self.shared:
            self.shared.unpersist()


class StoredLearner(HeldLearner):
    """HeldLearner for any number of rows, with its order, places, mini-batches, whole test split and results. Training rows are written
    once to the shared folder, in their order; the driver holds how many each of SLOTS ranges of it has (as WindowLearner does), which tells the
    ranges that an iteration's rows lie in. A job reads these alone and trains a task a worker, another takes the losses, over the whole test
    split. As only a loss says that a segment ends, iterations are trained ahead: one, then twice as many each time, and those after the end
    are dropped. What a task reads, and what the driver gets at once, stays under AHEAD_BYTES, or is one iteration."""

    SLOTS, SLOT_ROWS, AHEAD_BYTES, RANGES = 1 << 16, 256, 64 << 20, 64

    def __init__(self, rows: DataFrame, model, workers: int = 12, seed: int = 42, skew: str | None = None):
        tagged, self.order = self._ordered(rows, model, workers, seed, skew)
        path = f"{shared_dir(self.spark)}/stored-{uuid.uuid4().hex}"
        tagged.repartitionByRange(*self.order).sortWithinPartitions(*self.order).write.parquet(f"{path}/train")
        rows.where("split = 'test'").select("features", "label").write.parquet(f"{path}/test")
        read = lambda name: self.spark.read.schema(tagged.schema).parquet(f"{path}/{name}")
        self.train, self.test = read("train"), read("test").select("features", "label").persist()
        span = BUCKETS if self.skewed else 1 << 32
        slot = lambda n: F.floor(F.col(self.order[0]) / (span // n)).cast("int")
        self.begins = slotted(self.train, slot, self.SLOTS, self.SLOT_ROWS)
        self.slots = len(self.begins) - 1
        self.slot, self.width = slot(self.slots).alias("_slot"), span // self.slots
        one = rows.select(F.size("features").alias("d")).first()
        self.w_init, self.rows, self.row_bytes = model.init(seed), int(self.begins[-1]), 4 * (one["d"] if one else 1)
        self.abreast, self.shared = False, None

    def run(self, segments: list[Segment]) -> list[Segment]:
        states = {s.worker_id: GateState(s.gate[0], *s.gate[1:]) if s.gate else None for s in segments}
        ends = {s.worker_id: s.iteration + s.length for s in segments}
        live, ahead = segments, 1
        while live:
            at_once = max(max(len(live) * len(self.w_init), 2 * min(s.n_rows, self.rows) * self.row_bytes // 8) * 8 for s in live)
            ahead = max(1, min(ahead, self.AHEAD_BYTES // at_once))
            paths = self.paths(live, {s.worker_id: min(ahead, ends[s.worker_id] - s.iteration) for s in live})
            losses = iter(self.losses([self.w_init - s.lr * acc for s in live for acc in paths[s.worker_id][0]]))
            for s in live:
                accs, velocity = paths[s.worker_id]
                for acc, (loss, _) in zip(accs, [next(losses) for _ in accs], strict=True):
                    if not s.fired:
                        before, s.acc = s.acc, acc
                        looked(s, states[s.worker_id], before, acc, s.epochs * min(s.n_rows, self.rows), loss)
                s.velocity = None if s.fired else velocity
            live = [s for s in live if not s.fired and s.iteration < ends[s.worker_id]]
            ahead *= 2
        return segments

    def paths(self, segments: list[Segment], ahead: dict[int, int]) -> dict[int, tuple[np.ndarray, np.ndarray | None]]:
        """Where each of a worker's next iterations leads, and the velocity after them, by one job."""
        model, w_init, seed, order, skewed = self.model, self.w_init, self.seed, self.order, self.skewed
        places, skips = [], {}
        for s in segments:
            n = min(s.n_rows, self.rows)
            for i in range(s.iteration, s.iteration + ahead[s.worker_id]):
                skips[s.worker_id, i], slots = reached(self.begins, self.first(s.worker_id, i, n), n)
                places += [(slot, s.worker_id, i, turn) for slot, turn in slots]
        tasks = self.spark.sparkContext.broadcast(({s.worker_id: replace(s, losses=[], zs=[], trained=[], queue=[]) for s in segments}, ahead, skips, self.rows))

        def train(key, table):
            of, ahead, skips, rows = tasks.value
            s = of[key[0].as_py()]
            n = min(s.n_rows, rows)
            t = table.sort_by([(c, "ascending") for c in ("_iteration", "_turn", *order)])
            iterations, (x, y) = t.column("_iteration").to_numpy(), _matrix(t, model)
            acc, velocity, out = s.acc, np.zeros_like(s.acc) if s.velocity is None else s.velocity, []
            for i in range(s.iteration, s.iteration + ahead[s.worker_id]):
                at = int(np.searchsorted(iterations, i)) + skips[s.worker_id, i] + np.arange(n)
                at = np.random.default_rng((seed, s.worker_id, i)).permutation(at) if skewed else at
                parts = [at[a : a + s.batch_rows] for a in range(0, n, s.batch_rows)]
                acc, velocity, _ = iterated(s, acc, velocity, w_init, [(len(part), lambda p, part=part: model.gradient(p, x[part], y[part])) for part in parts])
                out.append(acc)
            return pa.table({"worker_id": pa.array([s.worker_id], pa.int32()), "accs": pa.array([np.stack(out).tobytes()], pa.binary()), "velocity": pa.array([velocity.tobytes() if s.momentum else None], pa.binary())})

        at = self.spark.createDataFrame(pa.table({c: pa.array(v, pa.int32()) for c, v in zip(("_slot", "_worker", "_iteration", "_turn"), zip(*places, strict=True), strict=True)}))
        rows = self.train.where(self.within({slot for slot, *_ in places})).select(*order, "features", "label", self.slot)
        rows = rows.join(F.broadcast(at), "_slot").drop("_slot").repartition(len(segments), "_worker")  # a few slots an iteration
        got = rows.groupBy("_worker").applyInArrow(train, "worker_id int, accs binary, velocity binary").collect()  # a row a worker
        tasks.destroy()
        return {r["worker_id"]: (np.frombuffer(r["accs"]).reshape(-1, len(w_init)), None if r["velocity"] is None else np.frombuffer(r["velocity"])) for r in got}

    def within(self, slots: set[int]):
        """A condition that all rows of these slots meet, which the Parquet reader takes: at most RANGES ranges, cut at the widest gaps."""
        at = np.array(sorted(slots))
        gaps = np.diff(at)
        cuts = np.sort(np.argsort(-gaps, kind="stable")[: self.RANGES - 1])
        cuts = cuts[gaps[cuts] > 1]
        lead = F.col(self.order[0])
        ranges = [(lead >= int(part[0]) * self.width) & (lead < (int(part[-1]) + 1) * self.width) for part in np.split(at, cuts + 1)]
        while len(ranges) > 1:  # a flat tree
            ranges = [a | b for a, b in zip(ranges[::2], ranges[1::2])] + ranges[len(ranges) // 2 * 2 :]  # noqa: B905
        return ranges[0]

    def losses(self, points: list[np.ndarray]) -> list[tuple[float, float]]:
        """Loss and score of several models over the whole test split, by one job."""
        model, shared = self.model, self.spark.sparkContext.broadcast(np.stack(points))

        def part(batches):
            total = np.zeros((len(shared.value), 4))
            for b in batches:
                x, y = _matrix(b, model) if b.num_rows else (None, ())
                for k, p in enumerate(shared.value if len(y) else ()):
                    total[k] += (len(y), *model.sums(p, x, y))
            yield pa.RecordBatch.from_arrays([pa.array(range(len(total)), pa.int32()), *(pa.array(c) for c in total.T)], names=["k", "n", "loss", "a", "b"])

        sums = self.test.mapInArrow(part, "k int, n double, loss double, a double, b double")
        got = {r["k"]: r for r in sums.groupBy("k").agg(*[F.sum(c).alias(c) for c in ("n", "loss", "a", "b")]).collect()}  # a row a model
        shared.destroy()
        return [(r["loss"] / r["n"], float(model.score(r["n"], r["loss"], r["a"], r["b"]))) if r and r["n"] else (float("nan"), float("nan")) for r in map(got.get, range(len(points)))]

    def evaluate(self, params: np.ndarray) -> tuple[float, float]:
        return self.losses([params])[0]

    def close(self) -> None:
        self.test.unpersist()


class SparkLearner:
    """A model trained in Spark tasks on rows that are dealt to the workers anew at each refresh.

    Training rows are written once to the shared folder, in `buckets` by a hash of key (with `skew`, labels have buckets of their own). At a
    worker's turn, which is the number of its refreshes, deal_rows() gives all workers their allotted rows from other buckets
    than before, and only those buckets are read. While a turn trains, the next one is fetched (Prefetcher). A size that differs
    from the dealt one is dealt anew. Workers that together ask for more rows than there are get their shares of what there is, and
    segments say so. The held-out probe that workers and server evaluate on is a bounded sample of the test split (least hashes of
    key); evaluate_all() goes over the whole of it.
    """

    def __init__(self, rows: DataFrame, model, workers: int = 12, seed: int = 42, probe_rows: int = 2000, skew: str | None = None, buckets: int | None = None, prefetch: bool = True):
        self.spark, self.model, self.seed = rows.sparkSession, model, seed
        self.buckets = buckets or max(64, 8 * workers)
        train = sizing.with_buckets(rows.where("split = 'train'"), F.col("key"), self.buckets, seed, None if skew is None else F.col(skew)).select("bucket", "key", "features", "label")
        self.path = f"{shared_dir(self.spark)}/train-{uuid.uuid4().hex}"
        train.repartition("bucket").write.partitionBy("bucket").parquet(self.path)
        self.table = self.spark.read.schema("key long, features array<float>, label " + train.schema["label"].dataType.simpleString() + ", bucket long").parquet(self.path)
        counted = self.table.groupBy("bucket").count().collect()  # at most `buckets` rows
        self.rows = sum(r["count"] for r in counted)
        self.counts = self.spark.createDataFrame([(r["bucket"], r["count"]) for r in counted], "bucket long, _rows long")
        self.test = rows.where("split = 'test'")
        probe = self.test.orderBy(F.xxhash64("key"), "key").limit(probe_rows).select("features", "label").toArrow()
        self.x, self.y = _matrix(probe, model) if probe.num_rows else (np.zeros((0, 1)), np.zeros(0, model.target))
        self.probe = self.spark.sparkContext.broadcast((self.x, self.y))
        self.w_init = model.init(seed)
        self.row_bytes = 4 * (self.x.shape[1] if len(self.y) else 1)
        self.jobs = 0
        self.sizes: dict[int, tuple[int, int]] = {}
        self.turns: dict[int, int] = {}
        self.deals: dict[int, tuple[dict, DataFrame]] = {}  # by turn: sizes and dealt rows
        self.ahead = Prefetcher(self.spark) if prefetch else None
        self.coming: tuple[int, dict] | None = None

    def dealt(self, turn: int) -> DataFrame:
        """The rows of a turn by worker: worker_id, pos, batch_no, key, features, label."""
        alloc = self.spark.createDataFrame([(w, n, b) for w, (n, b) in sorted(self.sizes.items())], "worker_id int, n_rows long, batch_rows int")
        return sizing.deal_rows(self.table, F.col("key"), alloc, turn, self.seed, buckets=self.buckets, counts=self.counts)

    def turn(self, turn: int) -> DataFrame:
        """The cached deal of a turn, with the sizes as they are now."""
        if turn in self.deals and self.deals[turn][0] != self.sizes:
            self.deals.pop(turn)[1].unpersist()
        if turn not in self.deals:
            got = None
            if self.coming:
                (at, sizes), self.coming = self.coming, None
                got = self.ahead.take()
                if at != turn or sizes != self.sizes:
                    if sizes == self.sizes and at not in self.deals:
                        self.deals[at] = sizes, got
                    else:
                        got.unpersist()
                    got = None
            if turn not in self.deals:
                self.deals[turn] = dict(self.sizes), got if got is not None else self.dealt(turn).persist()
        return self.deals[turn][1]

    def run(self, segments: list[Segment]) -> list[Segment]:
        model, seed, w_init, probe = self.model, self.seed, self.w_init, self.probe
        for s in segments:
            if not s.iteration:  # a run starts over
                self.turns[s.worker_id] = 0
            self.sizes[s.worker_id] = (s.n_rows, s.batch_rows)
        tasks = self.spark.sparkContext.broadcast({s.worker_id: s for s in segments})

        def train(key, table):
            s = tasks.value[key[0].as_py()]
            x, y = _matrix(table, model)
            px, py = probe.value

            def steps(iteration, n_rows, batch_rows):
                order = np.random.default_rng((seed, s.worker_id, iteration)).permutation(len(y))[:n_rows]
                for a in range(0, len(order), batch_rows):
                    part = order[a : a + batch_rows]
                    yield len(part), lambda p, part=part: model.gradient(p, x[part], y[part])

            done = run_segment(s, w_init, steps, lambda p: mean_loss(model, p, px, py)[0])
            return pa.table({"worker_id": pa.array([s.worker_id], pa.int32()), "state": pa.array([pickle.dumps(done)], pa.binary())})

        wanted = None
        for turn in sorted({self.turns[s.worker_id] for s in segments}):
            mine = [s.worker_id for s in segments if self.turns[s.worker_id] == turn]
            part = self.turn(turn).where(F.col("worker_id").isin(mine)).select("worker_id", "features", "label")
            wanted = part if wanted is None else wanted.unionByName(part)
        latest = max(self.turns.values()) + 1
        if self.ahead and not self.coming and latest not in self.deals:
            self.coming = latest, dict(self.sizes)
            self.ahead.submit(self.dealt(latest))
        got = {r["worker_id"]: pickle.loads(r["state"]) for r in wanted.groupBy("worker_id").applyInArrow(train, "worker_id int, state binary").collect()}
        tasks.unpersist()
        self.jobs += 1
        out = []
        for s in segments:
            if s.worker_id in got:
                out.append(got[s.worker_id])
            else:  # a worker without rows learns nothing
                s.iteration, s.fired = s.iteration + 1, True
                s.losses.append(mean_loss(model, w_init - s.lr * s.acc, self.x, self.y)[0])
                s.zs.append(None)
                s.trained.append(0)
                out.append(s)
            if out[-1].fired:
                self.turns[s.worker_id] += 1
        for old in [t for t in self.deals if t < min(self.turns.values())]:
            self.deals.pop(old)[1].unpersist()
        return out

    def evaluate(self, params: np.ndarray) -> tuple[float, float]:
        return mean_loss(self.model, params, self.x, self.y)

    def evaluate_all(self, params: np.ndarray) -> tuple[float, float]:
        return evaluate(self.model, params, self.test)

    def close(self) -> None:
        if self.ahead:
            self.ahead.close()
        for _, df in self.deals.values():
            df.unpersist()
        self.deals.clear()


def evaluate(model, params: np.ndarray, df: DataFrame) -> tuple[float, float]:
    """Mean loss and score over all rows: parameters broadcast, a row of sums a partition."""
    row = evaluation(model, params, df).first()
    return (row["loss"], row["accuracy"]) if row["n"] else (float("nan"), float("nan"))


def evaluation(model, params: np.ndarray, df: DataFrame, by: str | None = None) -> DataFrame:
    """One row: n, loss and accuracy; with `by`, a whole number or a string, a row for each of its values."""
    shared = df.sparkSession.sparkContext.broadcast(params)

    def part(batches):
        for b in batches:
            if not b.num_rows:
                continue
            x, y = _matrix(b, model)
            groups = b.column("by").to_pylist()
            for group in set(groups):
                at = np.array([g == group for g in groups])
                loss, s, t = model.sums(shared.value, x[at], y[at])
                yield pa.RecordBatch.from_arrays([b.column("by").filter(pa.array(at)).slice(0, 1), *(pa.array([float(v)]) for v in (at.sum(), loss, s, t))], names=["by", "n", "loss", "s", "t"])

    kind = df.schema[by].dataType.simpleString() if by else "int"
    tagged = df.select("features", "label", (F.col(by) if by else F.lit(0)).alias("by"))
    sums = tagged.mapInArrow(part, f"by {kind}, n double, loss double, s double, t double")
    sums = sums.groupBy("by") if by else sums.groupBy()
    sums = sums.agg(*[F.coalesce(F.sum(c), F.lit(0.0)).alias(c) for c in ("n", "loss", "s", "t")])
    if isinstance(model, LeastSquares):
        total = F.try_divide("s", "n") - F.try_divide("t", "n") ** 2
        score = 1 - F.try_divide(2 * F.try_divide("loss", "n"), total)
    else:
        score = F.try_divide("s", "n")
    return sums.select(*([F.col("by").alias(by)] if by else []), F.col("n").cast("long").alias("n"), F.try_divide("loss", "n").alias("loss"), score.alias("accuracy"))


def segment_gate(p: GateParams) -> tuple:
    return (p, p.z_cut, 0, 0)
