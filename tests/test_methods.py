"""The methods' hand examples, invariants and identities."""

import math
from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from tidegate.functions.scalar import normal_tail, z_for_tail
from tidegate.operators import gate, merge, sizing
from tidegate.operators.compress import from_half, to_half
from tidegate.operators.gate import GateParams, GateState
from tidegate.plans import experiments as x
from tidegate.plans.learners import Cnn, Mlp, Segment, Softmax, mean_loss, run_segment
from tidegate.plans.trainer import Policy, converged, elastic_counts, train
from tidegate.sources import tables

HAND = [1.0, 1.2, 0.8, 1.0, 0.9, 0.7, 0.9, 0.8, 0.9, 0.78, 0.4]
HAND_CUTS = [-1.3, -1.3, -1.17, -1.053, -0.9477, -0.85293, -0.85293, -0.85293, -0.767637, -0.690873, -0.690873]
HAND_QUIET = [1, 2, 3, 4, 5, 0, 1, 2, 3, 0, 0]
P3 = GateParams(history=3, quiet_limit=2)


def series(spark, losses, worker=1):
    return spark.createDataFrame([(worker, i + 1, i + 1, i + 1, v) for i, v in enumerate(losses)], "worker_id int, iter long, ts long, event_id long, loss double")


def test_gate_hand_example(spark):
    rows = gate.gate_adaptive_arrow(series(spark, HAND).orderBy(F.rand(1)), P3).orderBy("iter").collect()
    assert [r["iter"] for r in rows if r["push"]] == [6, 10, 11]
    assert [r["quiet_run"] for r in rows] == HAND_QUIET
    assert np.allclose([r["z_cut"] for r in rows], HAND_CUTS, atol=1e-6)
    assert rows[0]["z"] is None and abs(rows[5]["z"] + 2.44949) < 1e-5
    state = gate.gate_adaptive(series(spark, HAND), P3).first()
    assert (state["iterations"], state["pushes"], state["quiet_run"]) == (11, 3, 0) and abs(state["z_cut"] + 0.690873) < 1e-6


def test_gate_one_by_one():
    s, queue, pushed = GateState(P3), [], []
    for i, v in enumerate(HAND, 1):
        if s.observe(queue, v)[0]:
            pushed.append(i)
    assert pushed == [6, 10, 11] and len(queue) == 3


def test_gate_edges(spark):
    p = GateParams(history=3)
    constant = gate.gate_fixed(series(spark, [1.0] * 8), p)
    assert constant.where("push").count() == 0
    lower = gate.gate_fixed(series(spark, [1.0] * 5 + [0.5]), p).where("push").collect()
    assert [r["iter"] for r in lower] == [6]
    assert gate.gate_fixed(series(spark, [1.0, 0.5]), p).where("push").count() == 0
    gone = gate.rolling_stats(series(spark, [1.0, None, 0.9, 0.8, 0.7]), p)
    assert gone.count() == 4
    both = series(spark, HAND, 1).union(series(spark, HAND, 2))
    counts = gate.gate_adaptive(both, P3).select("pushes").collect()
    assert [r[0] for r in counts] == [3, 3]


def test_gate_scale_and_nesting(spark):
    e = tables.loss_series(tables.load(spark, "/root/testdata/sf0.001", "events"))
    a = gate.rolling_stats(e).select("worker_id", "iter", "z")
    b = gate.rolling_stats(e.withColumn("loss", 3 * F.col("loss") + 2)).select("worker_id", "iter", F.col("z").alias("z2"))
    assert a.join(b, ["worker_id", "iter"]).where("abs(z - z2) > 1e-6").count() == 0
    sets = [{(r[0], r[1]) for r in a.where(F.col("z") <= c).collect()} for c in (-0.9, -1.3, -1.6)]
    assert sets[2] <= sets[1] <= sets[0]
    fixed = gate.gate_fixed(e).where("push").groupBy("worker_id").count().collect()
    still = gate.gate_adaptive(e, GateParams(quiet_limit=10**6)).collect()
    assert {r[0]: r[1] for r in fixed} == {r["worker_id"]: r["pushes"] for r in still if r["pushes"]}


def test_gate_bound_with_current(spark):
    z = gate.rolling_stats(tables.loss_series(tables.load(spark, "/root/testdata/sf0.01", "events")), GateParams(include_current=True)).agg(F.max(F.abs("z"))).first()[0]
    assert z <= 3 + 1e-9


def test_gate_params():
    with pytest.raises(ValueError):
        GateParams(z_cut=0.5).validate()
    with pytest.raises(ValueError):
        GateParams(quiet_limit=0).validate()
    with pytest.warns(UserWarning):
        GateParams(relax=0.5).validate()


def test_published_firings(spark):
    z = gate.rolling_stats(tables.loss_series(tables.load(spark, "/root/testdata/sf0.01", "events")))
    got = z.agg(F.count("z"), *[F.count_if(F.col("z") <= c) for c in (-0.9, -1.3, -1.6)]).first()
    assert tuple(got) == (9880, 2467, 888, 428)
    pushes = gate.gate_adaptive(tables.loss_series(tables.load(spark, "/root/testdata/sf0.01", "events"))).orderBy("worker_id").collect()
    assert [r["pushes"] for r in pushes] == [463, 473, 437, 476, 469, 530, 450, 433, 427, 442, 436, 404]


def test_tails(spark):
    zs = [-8.0, -5.0, -2.5, -1.6, -1.3, -0.9, 0.0, 0.7, 3.0]
    got = spark.createDataFrame([(z,) for z in zs], "z double").select("z", normal_tail(F.col("z")).alias("p")).withColumn("back", z_for_tail(F.col("p"))).collect()
    for r in got:
        want = 0.5 * math.erfc(-r["z"] / 2**0.5)
        assert abs(r["p"] - want) < 1e-9 * max(1, want / 1e-9) and (abs(r["z"]) > 6 or abs(r["back"] - r["z"]) < 1e-6)


def test_fleet_sizing(spark):
    obs = tables.timings(tables.fleet(spark), iters=1)
    b = sizing.iqr_bounds(obs, "t_train").first()
    assert (b["q1"], b["q3"], b["iqr"], b["lo"], b["hi"]) == (1.6796875, 2.1875, 0.5078125, 0.91796875, 2.94921875)
    caps = sizing.with_caps(tables.fleet(spark))
    out = {r["worker_id"]: r for r in sizing.reallocate(obs, caps, 60_000).collect()}
    assert [w for w, r in out.items() if r["status"] == "straggler"] and {w for w, r in out.items() if r["status"] != "normal"} == {0, 1}
    assert out[0]["n_rows"] == 677 and out[5]["n_rows"] == 2500
    every = {r["worker_id"]: r["n_rows"] for r in sizing.reallocate(obs, caps, 60_000, "all").collect()}
    assert (every[2], every[5], every[8], every[10]) == (2321, 3250, 2500, 2954)


def test_search_by_batch(spark):
    w = spark.createDataFrame([(2**e,) for e in range(1, 9)], "b int")
    n = sizing.search_rows(F.lit(2.03125), F.lit(0.048), F.lit(1), F.col("b"), F.lit(60_000))
    assert [r[0] for r in w.orderBy("b").select(n).collect()] == [84, 169, 338, 677, 1354, 2708, 5416, 10833]


def test_search_against_closed_form(spark):
    rows = spark.range(1000).select(F.col("id").cast("int").alias("worker_id"), (0.0005 * (1 + F.col("id") % 97)).alias("sec_per_batch"), F.lit(1.7).alias("t_target"), F.lit(16).alias("batch_rows"), (500 + 37 * F.col("id")).alias("cap_rows"))
    got = sizing.dual_search(rows, 10**6).collect()
    for r in got:
        k, cap = 0.0005 * (1 + r["worker_id"] % 97), 500 + 37 * r["worker_id"]
        fits = [n for n in (math.floor(1.7 * r["batch_rows"] / k) + d for d in (-1, 0, 1)) if k * (n / r["batch_rows"]) <= 1.7]
        assert r["n_rows"] == min(cap, max(1, max(fits)))
    brute = {r["worker_id"]: r["batch_rows"] for r in sizing.dual_search_brute(rows, 10**6).collect()}
    largest = {r["worker_id"]: r["batch_rows"] for r in sizing.dual_search(rows, 10**6, prefer="largest").collect()}
    assert brute == largest


def test_merge_hand_example():
    goal = np.array([1.0, 2.0])
    s = merge.ServerState(np.zeros(2), 0.5, lambda p: 0.5 * float(((p - goal) ** 2).sum()) + 0.5)
    s.merge(np.array([-1.0, -1.0]))
    assert s.loss == 1.75 and s.params.tolist() == [0.5, 0.5]
    a, b = s.merge(np.array([-2.0, -3.0]))
    assert np.allclose((a, b), (0.263158, 0.736842), atol=1e-6) and np.allclose(s.params, (0.868421, 1.236842), atol=1e-6) and abs(s.loss - 0.799861) < 1e-6
    assert s.loss <= 2 / (1 / 1.75 + 1 / 0.625)
    s.merge(np.array([0.0, -4.0]))
    assert np.allclose(s.acc, (-0.964987, -3.151982), atol=1e-6)
    before = s.acc.copy()
    s.merge(np.array([1e6, 1e6]))
    assert np.allclose(s.acc, before, rtol=1e-3, atol=1e-3)  # a huge loss weighs next to nothing


def test_worker_identity():
    goal = np.array([1.0, -2.0, 0.5])
    for momentum in (0.0, 0.9):
        seen = []
        s = Segment(0, np.zeros(3), 8, 1, length=3, lr=0.05, momentum=momentum)

        def steps(it, n, b, seen=seen):
            for _ in range(n):
                yield 1, lambda p: seen.append(p.copy()) or p - goal

        out = run_segment(replace(s, gate=(GateParams(), -1.3, 0, 0)), np.zeros(3), steps, lambda p: float(((p - goal) ** 2).sum()))
        p, v = np.zeros(3), np.zeros(3)
        for _ in range(24):
            v = momentum * v + (p - goal)
            p = p - 0.05 * v
        assert np.allclose(-0.05 * out.acc, p, atol=1e-12)


@pytest.mark.parametrize("model", [Softmax(64, 10), Mlp(64, 10, 7), Cnn(8, 10, (3,)), Cnn(8, 10, (2, 3), 5)])
def test_gradients(model):
    r = np.random.default_rng(0)
    x_, y = r.normal(size=(6, 64)), r.integers(0, 10, 6)
    p = model.init(1) + r.normal(0, 0.05, model.size)
    g = model.gradient(p, x_, y)
    for k in r.integers(0, model.size, 25):
        d = np.zeros(model.size)
        d[k] = 1e-5
        num = (mean_loss(model, p + d, x_, y)[0] - mean_loss(model, p - d, x_, y)[0]) / 2e-5
        assert abs(num - g[k]) < 1e-4


def test_half():
    v = np.array([1.0, -0.333, 65504.0, 1e9, 0.0, 2**-14])
    back = from_half(to_half(v))
    assert len(to_half(v)) == 12 and abs(back[1] + 0.333) <= 0.333 / 2048 and back[3] == 65504
    assert (from_half(to_half(back)) == back).all()


def test_patience():
    assert not converged([3, 2, 1], 3) and converged([3, 1, 2, 2, 2], 3) and not converged([3, 2, 2, 2, 1], 3)


def test_elastic_bounds():
    speeds = {0: 3.0, 1: 1.0, 2: 1.5}
    assert elastic_counts(speeds, 1) == {0: 1, 1: 3, 2: 2}
    assert all(c >= 1 for c in elastic_counts(speeds, 150, "spread").values())


@pytest.fixture(scope="module")
def learner(spark):
    return x.tabular_learner(spark, "/root/testdata/sf0.01")


def runs(spark, learner, *policies, workers=None, **change):
    return x.compare(spark, learner, policies, replace(x.scaled(learner, x.TABULAR), **change), workers)


def test_framework_identities(spark, learner):
    asp, loose = runs(spark, learner, x.ASP, replace(x.SSP, staleness=10**9), latency_s=0.0)  # but for asking how far others are
    assert [r[2:] for r in asp.log] == [r[2:] for r in loose.log if r[4] != "peers"]
    late = runs(spark, learner, x.SSP)[0]
    assert late.trajectory[-1][2] > runs(spark, learner, x.ASP)[0].trajectory[-1][2]
    every = runs(spark, learner, Policy("gradient", delta=-1.0), merge="equal", max_segment=1, sizing=False)[0]
    assert len([r for r in every.log if r[4] == "push"]) > 0
    again = runs(spark, learner, x.GATED[1])[0]
    assert again.log == runs(spark, learner, x.GATED[1])[0].log
    one = tables.fleet_rows()[:1]
    a, b = runs(spark, learner, x.BSP, x.ASP, workers=one, max_merges=20, pushes_per_round=1, async_scale=1.0)
    assert np.allclose([t[4] for t in a.trajectory], [t[4] for t in b.trajectory])
    tight = runs(spark, learner, replace(x.SSP, staleness=0))[0]
    clocks = dict.fromkeys(range(12), 0)
    for r in tight.log:
        if r[4] == "push":
            clocks[r[3]] += 1
            assert max(clocks.values()) - min(clocks.values()) <= 1


def test_reported_behaviour(spark, learner):
    """Which method wins, on least squares over the fleet: gated runs beat full barriers in time at their accuracy and save
    calls against bounded staleness; only elastic barriers and gates let workers alone for more than one iteration."""
    rows = {r["run_id"]: r for r in x.summary(spark, runs(spark, learner, *x.ALL)).collect()}
    bsp, ssp = rows["bsp"], rows["ssp_125"]
    for name in ("gated_-0.9_0.1", "gated_-1.3_0.1", "gated_-1.6_0.15"):
        g = rows[name]
        assert g["speedup"] > 3 and abs(g["accuracy"] - bsp["accuracy"]) < 0.01 and g["calls"] < ssp["calls"] and g["independence"] > 1.2
    assert bsp["independence"] == 1.0 and abs(rows["asp"]["independence"] - 1) < 0.2 and rows["ebsp_150"]["independence"] > 1.5


def test_sizing_levels_times(spark, learner):
    run = runs(spark, learner, x.GATED[1], apply_sizes="next_iteration", max_segment=5)[0]
    last = {}
    for a in run.allocations:
        last[a[1]] = a[5]
    first = {w[0]: w[4] * 2500 / 16 for w in tables.fleet_rows()}
    cv = lambda t: np.std(list(t.values())) / np.mean(list(t.values()))
    assert cv(last) < 0.3 * cv(first)


def test_prefetch(spark):
    from tidegate.plans.prefetch import Prefetcher

    p = Prefetcher(spark)
    p.submit(spark.range(10))
    with pytest.raises(RuntimeError):
        p.submit(spark.range(1))
    assert p.take().count() == 10
    with pytest.raises(RuntimeError):
        p.take()
    p.close()


def test_stream_restart(spark, tmp_path):
    """A gate stream that is stopped and started again decides as one that never stopped."""
    from tidegate.streaming.gate_stream import gate_stream

    rows = [(w, i + 1, v + 0.01 * w) for w in (1, 2) for i, v in enumerate(HAND)]
    for k in range(3):
        spark.createDataFrame(rows[k::3] + rows[:2], "worker_id int, iter long, loss double").coalesce(1).orderBy("iter").write.mode("overwrite").parquet(f"{tmp_path}/all/{k}")
    ordered = sorted(rows, key=lambda r: r[1])
    for k in range(2):
        part = ordered[: len(ordered) // 2] if k == 0 else ordered[len(ordered) // 2 - 2 :]
        spark.createDataFrame(part, "worker_id int, iter long, loss double").coalesce(1).write.parquet(f"{tmp_path}/in{k}")
        import shutil

        (tmp_path / "in").mkdir(exist_ok=True)
        for f in (tmp_path / f"in{k}").glob("part-*.parquet"):
            shutil.copy(f, tmp_path / "in" / f"{k}.parquet")
        s = spark.readStream.schema("worker_id int, iter long, loss double").parquet(f"{tmp_path}/in")
        q = tables.start(gate_stream(s, P3), "parquet", f"{tmp_path}/checkpoint", f"{tmp_path}/out")
        q.awaitTermination()
    out = spark.read.parquet(f"{tmp_path}/out")
    assert out.count() == len(rows)
    assert sorted(r["iter"] for r in out.where("push and worker_id = 1").collect()) == [6, 10, 11]


def test_sizing_options(spark):
    w = spark.createDataFrame([(1, 0.01, 2.0, 16, 5000), (2, 10.0, 2.0, 16, 5000), (3, 0.01, 2.0, 16, 100)], "worker_id int, sec_per_batch double, t_target double, batch_rows int, cap_rows long")
    got = {r["worker_id"]: r for r in sizing.dual_search(w, 10**6, min_rows=32).collect()}
    assert (got[1]["n_rows"], got[1]["batch_rows"], got[1]["reached"]) == (3200, 16, True)
    assert got[2]["n_rows"] == 32 and not got[2]["reached"]  # no worker is idle, however slow
    assert got[3]["n_rows"] == 100 and got[3]["batch_rows"] == 2 and not got[3]["reached"]  # memory is never passed
    assert {r["batch_rows"] for r in sizing.dual_search(w, 10**6, prefer="smallest").collect()} == {2}
    t = spark.createDataFrame([(float(v),) for v in (1, 2, 3, 4, 100)], "t double")
    assert sizing.iqr_bounds(t, "t", quartiles="nearest").first()["q3"] == 4.0
    assert [r["status"] for r in sizing.flag_outliers(t, "t").orderBy("t").collect()] == ["normal"] * 4 + ["straggler"]


def test_equal_workers_stay(spark):
    fleet = spark.range(6).select(F.col("id").cast("int").alias("worker_id"), F.lit("x").alias("family"), F.lit(0.01).alias("sec_per_batch"))
    out = sizing.reallocate(tables.timings(fleet, iters=3), fleet.select("worker_id", F.lit(10**6).cast("long").alias("cap_rows")), 10**6, "all").collect()
    assert {(r["status"], r["n_rows"], r["batch_rows"]) for r in out} == {("normal", 2500, 16)}


def test_loss_sources():
    goal = np.array([1.0, 2.0])
    told = merge.ServerState(np.zeros(2), 0.5, lambda p: 0.5 * float(((p - goal) ** 2).sum()) + 0.5, loss_source="worker")
    told.merge(np.array([-1.0, -1.0]), 9.0)
    weights = told.merge(np.array([-2.0, -3.0]), 1.75)
    assert np.allclose(weights, (0.5, 0.5)) and np.allclose(told.acc, (-1.5, -2.0))  # equal losses: the midpoint
    assert told.evaluations == 2  # none for the pushed model


def test_loss_guards():
    """Losses of zero are held off by eps; logarithms tell large losses less apart."""
    s = merge.ServerState(np.zeros(1), 1.0, lambda p: 0.0)
    s.merge(np.array([1.0]))
    assert np.allclose(s.merge(np.array([3.0])), (0.5, 0.5)) and np.allclose(s.acc, 2.0)
    plain, logs = (merge.ServerState(np.zeros(1), 1.0, lambda p: 1.0 if p[0] > -2 else 99.0, log1p=flag) for flag in (False, True))
    for one in (plain, logs):
        one.merge(np.array([1.0]))
    assert np.allclose(plain.merge(np.array([3.0])), (0.99, 0.01)) and np.allclose(logs.merge(np.array([3.0]))[1], np.log(2) / (np.log(2) + np.log(100)))


def test_crash_and_independence(spark):
    from tidegate.plans import metrics
    from tidegate.plans.trainer import crashed

    assert crashed(tables.fleet(spark), 5).count() == 5 and crashed(tables.fleet(spark), 1).count() == 0
    rows = [("r", k, float(k), 1, "iter", 0, 0) for k in range(87)] + [("r", 100 + k, 100.0 + k, 1, "model_request", 4, 0) for k in range(10)] + [("r", 200, 0.0, 2, "iter", 0, 0)]
    log = spark.createDataFrame(rows, "run_id string, seq long, vtime double, worker_id int, kind string, bytes long, global_version long")
    got = {r["worker_id"]: r["independence"] for r in metrics.independence(log).collect()}
    assert got == {1: 8.7, 2: None}


def test_late_rows_and_alarms(spark, tmp_path):
    from tidegate.streaming.alarms import silent_workers

    for k, minutes in enumerate(([0, 10, 20], [200, 210], [900])):
        rows = [(1, m) for m in minutes] + ([(2, 5)] if k == 0 else [])
        spark.createDataFrame(rows, "worker_id int, m int").select("worker_id", F.timestamp_seconds(F.col("m") * 60).alias("ts")).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    s = spark.readStream.schema("worker_id int, ts timestamp").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    q = tables.start(silent_workers(s, 3600, "1 minute"), "parquet", f"{tmp_path}/c", f"{tmp_path}/o")
    q.awaitTermination()
    alarms = {(r["worker_id"], r["last_us"] // 60_000_000) for r in spark.read.schema("worker_id int, last_us long").parquet(f"{tmp_path}/o").collect()}
    assert alarms == {(2, 5), (1, 20), (1, 210)}


def points(spark, n=6000, train=1200):
    r = np.random.default_rng(4)
    rows = [(k, [float(v) for v in r.normal(size=2)], k % 2, "train" if k < train else "test") for k in range(n)]
    return spark.createDataFrame(rows, "key long, features array<float>, label int, split string")


def test_trained_rows_are_charged(spark):
    """In tasks: each worker's iterations train on the rows that it is dealt at its turn, and the clock charges these; the whole
    test split is reported; the next turn is fetched ahead."""
    from tidegate.plans.learners import SparkLearner, Softmax, evaluate
    from tidegate.plans.trainer import BSP, TrainConfig, train

    learner = SparkLearner(points(spark), Softmax(2, 2))
    assert learner.rows == 1200
    dealt = {}
    plain = learner.dealt
    learner.dealt = lambda turn: dealt.setdefault(turn, plain(turn))
    out = train(spark, learner, tables.fleet_rows(), BSP, TrainConfig(n0=70, b0=16, max_merges=3), "all")
    k = {w[0]: w[4] for w in tables.fleet_rows()}
    keys = {}
    for turn in range(3):
        rows = dealt[turn].select("worker_id", "key").collect()
        assert len({r["key"] for r in rows}) == len(rows)  # nobody shares a row
        for w in k:
            keys[w, turn] = {r["key"] for r in rows if r["worker_id"] == w}
    assert len(out.allocations) == 36
    for a in out.allocations:
        n = len(keys[a[1], a[2] - 1])
        assert 40 < n <= 70 and a[3] == n and abs(a[5] - k[a[1]] * n / 16) < 1e-9
    assert keys[0, 0] != keys[0, 1] and len(set().union(*keys.values())) > 900
    assert out.stopped == "cap" and learner.test.count() == 4800
    assert out.accuracy == evaluate(learner.model, out.params, learner.test)[1]
    learner.close()


def test_sizes_beyond_the_rows(spark):
    """Workers that ask for more rows than there are get their shares, and a new size is dealt anew at its turn."""
    from tidegate.plans.learners import Segment, Softmax, SparkLearner

    learner = SparkLearner(points(spark), Softmax(2, 2), workers=3, prefetch=False)
    zero = np.zeros(6)
    first = learner.run([Segment(w, zero, n, 16) for w, n in ((0, 5000), (1, 2500), (2, 2500))])
    got = {s.worker_id: s.trained[0] for s in first}
    assert sum(got.values()) == 1200 and 500 < got[0] < 700 and 200 < got[1] < 400
    again = learner.run([Segment(w, zero, n, 16, iteration=1) for w, n in ((0, 100), (1, 200), (2, 300))])
    assert {s.worker_id: s.trained[0] for s in again} == {0: 100, 1: 200, 2: 300}
    learner.close()


def test_learners_agree(spark, learner):
    """Least squares in tasks and on the driver reach the same model on other mini-batches."""
    from tidegate.plans.trainer import BSP, train

    tasks = x.tabular_learner(spark, "/root/testdata/sf0.001", held=0)
    held = x.tabular_learner(spark, "/root/testdata/sf0.001")
    assert type(tasks).__name__ == "SparkLearner" and tasks.rows == held.rows
    cfg = replace(x.TABULAR, n0=400, lr=0.02, max_merges=8)
    a, b = (train(spark, one, tables.fleet_rows(), BSP, cfg) for one in (tasks, held))
    assert np.allclose(a.params, b.params, atol=0.05) and abs(a.accuracy - b.accuracy) < 0.02 and a.accuracy > 0.9
    tasks.close()


def test_batch_size_acts_alike(spark):
    """The same batch size leaves the same noise in gradients whatever the table's length."""
    spread = []
    for sf in ("sf0.001", "sf0.01"):
        one = x.tabular_learner(spark, f"/root/testdata/{sf}")
        for b in (4, 64):
            g = [gradient(np.zeros(4)) for it in range(60) for _, gradient in list(one.steps(3)(it, b, b))]
            spread.append(np.std(g, axis=0)[0])
    assert abs(spread[0] / spread[2] - 1) < 0.4 and abs(spread[1] / spread[3] - 1) < 0.4 and spread[0] > 2.5 * spread[1]


def test_sizes_act_on_what_begins_after(spark, learner):
    """One by one: an iteration that begins after a resize has the new size, one that began before has the old."""
    run = runs(spark, learner, x.GATED[1], slow=(0, 12, 1.6), resize_every=20)[0]
    mine = [a for a in run.allocations if a[1] == 0]
    assert mine[0][3] == 2500 and mine[-1][3] < 700 and len({a[3] for a in mine}) >= 3
    assert all(abs(a[5] - 0.048 * (1.6 if a[2] > 12 else 1) * a[3] / 16) < 1e-9 for a in mine)


def test_elastic_benchmark_crashes(spark, learner):
    from tidegate.plans.trainer import EBSP, benchmark_demand, train

    assert benchmark_demand(110_033, 150, 12) < 2 < benchmark_demand(989_756, 150, 12) < 4
    assert benchmark_demand(989_756, 1, 12) < 2
    with pytest.raises(MemoryError):
        train(spark, learner, tables.fleet_rows(), EBSP, x.TABULAR, demand_gb=benchmark_demand(989_756, 150, 12))


def test_every_worker_owns_a_bucket(spark):
    """Also the ones whose share of rows is far under a bucket's."""
    alloc = spark.range(1500).select(F.col("id").cast("int").alias("worker_id"), F.when(F.col("id") == 7, 10**6).otherwise(1).cast("long").alias("n_rows"), F.lit(16).alias("batch_rows"))
    owned = sizing.owned_buckets(alloc, 64 * 1500)
    assert owned.select("worker_id").distinct().count() == 1500 and owned.select("bucket").distinct().count() == owned.count() == 64 * 1500
    dealt = sizing.deal_rows(spark.range(400_000), F.col("id"), alloc).groupBy("worker_id").count()
    assert dealt.count() >= 1450  # a bucket of four rows may be empty


def test_half_scaled_gradients():
    """fp16 keeps small gradients by a loss scale."""
    from tidegate.plans.learners import Segment, run_segment

    steps = lambda it, n, b: iter([(n, lambda p: np.full(2, 3e-8))])
    got = run_segment(Segment(0, np.zeros(2), 4, 4, precision="fp16"), np.zeros(2), steps, lambda p: 1.0).acc
    assert np.allclose(got, 3e-8, rtol=0.1)


def test_shared_folder_is_asked_for(spark, monkeypatch):
    """A cluster without a shared folder gets an error, no folder of one machine."""
    class Context:
        master = "spark://host:7077"
        getCheckpointDir = staticmethod(lambda: None)  # noqa: N815

    class Session:
        conf = type("Conf", (), {"get": staticmethod(lambda *a: None)})
        sparkContext = Context()  # noqa: N815

    with pytest.raises(RuntimeError):
        tables.shared_dir(Session())
