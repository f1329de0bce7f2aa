"""Registered queries of whole training runs: the framework, its baselines and the evaluation's workloads."""

from __future__ import annotations

import math
from dataclasses import replace

from pyspark.sql import Window
from pyspark.sql import functions as F

from tidegate.operators.gate import GateParams
from tidegate.operators.sizing import deal_rows
from tidegate.plans import experiments as x
from tidegate.plans import metrics
from tidegate.plans import replay_sql as sql
from tidegate.plans.prefetch import Prefetcher
from tidegate.plans.trainer import Policy, benchmark_demand, crashed, elastic_counts
from tidegate.registry import query
from tidegate.sources import tables

TIGHT, SPREAD = replace(x.SSP, staleness=3), replace(x.EBSP, objective="spread")
FORECAST_BYTES = 64 * 150
SYSTEM_GB = 1.0
#: runs with the sizes that were dealt first: the replays in SQL know no others
RUNS = {
    "b1_bsp_run": (x.BSP, sql.barrier_row("bsp")),
    "b2_asp_run": (x.ASP, sql.push_rows([("asp", None)])),
    "b3_ssp_run": (x.SSP, sql.push_rows([("ssp_125", 125)])),
    "b3_ssp_tight_run": (TIGHT, sql.push_rows([("ssp_3", 3)])),
    "b4_elastic_run": (x.EBSP, sql.barrier_row("ebsp_150", sql.elastic_counts(), FORECAST_BYTES, 600_000)),
    "b4_elastic_spread_run": (SPREAD, sql.barrier_row("ebsp_150", sql.elastic_counts(objective="spread"), FORECAST_BYTES, 2_500_000)),
    "b5_gradient_change_run": (x.GRADIENT, sql.gated_rows([("gradient", 0.0, 0.0, True, 0.5)])),
}
for name, (policy, oracle) in RUNS.items():

    @query(name, oracle)
    def _(spark, sf, policy=policy):
        learner = x.tabular_learner(spark, sf)
        return x.summary(spark, x.compare(spark, learner, (policy,), x.scaled(learner, x.STATIC)), workload="lineitem")


@query("t1_gated_run", sql.gated_rows([("gated_-1.3_0.1", -1.3, 0.1, True, None)], sql.RESIZED))
def _(spark, sf):
    """The whole framework: gate, weighted merges, and sizes that follow the monitor."""
    learner = x.tabular_learner(spark, sf)
    return x.summary(spark, x.compare(spark, learner, (x.GATED[1],), x.scaled(learner, x.TABULAR)), workload="lineitem")


def _elastic_sql(lookahead: int) -> str:
    return f"SELECT {lookahead} AS lookahead, CAST(q.w AS INTEGER) AS worker_id, CAST(c AS INTEGER) AS iterations, round(c * d, 6) AS finishes_at FROM ({sql.elastic_counts(lookahead)}) q JOIN took ON q.w = took.w"


@query("b4_elastic_barrier", f"WITH {tables.EVENT_FLEET}, took AS (SELECT worker_id AS w, k * 156.25::DOUBLE AS d FROM f) " + " UNION ALL ".join(f"SELECT * FROM ({_elastic_sql(r)})" for r in (10, 150)) + " UNION ALL SELECT 1, w, CAST(floor(m / d + 1e-9::DOUBLE) AS INTEGER), round(floor(m / d + 1e-9::DOUBLE) * d, 6) FROM took, (SELECT max(d) AS m FROM took)")
def _(spark, sf):
    found = tables.event_fleet(tables.load(spark, sf, "events", ["user_id", "value"])).collect()  # twelve workers
    speeds = {w["worker_id"]: w["sec_per_batch"] * 156.25 for w in found}
    rows = [(r, w, n, round(n * speeds[w], 6)) for r in (1, 10, 150) for w, n in elastic_counts(speeds, r).items()]
    return spark.createDataFrame(rows, "lookahead int, worker_id int, iterations int, finishes_at double")


#: forecasts of each worker's finishes, and the barrier with the least waiting, as joins and aggregates
@query("b4_barrier_forecast", f"""WITH {tables.EVENT_FLEET}, s AS (SELECT worker_id, k * 156.25::DOUBLE AS d FROM f), c AS (SELECT DISTINCT round(d * n, 6) AS barrier FROM s, range(1, 21) t(n)),
w AS (SELECT barrier, sum(barrier - floor(barrier / d + 1e-9) * d) / barrier AS cost, CAST(sum(floor(barrier / d + 1e-9)) AS BIGINT) AS iterations, max(d) AS slowest FROM c, s GROUP BY barrier)
SELECT round(barrier, 6) AS barrier, round(cost, 6) AS wait_share, iterations FROM w WHERE barrier >= slowest - 1e-9""")
def _(spark, sf):
    s = tables.event_fleet(tables.load(spark, sf, "events", ["user_id", "value"])).select("worker_id", (F.col("sec_per_batch") * 156.25).alias("d"))
    c = s.select(F.explode(F.transform(F.sequence(F.lit(1), F.lit(20)), lambda n: F.round(F.col("d") * n, 6))).alias("barrier")).distinct()
    n = F.floor(F.col("barrier") / F.col("d") + 1e-9)
    w = c.join(F.broadcast(s)).groupBy("barrier").agg(F.sum(F.col("barrier") - n * F.col("d")).alias("wait"), F.sum(n).alias("iterations"), F.max("d").alias("slowest"))  # twelve workers
    return w.where("barrier >= slowest - 1e-9").select(F.round("barrier", 6).alias("barrier"), F.round(F.col("wait") / F.col("barrier"), 6).alias("wait_share"), "iterations")


@query("b6_static_sizes_run", sql.gated_rows([("gated_-1.3_0.1_static", -1.3, 0.1, True, None)]))
def _(spark, sf):
    learner = x.tabular_learner(spark, sf)
    return x.summary(spark, x.compare(spark, learner, (x.GATED[1],), x.scaled(learner, x.STATIC), tag="_static"), workload="lineitem")


DEMANDS = [(m, p, r) for m, p in (("cnn", 110_033), ("deep_cnn", 989_756)) for r in (1, 150)]


@query("b7_crash", f"""WITH {tables.EVENT_FLEET},
d(model, parameters, lookahead) AS (VALUES {', '.join(f"('{m}', {p}::BIGINT, {r})" for m, p, r in DEMANDS)}),
n AS (SELECT *, {SYSTEM_GB}::DOUBLE + ((1 + lookahead) * 3 * parameters * 4 + 8 * lookahead * 12) / 1073741824.0::DOUBLE AS demand FROM d)
SELECT model, lookahead, round(demand, 6) AS demand_gb, worker_id, gb AS mem_gb FROM n JOIN f ON gb < demand""")
def _(spark, sf):
    """Workers that elastic benchmarking of each model would lose."""
    fleet, out = tables.event_fleet(tables.load(spark, sf, "events", ["user_id", "value"])), None
    for model, parameters, lookahead in DEMANDS:
        need = benchmark_demand(parameters, lookahead, 12)
        lost = crashed(fleet, need).select(F.lit(model).alias("model"), F.lit(lookahead).alias("lookahead"), F.round(F.lit(need), 6).alias("demand_gb"), "worker_id", "mem_gb")
        out = lost if out is None else out.unionByName(lost)
    return out


def _turns_sql(turns: int, rows: int, buckets: int = 96, w: int = 12) -> str:
    """What deal_rows() gives each worker at each turn, from rows counted by bucket."""
    h = "(((key * 1009 + 42) % 2147483647) * 2654435761) % 4294967296"
    return f"""WITH {sql.TABULAR}, b AS (SELECT {h} % {buckets} AS bucket, count(*) AS n FROM rows WHERE split = 'train' GROUP BY 1),
o AS (SELECT w, CAST(floor({rows} * w * {buckets - w} / {rows * w}::DOUBLE) AS BIGINT) + w AS lo, CAST(floor({rows} * (w + 1) * {buckets - w} / {rows * w}::DOUBLE) AS BIGINT) + w + 1 AS hi FROM range({w}) r(w)),
p AS (SELECT t, (bucket + t * {buckets // 3 + 1}) % {buckets} AS place, n FROM b, range({turns}) r(t))
SELECT CAST(t AS INTEGER) AS iter, CAST(w AS INTEGER) AS worker_id, CAST(least(sum(n), {rows}) AS BIGINT) AS n_rows FROM p JOIN o ON place >= lo AND place < hi GROUP BY 1, 2"""


@query("p1_prefetch", _turns_sql(3, 500))
def _(spark, sf):
    """Three turns of dealt rows, each fetched while the one before is counted, as the learner does while it trains."""
    learner = x.tabular_learner(spark, sf, held=0)
    p, seen = Prefetcher(spark), []
    try:
        learner.sizes = {w[0]: (500, 16) for w in tables.fleet_rows()}
        p.submit(learner.dealt(0))
        for it in range(3):
            shard = p.take()
            if it < 2:
                p.submit(learner.dealt(it + 1))
            seen += [(it, r["worker_id"], r["n"]) for r in shard.groupBy("worker_id").agg(F.count(F.lit(1)).alias("n")).collect()]  # a row a worker
            shard.unpersist()
    finally:
        p.close()
        learner.close()
    return spark.createDataFrame(seen, "iter int, worker_id int, n_rows long")


#: far limits, so that patience ends runs; "stopped" says which did
FAR = {"max_merges": 6_000, "max_iterations": 300_000}


@query("x1_image_frameworks")
def _(spark, sf):
    learner = x.image_learner(spark, sf)
    cfg = replace(x.scaled(learner, x.SMALL, 1 / 12), epochs=8, max_segment=20, precision="mixed", **FAR)
    return _closing(learner, x.summary(spark, x.compare(spark, learner, x.ALL, cfg), workload="embeddings"))


@query("x1_image_cnn")
def _(spark, sf):
    """The smaller published model's size (110,033 parameters) and settings, under all frameworks but elastic barriers."""
    learner = x.image_learner(spark, sf, "cnn")
    cfg = replace(x.scaled(learner, x.SMALL, 1 / 12), epochs=8, max_segment=20, min_delta=0.001, **FAR)
    return _closing(learner, x.summary(spark, x.compare(spark, learner, (x.BSP, x.ASP, x.SSP, *x.GATED), cfg), workload="embeddings"))


@query("x2_text_frameworks")
def _(spark, sf):
    """The larger model's settings; elastic barriers lose the workers whose memory its benchmark exceeds, and their run fails."""
    learner = x.text_learner(spark, sf)
    cfg = replace(x.scaled(learner, x.LARGE, 1 / 12), epochs=8, max_segment=20, **FAR)
    policies = (x.BSP, x.ASP, x.SSP, *x.with_quiet(x.GATED[2:], 15))
    done = _closing(learner, x.summary(spark, x.compare(spark, learner, policies, cfg), workload="documents"))
    need = benchmark_demand(989_756, x.EBSP.lookahead, 12)
    try:
        x.train(spark, learner, tables.fleet_rows(), x.EBSP, cfg, demand_gb=need)
    except MemoryError:
        failed = spark.createDataFrame([("documents", x.EBSP.name, "crashed")], "workload string, run_id string, stopped string")
        return done.unionByName(failed, allowMissingColumns=True)
    return done


def _closing(learner, df):
    rows, kind = df.collect(), df.schema  # a row a run
    learner.close()
    return df.sparkSession.createDataFrame(rows, kind)


GATES = [("gated_-0.9_0.1", -0.9, 0.1, True, None), ("gated_-1.3_0.1", -1.3, 0.1, True, None), ("gated_-1.6_0.15", -1.6, 0.15, True, None)]


def _frameworks_sql() -> str:
    undamped = sql.push_rows([("asp_undamped", None), ("ssp_125_undamped", 125)], "1::DOUBLE")
    runs = [sql.barrier_row("bsp"), sql.barrier_row("ebsp_150", sql.elastic_counts(), FORECAST_BYTES, 600_000), sql.push_rows([("asp", None), ("ssp_125", 125)]), undamped, sql.gated_rows([*GATES, ("gradient", 0.0, 0.0, True, 0.5)], sql.RESIZED)]
    every = " UNION ALL ".join(f"SELECT * FROM ({q})" for q in runs)
    return f"""WITH r AS ({every}), b AS (SELECT minutes AS bm, accuracy AS ba FROM r WHERE run_id = 'bsp')
SELECT r.* REPLACE (round(bm / minutes, 4) AS speedup, round(100 * (accuracy - ba), 4) AS accuracy_delta) FROM r, b"""


@query("x3_tabular_frameworks", _frameworks_sql())
def _(spark, sf):
    learner = x.tabular_learner(spark, sf)
    runs = x.compare(spark, learner, (*x.ALL, x.GRADIENT), x.scaled(learner, x.TABULAR))
    runs += x.compare(spark, learner, (x.ASP, x.SSP), x.scaled(learner, x.UNDAMPED), tag="_undamped")
    return x.summary(spark, runs, workload="lineitem")


@query("x4_straggler_waits", f"""WITH {sql.TABULAR}, {sql.FLEET}, size AS (SELECT CAST(greatest(16, least(2500, floor(0.05::DOUBLE * count(*)))) AS BIGINT) AS n FROM rows WHERE split = 'train'),
d AS (SELECT w, family, k * n / 16 AS d FROM f, size)
SELECT CAST(w AS INTEGER) AS worker_id, family, round(max(d) OVER () - d + 1e-9::DOUBLE, 3) AS mean_wait, round(max(d) OVER () + 2 * {sql.SENT} + 1e-9::DOUBLE, 3) AS mean_gap, round(d + 1e-9::DOUBLE, 3) AS train_time, d = min(d) OVER () AS fastest FROM d""")
def _(spark, sf):
    """Under full barriers: each worker's training time, its wait for the others, and the time from update to update."""
    learner = x.tabular_learner(spark, sf)
    log, _, obs = x.logs(spark, x.compare(spark, learner, (x.BSP,), x.scaled(learner, x.STATIC)))
    waits = metrics.wait_times(log).groupBy("worker_id").agg(F.round(F.avg("wait") + 1e-9, 3).alias("mean_wait"))
    gaps = metrics.train_times(log).groupBy("worker_id").agg(F.round(F.avg("gap") + 1e-9, 3).alias("mean_gap"))
    own = obs.groupBy("worker_id").agg(F.round(F.avg("t_train") + 1e-9, 3).alias("train_time"))
    own = own.withColumn("fastest", F.col("train_time") == F.min("train_time").over(Window.partitionBy()))  # a row a worker
    return waits.join(gaps, "worker_id").join(own, "worker_id").join(tables.fleet(spark).select("worker_id", "family"), "worker_id")


#: trajectories of a full barrier, of no barrier, and of a gate
def _trajectory_sql() -> str:
    step = f"SELECT 'bsp' AS run_id, v AS global_version, v * ((SELECT max(d) FROM took) + {sql.SENT}) + (v - 1) * {sql.SENT} AS vtime, -1 AS worker_id, loss FROM (SELECT r.* FROM rounds r JOIN ends e ON r.v <= e.v)"
    bsp = f"SELECT * FROM (WITH RECURSIVE {sql.maps()}, {sql.barriers()}, {sql.stop('rounds')} SELECT q.*, {sql.ACCURACY.format(loss='q.loss')} AS accuracy FROM ({step}) q, t)"
    asp = f"SELECT * FROM (WITH RECURSIVE {sql.maps()}, {sql.pushes([('asp', None)])}, {sql.stop('events')} SELECT e.run, e.v, e.time, NULL, e.loss, {sql.ACCURACY.format(loss='e.loss')} FROM events e JOIN ends x ON e.run = x.run AND e.v <= x.v, t)"
    gated = f"SELECT * FROM (WITH RECURSIVE {sql.maps()}, {sql.gated([('gated_-1.3_0.1', -1.3, 0.1, True, None)])}, {sql.stop('events')} SELECT e.run, e.v, e.time, e.worker_id, e.loss, {sql.ACCURACY.format(loss='e.loss')} FROM events e JOIN ends x ON e.run = x.run AND e.v <= x.v, t)"
    return f"SELECT run_id, CAST(global_version AS BIGINT) AS global_version, round(vtime, 4) AS vtime, round(loss, 6) AS loss, round(accuracy, 6) AS accuracy FROM ({bsp} UNION ALL {asp} UNION ALL {gated})"


@query("x5_trajectory", _trajectory_sql())
def _(spark, sf):
    learner = x.tabular_learner(spark, sf)
    steps = x.logs(spark, x.compare(spark, learner, (x.BSP, x.ASP, x.GATED[1]), x.scaled(learner, x.STATIC)))[1]
    return steps.select("run_id", "global_version", *[F.round(c, n).alias(c) for c, n in (("vtime", 4), ("loss", 6), ("accuracy", 6))])


def _settled_sql() -> str:
    run = [("gated_-1.3_0.1", -1.3, 0.1, True, None)]
    return f"""WITH RECURSIVE {sql.gated_end(run, sizes=sql.RESIZED)},
c AS (SELECT f.w, min(its[f.w + 1]) + 1 AS turn FROM walk, f WHERE sz[f.w + 1] = 1 AND time <= (SELECT time FROM s) GROUP BY 1),
e AS (SELECT f.w, f.family, done[f.w + 1] AS iterations, CASE WHEN turn <= done[f.w + 1] THEN turn ELSE 1 END AS settled, CASE WHEN turn <= done[f.w + 1] THEN 1 ELSE 0 END AS z FROM s, f LEFT JOIN c ON c.w = f.w),
g AS (SELECT e.*, a.d AS first_time, b.d AS settled_time, x.n AS settled_rows, median(b.d) OVER () AS median_time, min(e.w) OVER (PARTITION BY e.family) AS head
  FROM e JOIN took a ON a.w = e.w AND a.z = 0 JOIN took b ON b.w = e.w AND b.z = e.z JOIN sizes x ON x.w = e.w AND x.z = e.z)
SELECT family, CAST(w AS INTEGER) AS worker_id, round(first_time + 1e-9::DOUBLE, 3) AS first_time, round(settled_time + 1e-9::DOUBLE, 3) AS settled_time, round(median_time + 1e-9::DOUBLE, 3) AS median_time, CAST(settled_rows AS BIGINT) AS settled_rows,
  CAST(settled AS BIGINT) AS settled_at, CAST(iterations AS BIGINT) AS iterations FROM g WHERE w = head"""


@query("x6_stabilised_times", _settled_sql())
def _(spark, sf):
    """Iteration times of one worker of each family before and after sizing, and when they settled near the fleet's median."""
    learner = x.tabular_learner(spark, sf)
    obs = x.logs(spark, x.compare(spark, learner, (x.GATED[1],), x.scaled(learner, x.TABULAR)))[2]
    ends = obs.groupBy("worker_id").agg(F.min_by("t_train", "iter").alias("first_time"), F.max_by("t_train", "iter").alias("settled_time"), F.max_by("n_rows", "iter").alias("settled_rows"), F.count(F.lit(1)).alias("iterations"))
    settled = obs.join(ends.select("worker_id", "settled_time"), "worker_id").where("abs(t_train - settled_time) < 1e-9").groupBy("worker_id").agg(F.min("iter").alias("settled_at"))
    fleet = tables.fleet(spark).groupBy("family").agg(F.min("worker_id").alias("worker_id"))  # one of each family
    median = ends.agg(F.median("settled_time").alias("median_time"))
    both = ends.join(settled, "worker_id").join(fleet, "worker_id").crossJoin(F.broadcast(median))  # one row
    return both.select("family", "worker_id", *[F.round(F.col(c) + 1e-9, 3).alias(c) for c in ("first_time", "settled_time", "median_time")], "settled_rows", "settled_at", "iterations")


def _spread_sql() -> str:
    ends = "SELECT 'first' AS iter, d FROM took WHERE z = 0 UNION ALL SELECT 'last', max_by(d, z) FROM took GROUP BY w"
    return f"""WITH {sql.maps(spare=0, sizes=sql.RESIZED)}, o AS ({ends}), q AS (SELECT iter, quantile_cont(d, 0.25) AS a, quantile_cont(d, 0.75) AS b FROM o GROUP BY 1)
SELECT o.iter, round(avg(d), 6) AS mean_t, round(stddev_pop(d), 6) AS sd_t, round(stddev_pop(d) / avg(d), 6) AS cv, round(avg(CASE WHEN d BETWEEN a - 1.5 * (b - a) AND b + 1.5 * (b - a) THEN 1.0::DOUBLE ELSE 0 END), 6) AS share_inside FROM o JOIN q ON o.iter = q.iter GROUP BY 1"""


@query("x6_time_spread", _spread_sql())
def _(spark, sf):
    """Spread of the fleet's iteration times before and after sizing."""
    learner = x.tabular_learner(spark, sf)
    obs = x.logs(spark, x.compare(spark, learner, (x.GATED[1],), x.scaled(learner, x.TABULAR)))[2]
    ends = obs.groupBy("worker_id").agg(F.min_by("t_train", "iter").alias("first"), F.max_by("t_train", "iter").alias("last"))
    both = ends.select(F.explode(F.array(F.struct(F.lit("first").alias("iter"), F.col("first").alias("t_train")), F.struct(F.lit("last").alias("iter"), F.col("last").alias("t_train")))).alias("r")).select("r.*")
    spread = metrics.time_spread(both)
    return spread.select("iter", *[F.round(c, 6).alias(c) for c in spread.columns if c != "iter"])


@query("x7_weakest_worker")
def _(spark, sf):
    learner = x.tabular_learner(spark, sf)
    cfg = replace(x.scaled(learner, x.TABULAR), slow=(0, 12, 1.6), resize_every=20)
    return metrics.size_trace(x.logs(spark, x.compare(spark, learner, (x.GATED[1],), cfg))[2], 0)


MARKED = 8  # a worker of the family that the published figure shows


def _marks_sql() -> str:
    run = [("gated_-1.3_0.1", -1.3, 0.1, True, None)]
    return f"""WITH RECURSIVE {sql.maps()}, {sql.gated(run)}, {sql.stop('events')},
g AS (SELECT e.v, e.time, e.worker_id, {sql.ACCURACY.format(loss='e.loss')} AS accuracy FROM events e JOIN ends x ON e.v <= x.v, t),
s AS (SELECT *, accuracy - lag(accuracy) OVER (ORDER BY v) AS step FROM g),
last AS (SELECT max(v) AS v, max(time) AS time FROM g),
w AS (SELECT ev, time, its[{MARKED + 1}] AS iter, list_last(queue[{MARKED + 1}]) AS loss, pend[{MARKED + 1}] AS push FROM walk WHERE who = {MARKED + 1} AND NOT pushed AND time <= (SELECT time FROM last))
SELECT CAST(iter AS BIGINT) AS iter, round(w.time, 4) AS vtime, round(loss, 6) AS loss, push, CAST(s.v AS BIGINT) AS global_version, round(s.accuracy, 6) AS accuracy, round(s.step, 6) AS step
FROM w LEFT JOIN s ON push AND s.worker_id = {MARKED} AND abs(s.time - w.time - {sql.SENT}) < 1e-6"""


@query("x8_marks_and_steps", _marks_sql())
def _(spark, sf):
    """One worker's loss series, the marks where its gate pushed, and what each of these pushes did to the global model's score."""
    learner = x.tabular_learner(spark, sf)
    run = x.compare(spark, learner, (x.GATED[1],), x.scaled(learner, x.STATIC))[0]
    log, steps, obs = x.logs(spark, [run])
    at = log.where(f"kind = 'iter' and worker_id = {MARKED}").withColumn("iter", F.row_number().over(Window.partitionBy("worker_id").orderBy("vtime")).cast("long")).select("iter", "vtime")
    gains = metrics.accuracy_steps(steps).join(steps.select("global_version", F.col("vtime").alias("merged")), "global_version").where(f"worker_id = {MARKED}")
    mine = obs.where(f"worker_id = {MARKED}").select("iter", "loss", "push").join(at, "iter")
    sent = learner_sent(learner)
    j = mine.join(F.broadcast(gains), F.col("push") & (F.abs(F.col("merged") - F.col("vtime") - sent) < 1e-6), "left")  # a row a push of one worker
    return j.select("iter", F.round("vtime", 4).alias("vtime"), F.round("loss", 6).alias("loss"), "push", "global_version", F.round("accuracy", 6).alias("accuracy"), F.round("step", 6).alias("step"))


def learner_sent(learner, cfg=x.STATIC) -> float:
    """Virtual time that a push is on its way."""
    return cfg.latency_s + 4 * len(learner.w_init) / cfg.link_bytes_per_s


GRID_RUNS = [(f"gated_{z}_{r}", z, r, True, None) for z, r in tables.GRID]
GRID_SQL = f"WITH RECURSIVE {sql.gated_end(GRID_RUNS)}"


def grid_runs(spark, sf):
    learner = x.tabular_learner(spark, sf)
    runs = x.compare(spark, learner, tuple(Policy("gated", GateParams(z_cut=z, relax=r)) for z, r in tables.GRID), x.scaled(learner, x.STATIC))
    rows = [(z, r, run.trajectory[-1][1], sum(k[4] == "iter" for k in run.log), float(run.accuracy)) for (z, r), run in zip(tables.GRID, runs, strict=True)]
    return spark.createDataFrame(rows, "z_cut double, relax double, pushes long, iterations long, accuracy double")


@query("x10_pushes_and_accuracy", GRID_SQL + ", k(run, z, r) AS (VALUES " + ", ".join(f"('gated_{z}_{r}', {z}::DOUBLE, {r}::DOUBLE)" for z, r in tables.GRID) + ") SELECT z AS z_cut, r AS relax, CAST(v AS BIGINT) AS pushes, CAST(iterations AS BIGINT) AS iterations, round(v / iterations::DOUBLE, 6) AS share, round(accuracy, 6) AS accuracy FROM s JOIN k ON s.run = k.run")
def _(spark, sf):
    """Pushes and final accuracy of whole runs for each cut and relaxation."""
    return grid_runs(spark, sf).select("z_cut", "relax", "pushes", "iterations", F.round(F.col("pushes") / F.col("iterations"), 6).alias("share"), F.round("accuracy", 6).alias("accuracy"))


@query("x14_ablation")
def _(spark, sf):
    learner = x.tabular_learner(spark, sf)
    cfg = x.scaled(learner, x.TABULAR)
    runs = x.compare(spark, learner, (x.BSP, x.GATED[1]), cfg)
    for tag, change in (("_no_sizing", {"sizing": False}), ("_equal_merge", {"merge": "equal"}), ("_no_prefetch", {"prefetch": False}), ("_half", {"precision": "mixed"}), ("_worker_loss", {"loss_source": "worker"})):
        runs += x.compare(spark, learner, (x.GATED[1],), replace(cfg, **change), tag=tag)
    runs += x.compare(spark, learner, (x.ASP,), cfg, tag="_no_gate")
    return x.summary(spark, runs, workload="lineitem")


@query("x15_merge_rules", sql.gated_rows([("gated_-1.3_0.1_weighted", -1.3, 0.1, True, None), ("gated_-1.3_0.1_equal", -1.3, 0.1, False, None)]).join(["SELECT run_id, iterations, minutes, accuracy, loss, calls FROM (", ")"]) + f" UNION ALL SELECT run_id, iterations, minutes, accuracy, loss, calls FROM ({sql.barrier_row('bsp')})")
def _(spark, sf):
    learner = x.tabular_learner(spark, sf)
    cfg = x.scaled(learner, x.STATIC)
    runs = x.compare(spark, learner, (x.GATED[1],), cfg, tag="_weighted") + x.compare(spark, learner, (x.GATED[1],), replace(cfg, merge="equal"), tag="_equal") + x.compare(spark, learner, (x.BSP,), cfg)
    return x.summary(spark, runs, workload="lineitem").select("run_id", "iterations", "minutes", "accuracy", "loss", "calls")


def _calls_sql() -> str:
    one = lambda q: f"SELECT run_id, calls FROM ({q})"
    runs = [sql.barrier_row("bsp"), sql.barrier_row("ebsp_150", sql.elastic_counts(), FORECAST_BYTES, 600_000), sql.push_rows([("asp", None), ("ssp_125", 125)]), sql.gated_rows(GATES)]
    return f"WITH c AS ({' UNION ALL '.join(map(one, runs))}) SELECT run_id, calls, round(100 * (1 - calls / (SELECT calls FROM c WHERE run_id = 'ssp_125')::DOUBLE), 6) AS reduction_pct FROM c"


@query("x16_communication", _calls_sql())
def _(spark, sf):
    learner = x.tabular_learner(spark, sf)
    log, _, _ = x.logs(spark, x.compare(spark, learner, x.ALL, x.scaled(learner, x.STATIC)))
    return metrics.comm_reduction(metrics.total_calls(log), "ssp_125").withColumn("reduction_pct", F.round("reduction_pct", 6))


@query("x17_accuracy_spread", GRID_SQL + " SELECT count(*) AS runs, round(min(accuracy), 6) AS least, round(max(accuracy), 6) AS most, round(100 * (max(accuracy) - min(accuracy)), 4) AS spread_points FROM s")
def _(spark, sf):
    acc = grid_runs(spark, sf)
    return acc.agg(F.count(F.lit(1)).alias("runs"), F.round(F.min("accuracy"), 6).alias("least"), F.round(F.max("accuracy"), 6).alias("most"), F.round(100 * (F.max("accuracy") - F.min("accuracy")), 4).alias("spread_points"))


def _seeds_sql() -> str:
    run = [("gated_-1.6_0.15", -1.6, 0.15, True, None)]
    one = lambda s: f"SELECT * FROM (WITH RECURSIVE {sql.gated_end(run, s)} SELECT run AS config, accuracy, time / 60 AS minutes FROM s)"
    return f"SELECT config, count(*) AS runs, round(avg(accuracy), 6) AS accuracy, round(avg(minutes), 4) AS minutes FROM ({' UNION ALL '.join(one(s) for s in (1, 2, 3))}) GROUP BY 1"


@query("m16_three_seeds", _seeds_sql())
def _(spark, sf):
    runs = []
    for seed in (1, 2, 3):
        learner = x.tabular_learner(spark, sf, seed)
        runs += x.compare(spark, learner, (x.GATED[2],), x.scaled(learner, replace(x.STATIC, seed=seed)))
    rows = [(r.run_id, float(r.accuracy), r.trajectory[-1][2] / 60) for r in runs]
    means = metrics.mean_of_runs(spark.createDataFrame(rows, "config string, accuracy double, minutes double"), "config", ["accuracy", "minutes"])
    return means.withColumns({"accuracy": F.round("accuracy", 6), "minutes": F.round("minutes", 4)})


@query("a8_local_training")
def _(spark, sf):
    """Each worker trains alone on its dealt rows from the common start: its losses by iteration, and rows trained."""
    from tidegate.plans.learners import Segment

    learner = x.image_learner(spark, sf, held=0)
    try:
        rows = []
        for momentum in (0.0, 0.9):
            segments = [Segment(w[0], learner.w_init * 0, math.ceil(learner.rows / 12), 16, epochs=4, length=1, lr=0.1 * (1 - momentum), momentum=momentum) for w in tables.fleet_rows()]
            for it in range(3):
                segments = [replace(s, losses=[], zs=[], trained=[], fired=False) if it else s for s in segments]
                segments = learner.run(segments)
                rows += [(momentum, it + 1, s.worker_id, s.trained[0], float(learner.evaluate(learner.w_init - s.lr * s.acc)[0])) for s in segments]
    finally:
        learner.close()
    return spark.createDataFrame(rows, "momentum double, iter int, worker_id int, trained int, loss double")
