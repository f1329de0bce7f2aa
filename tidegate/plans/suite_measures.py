"""Registered queries of the measures, over a log made of the events table."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from tidegate.plans import metrics as m
from tidegate.registry import query
from tidegate.sources import tables

KINDS = {"view": "iter", "click": "model_request", "purchase": "push", "signup": "data", "error": "report"}
FAMILY = "CASE WHEN worker_id < 2 THEN 'B1ms' WHEN worker_id < 5 THEN 'F2s_v2' WHEN worker_id < 8 THEN 'DS2_v2' WHEN worker_id < 10 THEN 'E2ds_v4' ELSE 'F4s_v2' END"
LOG = f"""e AS (SELECT 'run' || (event_id % 3) AS run_id, event_id AS seq, epoch_us(ts) / 1000000.0::DOUBLE - 1704067200 AS vtime, CAST(user_id % 12 AS INTEGER) AS worker_id,
CASE event_type {' '.join(f"WHEN '{a}' THEN '{b}'" for a, b in KINDS.items())} END AS kind, CAST(floor(value) AS BIGINT) AS bytes, event_id // 25 AS global_version FROM events),
log AS (SELECT *, {FAMILY} AS family FROM e)"""


def log(spark, sf):
    e = tables.load(spark, sf, "events", ["event_id", "ts", "user_id", "event_type", "value"])
    kinds = F.create_map(*[F.lit(x) for pair in KINDS.items() for x in pair])
    seconds = F.unix_micros(F.col("ts").cast("timestamp")) / 1e6 - 1704067200
    return e.select(
        F.concat(F.lit("run"), F.col("event_id") % 3).alias("run_id"), F.col("event_id").alias("seq"), seconds.alias("vtime"), (F.col("user_id") % 12).cast("int").alias("worker_id"),
        kinds[F.col("event_type")].alias("kind"), F.floor("value").alias("bytes"), F.floor(F.col("event_id") / 25).alias("global_version"),
    )


def r(df, *names, digits=6):
    return df.withColumns({n: F.round(n, digits) for n in names})


CALLS = "kind IN ('model_request', 'data', 'push', 'report', 'benchmark')"
CALL_SUMS = "SELECT run_id, count(*) FILTER (kind IN ('model_request', 'data', 'push', 'report', 'benchmark')) AS calls FROM log GROUP BY 1"
RATIO = "SELECT run_id, worker_id, count(*) FILTER (kind = 'iter') AS iterations, count(*) FILTER (kind = 'model_request') AS requests FROM log GROUP BY 1, 2"


@query("m1_total_iterations", f"WITH {LOG} SELECT run_id, count(*) AS iterations FROM log WHERE kind = 'iter' GROUP BY 1")
def _(spark, sf):
    return m.total_iterations(log(spark, sf))


@query("m2_time_to_converge", f"WITH {LOG} SELECT run_id, round(max(vtime) / 60, 4) AS minutes FROM log WHERE kind = 'push' GROUP BY 1")
def _(spark, sf):
    return r(m.time_to_converge(log(spark, sf)), "minutes", digits=4)


@query("m3_independence", f"WITH {LOG} SELECT *, round(iterations / nullif(requests, 0)::DOUBLE, 6) AS independence FROM ({RATIO})")
def _(spark, sf):
    return r(m.independence(log(spark, sf)), "independence")


@query("m3_mean_independence", f"WITH {LOG} SELECT run_id, round(avg(iterations / nullif(requests, 0)::DOUBLE), 6) AS independence FROM ({RATIO}) GROUP BY 1")
def _(spark, sf):
    return r(m.mean_independence(log(spark, sf)), "independence")


@query("m3_pooled_independence", f"WITH {LOG} SELECT run_id, round(sum(iterations) / nullif(sum(requests), 0)::DOUBLE, 6) AS independence FROM ({RATIO}) GROUP BY 1")
def _(spark, sf):
    return r(m.mean_independence(log(spark, sf), "pooled"), "independence")


@query("m3_independence_rollup", f"WITH {LOG} SELECT family, worker_id, count(*) FILTER (kind = 'iter') AS iterations, count(*) FILTER (kind = 'model_request') AS requests, CAST(grouping(family, worker_id) AS INTEGER) AS level, round(count(*) FILTER (kind = 'iter') / nullif(count(*) FILTER (kind = 'model_request'), 0)::DOUBLE, 6) AS independence FROM log GROUP BY ROLLUP (family, worker_id)")
def _(spark, sf):
    return r(m.independence_rollup(log(spark, sf), tables.fleet(spark)), "independence")


#: a fixed model of letter shares: for each language the sum of its letters' shares
MARKS = {"de": "äöüß", "en": "wy", "es": "ñóíá", "fr": "èêç"}


def _letters_sql() -> str:
    share = lambda c: f"CAST((len(low) - len(replace(low, '{c}', ''))) * 10.0::DOUBLE / greatest(len(text), 1) AS FLOAT)::DOUBLE"
    logits = ", ".join(" + ".join(share(c) for c in MARKS[lang]) + f" AS z{k}" for k, lang in enumerate(tables.LANGS))
    top = "greatest(z0, z1, z2, z3)"
    return f"""WITH d AS (SELECT lang, text, lower(text) AS low FROM documents WHERE doc_id % 20 >= 17 AND lang IN ('de', 'en', 'es', 'fr') AND text IS NOT NULL), z AS (SELECT lang, {logits} FROM d),
p AS (SELECT lang, CASE {' '.join(f"WHEN z{k} = {top} THEN '{lang}'" for k, lang in enumerate(tables.LANGS))} END AS said, ln(exp(z0) + exp(z1) + exp(z2) + exp(z3)) - CASE lang {' '.join(f"WHEN '{lang}' THEN z{k}" for k, lang in enumerate(tables.LANGS))} END AS loss FROM z)
SELECT lang, count(*) AS n, round(avg(loss), 6) AS loss, round(avg(CASE WHEN said = lang THEN 1.0::DOUBLE ELSE 0 END), 6) AS accuracy FROM p GROUP BY 1"""


@query("m4_accuracy_by_group", _letters_sql())
def _(spark, sf):
    """Loss and accuracy of a model on the whole test split, by group."""
    from tidegate.plans.learners import Softmax, evaluation

    model = Softmax(len(tables.LETTERS), len(tables.LANGS))
    w = np.zeros((model.d + 1, model.k))
    for k, lang in enumerate(tables.LANGS):
        w[[tables.LETTERS.index(c) for c in MARKS[lang]], k] = 1.0
    rows = tables.load(spark, sf, "documents").where("text is not null")
    test = tables.text_rows(rows).where("split = 'test' and label is not null")
    lang = F.element_at(F.array(*map(F.lit, tables.LANGS)), F.col("label") + 1)
    return r(evaluation(model, w.ravel(), test.withColumn("lang", lang), by="lang"), "loss", "accuracy")


@query("m5_api_calls", f"WITH {LOG} SELECT run_id, kind, count(*) AS calls, CAST(sum(bytes) AS BIGINT) AS bytes FROM log WHERE {CALLS} GROUP BY 1, 2")
def _(spark, sf):
    return m.api_calls(log(spark, sf))


@query("m6_bytes_moved", f"WITH {LOG} SELECT run_id, CAST(sum(bytes) AS BIGINT) AS bytes, sum(CASE WHEN kind IN ('push', 'model_request') THEN bytes / 2.0::DOUBLE ELSE bytes END) AS bytes_half FROM log GROUP BY 1")
def _(spark, sf):
    return m.bytes_moved(log(spark, sf))


RUNS = f"runs AS (SELECT family AS workload, run_id, max(vtime) / 60 AS minutes, avg(bytes) / 100 AS accuracy FROM log WHERE kind = 'push' GROUP BY 1, 2)"


def runs(spark, sf):
    named = log(spark, sf).where("kind = 'push'").join(F.broadcast(tables.fleet(spark).select("worker_id", F.col("family").alias("workload"))), "worker_id")
    return named.groupBy("workload", "run_id").agg((F.max("vtime") / 60).alias("minutes"), (F.avg("bytes") / 100).alias("accuracy"))


@query("m7_speedup", f"WITH {LOG}, {RUNS} SELECT workload, run_id, round(max(CASE WHEN run_id = 'run0' THEN minutes END) OVER (PARTITION BY workload) / minutes, 6) AS speedup FROM runs")
def _(spark, sf):
    return r(m.speedup(runs(spark, sf), "run0"), "speedup").select("workload", "run_id", "speedup")


@query("m8_comm_reduction", f"WITH {LOG}, c AS ({CALL_SUMS}) SELECT run_id, calls, round(100 * (1 - calls / (SELECT calls FROM c WHERE run_id = 'run0')::DOUBLE), 6) AS reduction_pct FROM c")
def _(spark, sf):
    return r(m.comm_reduction(m.total_calls(log(spark, sf)), "run0"), "reduction_pct")


@query("m9_accuracy_delta", f"WITH {LOG}, {RUNS} SELECT a.workload, a.run_id, round(100 * (a.accuracy - b.accuracy), 6) AS accuracy_delta FROM runs a JOIN runs b ON a.workload = b.workload AND b.run_id = 'run0'")
def _(spark, sf):
    return r(m.accuracy_delta(runs(spark, sf), "run0"), "accuracy_delta").select("workload", "run_id", "accuracy_delta")


@query("m10_wait_times", f"WITH {LOG} SELECT run_id, global_version, worker_id, round(max(vtime) OVER (PARTITION BY run_id, global_version) - vtime, 4) AS wait FROM log WHERE kind = 'push'")
def _(spark, sf):
    return r(m.wait_times(log(spark, sf)), "wait", digits=4)


@query("m11_train_times", f"WITH {LOG} SELECT run_id, worker_id, seq, round(vtime - lag(vtime) OVER (PARTITION BY run_id, worker_id ORDER BY vtime, seq), 4) AS gap FROM log WHERE kind = 'iter'")
def _(spark, sf):
    return r(m.train_times(log(spark, sf)), "gap", digits=4).drop("vtime")


@query("m11_update_gaps", f"WITH {LOG} SELECT run_id, worker_id, seq, round(vtime - lag(vtime) OVER (PARTITION BY run_id ORDER BY vtime, seq), 4) AS gap FROM log WHERE kind = 'push'")
def _(spark, sf):
    return r(m.update_gaps(log(spark, sf)), "gap", digits=4).drop("vtime")


OBS = "o AS (SELECT l_linenumber AS iter, l_suppkey, sum(l_quantity) AS t FROM lineitem GROUP BY 1, 2)"


@query("m12_time_spread", f"""WITH {OBS}, q AS (SELECT iter, quantile_cont(t, 0.25) AS a, quantile_cont(t, 0.75) AS b FROM o GROUP BY 1)
SELECT CAST(o.iter AS BIGINT) AS iter, round(avg(t), 6) AS mean_t, round(stddev_pop(t), 6) AS sd_t, round(stddev_pop(t) / avg(t), 6) AS cv, round(avg(CASE WHEN t BETWEEN a - 1.5 * (b - a) AND b + 1.5 * (b - a) THEN 1.0::DOUBLE ELSE 0 END), 6) AS share_inside
FROM o JOIN q ON o.iter = q.iter GROUP BY 1""")
def _(spark, sf):
    rows = tables.load(spark, sf, "lineitem", ["l_suppkey", "l_linenumber", "l_quantity"])
    obs = rows.groupBy(F.col("l_linenumber").cast("long").alias("iter"), "l_suppkey").agg(F.sum("l_quantity").alias("t_train"))
    return r(m.time_spread(obs), "mean_t", "sd_t", "cv", "share_inside")


@query("m13_size_trace", "SELECT CAST(l_linenumber AS BIGINT) AS iter, CAST(sum(l_quantity) AS BIGINT) AS n_rows, CAST(min(l_orderkey) % 7 + 1 AS INTEGER) AS batch_rows, round(avg(l_discount), 6) AS t_train FROM lineitem WHERE l_suppkey = 1 GROUP BY 1")
def _(spark, sf):
    """Sizes and times of one worker: suppliers as workers, line numbers as iterations."""
    rows = tables.load(spark, sf, "lineitem", ["l_orderkey", "l_suppkey", "l_linenumber", "l_quantity", "l_discount"])
    obs = rows.groupBy(F.col("l_suppkey").cast("int").alias("worker_id"), F.col("l_linenumber").cast("long").alias("iter")).agg(F.sum("l_quantity").cast("long").alias("n_rows"), (F.min("l_orderkey") % 7 + 1).cast("int").alias("batch_rows"), F.avg("l_discount").alias("t_train"))
    return r(m.size_trace(obs, 1), "t_train")


@query("m14_push_frequency", f"WITH {LOG} SELECT run_id, count(*) FILTER (kind = 'push') AS pushes, count(*) FILTER (kind = 'iter') AS iterations, round(count(*) FILTER (kind = 'push') / nullif(count(*) FILTER (kind = 'iter'), 0)::DOUBLE, 6) AS share FROM log GROUP BY 1")
def _(spark, sf):
    return r(m.push_frequency(log(spark, sf)), "share")


TRAJECTORY = "t AS (SELECT run_id, seq AS global_version, worker_id, bytes / 1000.0::DOUBLE AS accuracy FROM log WHERE kind = 'push')"


@query("m15_accuracy_steps", f"WITH {LOG}, {TRAJECTORY} SELECT run_id, global_version, worker_id, round(accuracy, 6) AS accuracy, round(accuracy - lag(accuracy) OVER (PARTITION BY run_id ORDER BY global_version), 6) AS step FROM t")
def _(spark, sf):
    t = log(spark, sf).where("kind = 'push'").select("run_id", F.col("seq").alias("global_version"), "worker_id", (F.col("bytes") / 1000.0).alias("accuracy"))
    return r(m.accuracy_steps(t), "accuracy", "step")


@query("m16_mean_of_runs", f"WITH {LOG}, {RUNS} SELECT workload, count(*) AS runs, round(avg(minutes), 4) AS minutes, round(avg(accuracy), 6) AS accuracy FROM runs GROUP BY 1")
def _(spark, sf):
    return r(r(m.mean_of_runs(runs(spark, sf), "workload", ["minutes", "accuracy"]), "accuracy"), "minutes", digits=4)


@query("m17_data_share", f"WITH {LOG} SELECT run_id, family, CAST(sum(bytes) AS BIGINT) AS bytes, round(sum(bytes) / sum(sum(bytes)) OVER (PARTITION BY run_id)::DOUBLE, 6) AS share FROM log WHERE kind = 'data' GROUP BY 1, 2")
def _(spark, sf):
    return r(m.data_share(log(spark, sf), tables.fleet(spark)), "share")


@query("m18_staleness", f"""WITH {LOG}, f AS (SELECT *, max(CASE WHEN kind = 'model_request' THEN global_version END) OVER (PARTITION BY run_id, worker_id ORDER BY vtime, seq ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS fetched FROM log)
SELECT run_id, seq, worker_id, CAST(global_version AS BIGINT) AS global_version, CAST(global_version - fetched AS BIGINT) AS staleness FROM f WHERE kind = 'push'""")
def _(spark, sf):
    return m.staleness(log(spark, sf))


@query("m_data_model_bytes", f"WITH {LOG} SELECT kind, CAST(sum(bytes) AS BIGINT) AS bytes FROM log GROUP BY 1")
def _(spark, sf):
    return log(spark, sf).groupBy("kind").agg(F.sum("bytes").alias("bytes"))
