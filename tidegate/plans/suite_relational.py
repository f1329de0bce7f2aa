"""Registered queries of the surrounding relational operators: scans, joins, aggregates, windows, sorts, sets, functions."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F

from tidegate.functions.scalar import arithmetic_hash, cosine, dot, register, squared_norm
from tidegate.plans.suite_streams import _shared
from tidegate.registry import query
from tidegate.sources import tables
from tidegate.sources.tables import load

C = F.col


def count_all():
    return F.count(F.lit(1))



def events(spark, sf, *more):
    e = load(spark, sf, "events", ["event_id", "ts", "user_id", "event_type", "value", *more])
    return e.withColumn("w", (C("user_id") % 12).cast("int"))


EV = "e AS (SELECT *, CAST(user_id % 12 AS INTEGER) AS w FROM events)"


def by_worker():
    return Window.partitionBy("w").orderBy("ts", "event_id")


WIN = "(PARTITION BY w ORDER BY ts, event_id)"


def r6(c, name):
    return F.round(c, 6).alias(name)


# ---- scans and sources -------------------------------------------------------------------------------------------


@query("r1_scan_all_tables", " UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in tables.TABLES))
def _(spark, sf):
    out = None
    for t in tables.TABLES:
        one = load(spark, sf, t).agg(count_all().alias("n")).select(F.lit(t).alias("name"), "n")
        out = one if out is None else out.unionByName(one)
    return out


@query("r2_pruned_scan", "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity >= 49 AND l_shipdate >= TIMESTAMP '1996-01-01'")
def _(spark, sf):
    return load(spark, sf, "lineitem", ["l_orderkey", "l_quantity"], (C("l_quantity") >= 49) & (C("l_shipdate") >= F.lit("1996-01-01").cast("timestamp_ntz")))


@query("r3_image_rows", """WITH s AS (SELECT vec_id AS key, [list_sum([x::DOUBLE FOR x IN embedding[6 * k + 1:6 * k + 6]]) FOR k IN range(10)] AS s FROM embeddings)
SELECT key, CAST(list_position(s, list_max(s)) - 1 AS INTEGER) AS label, CASE WHEN key % 20 >= 17 THEN 'test' ELSE 'train' END AS split FROM s""")
def _(spark, sf):
    return tables.image_rows(load(spark, sf, "embeddings")).select("key", "label", "split")


@query("r4_text_rows", "SELECT doc_id AS key, CAST(list_position(['de', 'en', 'es', 'fr'], lang) - 1 AS INTEGER) AS label, round(10 * (length(text) - length(replace(lower(text), 'e', ''))) / greatest(length(text), 1)::DOUBLE, 3) AS share_e FROM documents")
def _(spark, sf):
    t = tables.text_rows(load(spark, sf, "documents"))
    return t.select("key", "label", F.round(F.col("features")[4].cast("double"), 3).alias("share_e"))


@query("r5_tabular_rows", "WITH st AS (SELECT avg(l_quantity) AS m, stddev_pop(l_quantity) AS s FROM lineitem) SELECT l_orderkey * 7 + l_partkey * 31 + l_suppkey * 131 + l_linenumber * 1031 AS key, round((l_quantity - m) / s, 6) AS x1 FROM lineitem, st")
def _(spark, sf):
    return tables.tabular_rows(load(spark, sf, "lineitem")).select("key", r6(C("x1"), "x1"))


@query("r6_split", "SELECT CASE WHEN doc_id % 20 >= 17 THEN 'test' ELSE 'train' END AS split, count(*) AS n FROM documents GROUP BY 1")
def _(spark, sf):
    return tables.with_split(load(spark, sf, "documents", ["doc_id"]), C("doc_id")).groupBy("split").agg(count_all().alias("n"))


@query("r7_loss_series", "SELECT CAST(user_id % 12 AS INTEGER) AS worker_id, row_number() OVER (PARTITION BY user_id % 12 ORDER BY ts, event_id) AS iter, round(0.1::DOUBLE + 2.2::DOUBLE * exp(-(row_number() OVER (PARTITION BY user_id % 12 ORDER BY ts, event_id))::DOUBLE / 40) + 0.002::DOUBLE * value, 6) AS loss FROM events")
def _(spark, sf):
    return tables.loss_series(events(spark, sf)).select("worker_id", "iter", r6(C("loss"), "loss"))


@query("r8_file_stream", "SELECT event_id, event_type FROM events")
def _(spark, sf):
    from tidegate.plans.suite_streams import drained

    return drained(spark, tables.events_stream(spark, sf).select("event_id", "event_type"))


@query("r10_inline_fixtures", "SELECT f.worker_id, g.z_cut::DOUBLE AS z_cut, g.relax::DOUBLE AS relax FROM (SELECT DISTINCT CAST(user_id % 12 AS INTEGER) AS worker_id FROM events) f, (SELECT a.z_cut, b.relax FROM (VALUES (-0.9), (-1.3), (-1.6)) a(z_cut), (VALUES (0.01), (0.05), (0.1), (0.15)) b(relax)) g")
def _(spark, sf):
    workers = events(spark, sf).select(F.pmod("user_id", F.lit(12)).cast("int").alias("worker_id")).distinct()
    return workers.join(F.broadcast(tables.param_grid(spark)))  # twelve rows of settings


for form in ("parquet", "json", "csv"):

    @query(f"r11_sink_{form}", "SELECT o_orderstatus, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders GROUP BY 1")
    def _(spark, sf, form=form):
        path = f"{_shared(spark)}/sink-{uuid.uuid4().hex}"
        o = load(spark, sf, "orders", ["o_orderkey", "o_orderstatus", "o_totalprice"])
        tables.save(o, path, form, ["o_orderstatus"])
        reader = spark.read.schema(o.schema).format(form)
        back = (reader.option("header", True) if form == "csv" else reader).load(path)
        return back.groupBy("o_orderstatus").agg(count_all().alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


@query("r11_bucketed_join", "SELECT count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey")
def _(spark, sf):
    a, b = (f"bucketed_{x}_{uuid.uuid4().hex}" for x in "ab")
    try:
        tables.save_bucketed(load(spark, sf, "lineitem", ["l_orderkey", "l_quantity"]), a, "l_orderkey", 8)
        tables.save_bucketed(load(spark, sf, "orders", ["o_orderkey"]), b, "o_orderkey", 8)
        j = spark.table(a).hint("merge").join(spark.table(b), C("l_orderkey") == C("o_orderkey"))
        rows = j.agg(count_all().alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity")).collect()  # one row
    finally:
        for t in (a, b):
            spark.sql(f"DROP TABLE IF EXISTS {t}")
    return spark.createDataFrame(rows, "n long, quantity double")


def _state_sql() -> str:
    from tidegate.plans import replay_sql as sql

    run = [("gated_-1.3_0.1", -1.3, 0.1, True, None)]
    return f"WITH RECURSIVE {sql.gated_end(run)} SELECT TRUE AS same, round(loss, 6) AS loss, CAST(v AS BIGINT) AS version, TRUE AS logged FROM s"


@query("r13_run_state", _state_sql())
def _(spark, sf):
    """A run's state and log, written and read again."""
    from tidegate.plans import experiments as x
    from tidegate.plans.trainer import load_state, save_state

    learner = x.tabular_learner(spark, sf)
    run = x.compare(spark, learner, (x.GATED[1],), x.scaled(learner, x.STATIC))[0]
    path = f"{_shared(spark)}/state-{uuid.uuid4().hex}"
    save_state(spark, path, run)
    params, loss, version = load_state(spark, path)
    logged = spark.read.parquet(f"{path}/log").count() == len(run.log)
    return spark.createDataFrame([(bool((params == run.params).all()), round(loss, 6), version, logged)], "same boolean, loss double, version long, logged boolean")


# ---- projections and predicates ----------------------------------------------------------------------------------


@query("r14_computed_columns", "SELECT l_orderkey, round(l_extendedprice * (1 - l_discount) * (1 + l_tax), 6) AS charge, CAST(year(l_shipdate) AS INTEGER) AS y FROM lineitem")
def _(spark, sf):
    return load(spark, sf, "lineitem").select("l_orderkey", F.round(C("l_extendedprice") * (1 - C("l_discount")) * (1 + C("l_tax")), 6).alias("charge"), F.year("l_shipdate").alias("y"))


@query("r15_case_when", "SELECT s_suppkey, CASE WHEN s_acctbal > 5000 THEN 'high' WHEN s_acctbal < 0 THEN 'below' ELSE 'normal' END AS status FROM supplier")
def _(spark, sf):
    return load(spark, sf, "supplier").select("s_suppkey", F.when(C("s_acctbal") > 5000, "high").when(C("s_acctbal") < 0, "below").otherwise("normal").alias("status"))


@query("r16_outside_interval", "SELECT s_suppkey, s_acctbal FROM supplier WHERE NOT s_acctbal BETWEEN 0 AND 5000")
def _(spark, sf):
    return load(spark, sf, "supplier", ["s_suppkey", "s_acctbal"]).where(~C("s_acctbal").between(0, 5000))


@query("r17_membership", "SELECT p_partkey, p_size FROM part WHERE p_size IN (2, 4, 8, 16, 32, 64, 128, 256)")
def _(spark, sf):
    return load(spark, sf, "part", ["p_partkey", "p_size"]).where(C("p_size").isin([2**k for k in range(1, 9)]))


@query("r18_null_handling", f"WITH {EV}, l AS (SELECT event_id, lag(value) OVER {WIN} AS b, nullif(event_type, 'error') AS t FROM e) SELECT event_id, coalesce(b, -1.0) AS b, t IS NULL AS gone, b IS NOT DISTINCT FROM NULL AS first FROM l")
def _(spark, sf):
    e = events(spark, sf).withColumn("b", F.lag("value").over(by_worker()))
    return e.select("event_id", F.coalesce("b", F.lit(-1.0)).alias("b"), F.nullif(C("event_type"), F.lit("error")).isNull().alias("gone"), C("b").eqNullSafe(F.lit(None)).alias("first"))


@query("r19_patterns", "SELECT doc_id FROM documents WHERE text LIKE '%!!%' OR regexp_matches(source, '^src1[0-4]$') OR starts_with(lang, 'f')")
def _(spark, sf):
    return load(spark, sf, "documents").where(C("text").like("%!!%") | C("source").rlike("^src1[0-4]$") | C("lang").startswith("f")).select("doc_id")


@query("r20_safe_division", "SELECT event_id, round(value / nullif(user_id % 7, 0), 6) AS q, TRY_CAST(event_type AS INTEGER) AS k FROM events")
def _(spark, sf):
    return events(spark, sf).select("event_id", r6(F.try_divide(C("value"), C("user_id") % 7), "q"), F.expr("try_cast(event_type AS INT)").alias("k"))


# ---- joins -------------------------------------------------------------------------------------------------------


@query("r21_broadcast_join", "SELECT s_nationkey, count(*) AS n, round(sum(l_quantity), 2) AS q FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1")
def _(spark, sf):
    s = load(spark, sf, "supplier", ["s_suppkey", "s_nationkey"])
    small = F.broadcast(s) if s.count() <= 1_000_000 else s  # a size that is checked
    return load(spark, sf, "lineitem", ["l_suppkey", "l_quantity"]).join(small, C("l_suppkey") == C("s_suppkey")).groupBy("s_nationkey").agg(count_all().alias("n"), F.round(F.sum("l_quantity"), 2).alias("q"))


@query("r22_sort_merge_join", "SELECT o_orderpriority, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def _(spark, sf):
    o = load(spark, sf, "orders", ["o_orderkey", "o_orderpriority"]).hint("merge")
    return load(spark, sf, "lineitem", ["l_orderkey"]).join(o, C("l_orderkey") == C("o_orderkey")).groupBy("o_orderpriority").agg(count_all().alias("n"))


@query("r23_shuffle_hash_join", "SELECT c_mktsegment, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def _(spark, sf):
    c = load(spark, sf, "customer", ["c_custkey", "c_mktsegment"]).hint("shuffle_hash")
    return load(spark, sf, "orders", ["o_custkey", "o_totalprice"]).join(c, C("o_custkey") == C("c_custkey")).groupBy("c_mktsegment").agg(count_all().alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


@query("r24_cross_with_choices", "SELECT s_suppkey, b FROM supplier, (SELECT unnest([2, 4, 8, 16, 32, 64, 128, 256]) AS b)")
def _(spark, sf):
    return load(spark, sf, "supplier", ["s_suppkey"]).select("s_suppkey", F.explode(F.array(*[F.lit(2**k) for k in range(1, 9)])).alias("b"))


@query("r25_theta_join", "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey AND a.n_regionkey = b.n_regionkey AND a.n_name > b.n_name")
def _(spark, sf):
    n = load(spark, sf, "nation", ["n_nationkey", "n_name", "n_regionkey"])
    return n.alias("a").join(n.alias("b"), (C("a.n_nationkey") < C("b.n_nationkey")) & (C("a.n_regionkey") == C("b.n_regionkey")) & (C("a.n_name") > C("b.n_name"))).select(C("a.n_nationkey").alias("a"), C("b.n_nationkey").alias("b"))


RANGES = "g(k, lo, hi) AS (SELECT k, k * 5 + 1, k * 5 + 6 FROM range(10) t(k))"


@query("r26_range_join", f"WITH {RANGES} SELECT k, count(*) AS n FROM lineitem JOIN g ON l_quantity >= lo AND l_quantity < hi GROUP BY 1")
def _(spark, sf):
    g = spark.range(10).select(C("id").alias("k"), (C("id") * 5 + 1).alias("lo"), (C("id") * 5 + 6).alias("hi"))
    return load(spark, sf, "lineitem", ["l_quantity"]).join(F.broadcast(g), (C("l_quantity") >= C("lo")) & (C("l_quantity") < C("hi"))).groupBy("k").agg(count_all().alias("n"))  # ten ranges


@query("r27_interval_join", "SELECT epoch_us(ts) // 21600000000 AS tick, count(*) AS n FROM events GROUP BY 1")
def _(spark, sf):
    e = events(spark, sf).withColumn("us", F.unix_micros(C("ts").cast("timestamp"))).withColumn("bin", F.floor(C("us") / 21600000000))
    ticks = e.select("bin").distinct().select(C("bin").alias("tick"), (C("bin") * 21600000000).alias("start"), ((C("bin") + 1) * 21600000000).alias("end"))
    # the bin makes the interval an equality, and the interval is then checked
    return e.join(ticks, (C("bin") == C("tick")) & (C("us") >= C("start")) & (C("us") < C("end"))).groupBy("tick").agg(count_all().alias("n"))


@query("r28_asof_backward", "SELECT p.event_id, v.event_id AS view_id FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT event_id, user_id, ts FROM events WHERE event_type = 'view') v ON p.user_id = v.user_id AND p.ts >= v.ts")
def _(spark, sf):
    e = events(spark, sf).where(C("event_type").isin("purchase", "view"))
    w = Window.partitionBy("user_id").orderBy("ts", (C("event_type") == "purchase").cast("int"), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return e.withColumn("view_id", F.last(F.when(C("event_type") == "view", C("event_id")), ignorenulls=True).over(w)).where("event_type = 'purchase'").select("event_id", "view_id")


@query("r29_asof_forward", "SELECT p.event_id, v.event_id AS view_id FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT event_id, user_id, ts FROM events WHERE event_type = 'view') v ON p.user_id = v.user_id AND p.ts <= v.ts")
def _(spark, sf):
    e = events(spark, sf).where(C("event_type").isin("purchase", "view"))
    w = Window.partitionBy("user_id").orderBy("ts", (C("event_type") == "view").cast("int"), "event_id").rowsBetween(0, Window.unboundedFollowing)
    return e.withColumn("view_id", F.first(F.when(C("event_type") == "view", C("event_id")), ignorenulls=True).over(w)).where("event_type = 'purchase'").select("event_id", "view_id")


@query("r30_semi_join", "SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)")
def _(spark, sf):
    return load(spark, sf, "documents", ["doc_id", "lang"]).join(load(spark, sf, "labels", ["doc_id"], "quality = 1"), "doc_id", "left_semi")


@query("r31_anti_join", "SELECT doc_id, lang FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def _(spark, sf):
    return load(spark, sf, "documents", ["doc_id", "lang"]).join(load(spark, sf, "labels", ["doc_id"]), "doc_id", "left_anti")


@query("r32_left_join", "SELECT s_suppkey, count(l_suppkey) AS n FROM supplier LEFT JOIN (SELECT l_suppkey FROM lineitem WHERE l_quantity = 50) ON s_suppkey = l_suppkey GROUP BY 1")
def _(spark, sf):
    n = load(spark, sf, "lineitem", ["l_suppkey"], "l_quantity = 50").groupBy("l_suppkey").agg(count_all().alias("n"))
    return load(spark, sf, "supplier", ["s_suppkey"]).join(n, C("s_suppkey") == C("l_suppkey"), "left").select("s_suppkey", F.coalesce("n", F.lit(0)).cast("long").alias("n"))


@query("r32_full_join", "SELECT coalesce(a.k, b.k) AS k, a.n AS views, b.n AS clicks FROM (SELECT user_id AS k, count(*) AS n FROM events WHERE event_type = 'view' AND value > 100 GROUP BY 1) a FULL JOIN (SELECT user_id AS k, count(*) AS n FROM events WHERE event_type = 'click' AND value > 100 GROUP BY 1) b ON a.k = b.k")
def _(spark, sf):
    of = lambda t, n: events(spark, sf).where((C("event_type") == t) & (C("value") > 100)).groupBy(C("user_id").alias("k")).agg(count_all().alias(n))
    return of("view", "views").join(of("click", "clicks"), "k", "full")


@query("r33_self_join", "SELECT a.event_id, b.value - a.value AS step FROM events a JOIN events b ON b.event_id = a.event_id + 1 AND a.event_type = b.event_type")
def _(spark, sf):
    e = load(spark, sf, "events", ["event_id", "event_type", "value"])
    return e.alias("a").join(e.alias("b"), (C("b.event_id") == C("a.event_id") + 1) & (C("a.event_type") == C("b.event_type"))).select("a.event_id", (C("b.value") - C("a.value")).alias("step"))


# ---- aggregates --------------------------------------------------------------------------------------------------


@query("r36_hash_aggregate", "SELECT l_suppkey, count(*) AS n, round(sum(l_quantity), 2) AS s, round(avg(l_discount), 6) AS a, min(l_tax) AS lo, max(l_tax) AS hi FROM lineitem GROUP BY 1")
def _(spark, sf):
    return load(spark, sf, "lineitem").groupBy("l_suppkey").agg(count_all().alias("n"), F.round(F.sum("l_quantity"), 2).alias("s"), r6(F.avg("l_discount"), "a"), F.min("l_tax").alias("lo"), F.max("l_tax").alias("hi"))


@query("r37_ordered_collect", f"WITH {EV} SELECT w, string_agg(event_type, ',' ORDER BY ts, event_id) AS types, arg_max(event_type, event_id) AS last FROM e WHERE value > 150 GROUP BY 1")
def _(spark, sf):
    e = events(spark, sf).where("value > 150")
    g = e.groupBy("w").agg(F.sort_array(F.collect_list(F.struct("ts", "event_id", "event_type"))).alias("l"), F.max_by("event_type", "event_id").alias("last"))
    return g.select("w", F.array_join(F.transform("l", lambda x: x["event_type"]), ",").alias("types"), "last")


@query("r38_distinct_aggregates", "SELECT event_type, count(DISTINCT user_id) AS users, CAST(sum(DISTINCT user_id) AS BIGINT) AS ids FROM events GROUP BY 1")
def _(spark, sf):
    return events(spark, sf).groupBy("event_type").agg(F.count_distinct("user_id").alias("users"), F.sum_distinct("user_id").alias("ids"))


@query("r39_approximate_distinct", "SELECT event_type, count(DISTINCT user_id) AS users, TRUE AS near FROM events GROUP BY 1")
def _(spark, sf):
    """The sketch's count lies within three times its error of the true one."""
    both = events(spark, sf).groupBy("event_type").agg(F.count_distinct("user_id").alias("users"), F.approx_count_distinct("user_id", 0.02).alias("said"))
    return both.select("event_type", "users", (F.abs(F.col("said") - F.col("users")) <= 1 + 0.06 * F.col("users")).alias("near"))


@query("r40_exact_quantiles", "SELECT event_type, round(median(value), 6) AS med, round(quantile_cont(value, 0.9), 6) AS p90, quantile_disc(value, 0.5) AS disc FROM events GROUP BY 1")
def _(spark, sf):
    return events(spark, sf).groupBy("event_type").agg(r6(F.median("value"), "med"), r6(F.percentile("value", 0.9), "p90"), F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY value)").alias("disc"))


@query("r41_approximate_quantiles", "SELECT event_type, count(value) AS n, TRUE AS near FROM events GROUP BY 1")
def _(spark, sf):
    """The approximate quartiles' true ranks are within a thousandth of a quarter, a half and three quarters."""
    e = events(spark, sf).where("value is not null")
    q = e.groupBy("event_type").agg(F.percentile_approx("value", [0.25, 0.5, 0.75], 10_000).alias("q"))
    ranks = [f(F.count_if(test(F.col("value"), F.col("q")[k])) / F.count(F.lit(1)), p) for k, p in enumerate((0.25, 0.5, 0.75)) for f, test in ((lambda c, p: c <= p + 0.001, lambda v, x: v < x), (lambda c, p: c >= p - 0.001, lambda v, x: v <= x))]
    near = ranks[0] & ranks[1] & ranks[2] & ranks[3] & ranks[4] & ranks[5]
    return e.join(F.broadcast(q), "event_type").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), near.alias("near"))  # a row a kind of event


@query("r42_moments", """SELECT event_type, round(stddev_pop(value), 6) AS sdp, round(stddev_samp(value), 6) AS sds, round(var_pop(value), 4) AS vp, round(corr(value, user_id), 6) AS c, round(covar_pop(value, user_id), 4) AS cv, round(regr_slope(value, user_id), 6) AS slope FROM events GROUP BY 1""")
def _(spark, sf):
    v, u = C("value"), C("user_id")
    return events(spark, sf).groupBy("event_type").agg(r6(F.stddev_pop(v), "sdp"), r6(F.stddev_samp(v), "sds"), F.round(F.var_pop(v), 4).alias("vp"), r6(F.corr(v, u), "c"), F.round(F.covar_pop(v, u), 4).alias("cv"), r6(F.regr_slope(v, u), "slope"))


@query("r43_argmin_argmax", "SELECT s_nationkey, arg_min(s_suppkey, s_acctbal) AS least, arg_max(s_suppkey, s_acctbal) AS most FROM supplier GROUP BY 1")
def _(spark, sf):
    return load(spark, sf, "supplier").groupBy("s_nationkey").agg(F.min_by("s_suppkey", "s_acctbal").alias("least"), F.max_by("s_suppkey", "s_acctbal").alias("most"))


@query("r44_filtered_counts", f"WITH {EV} SELECT w, count(*) FILTER (event_type = 'view') AS views, round(coalesce(sum(value) FILTER (event_type = 'purchase'), 0), 4) AS paid FROM e GROUP BY 1")
def _(spark, sf):
    return events(spark, sf).groupBy("w").agg(F.count_if(C("event_type") == "view").alias("views"), F.round(F.coalesce(F.sum(F.when(C("event_type") == "purchase", C("value"))), F.lit(0.0)), 4).alias("paid"))


@query("r45_rollup", "SELECT n_regionkey, s_nationkey, CAST(grouping(n_regionkey, s_nationkey) AS INTEGER) AS level, count(*) AS n FROM supplier JOIN nation ON s_nationkey = n_nationkey GROUP BY ROLLUP (n_regionkey, s_nationkey)")
def _(spark, sf):
    n = load(spark, sf, "nation", ["n_nationkey", "n_regionkey"])
    return load(spark, sf, "supplier", ["s_nationkey"]).join(n, C("s_nationkey") == C("n_nationkey")).rollup("n_regionkey", "s_nationkey").agg(F.grouping_id().cast("int").alias("level"), count_all().alias("n"))


@query("r46_cube", "SELECT event_type, CAST(day(ts) AS INTEGER) AS d, count(*) AS n FROM events GROUP BY CUBE (event_type, CAST(day(ts) AS INTEGER))")
def _(spark, sf):
    return events(spark, sf).withColumn("d", F.dayofmonth("ts")).cube("event_type", "d").agg(count_all().alias("n"))


@query("r47_grouping_sets", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
def _(spark, sf):
    return load(spark, sf, "orders").groupingSets([["o_orderstatus"], ["o_orderpriority"], []], "o_orderstatus", "o_orderpriority").agg(count_all().alias("n"))


TYPES = ("click", "error", "purchase", "signup", "view")


@query("r48_pivot", f"WITH {EV} SELECT w, " + ", ".join(f"count(*) FILTER (event_type = '{t}') AS {t}" for t in TYPES) + " FROM e GROUP BY 1")
def _(spark, sf):
    return events(spark, sf).groupBy("w").pivot("event_type", list(TYPES)).agg(count_all()).na.fill(0)


@query("r48_unpivot", "SELECT l_linenumber AS k, name, round(v, 4) AS v FROM (SELECT l_linenumber, avg(l_quantity) AS quantity, avg(l_tax) AS tax FROM lineitem GROUP BY 1) UNPIVOT (v FOR name IN (quantity, tax))")
def _(spark, sf):
    g = load(spark, sf, "lineitem").groupBy(C("l_linenumber").alias("k")).agg(F.avg("l_quantity").alias("quantity"), F.avg("l_tax").alias("tax"))
    return g.unpivot("k", ["quantity", "tax"], "name", "v").withColumn("v", F.round("v", 4))


@query("r49_having", "SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY 1 HAVING count(*) > 610")
def _(spark, sf):
    return load(spark, sf, "lineitem", ["l_suppkey"]).groupBy("l_suppkey").agg(count_all().alias("n")).where("n > 610")


@query("r50_vector_aggregate", "SELECT label, round(sum(embedding[i]::DOUBLE * i), 5) AS s FROM embeddings, range(1, 65) t(i) GROUP BY 1")
def _(spark, sf):
    e = load(spark, sf, "embeddings", ["label", "embedding"]).select("label", F.posexplode("embedding").alias("p", "x"))
    return e.groupBy("label").agg(F.round(F.sum(C("x").cast("double") * (C("p") + 1)), 5).alias("s"))


# ---- windows -----------------------------------------------------------------------------------------------------


@query("r51_numbering", f"WITH {EV} SELECT event_id, row_number() OVER {WIN} AS k FROM e")
def _(spark, sf):
    return events(spark, sf).select("event_id", F.row_number().over(by_worker()).cast("long").alias("k"))


@query("r52_ranking", f"WITH {EV} SELECT event_id, rank() OVER v AS r, dense_rank() OVER v AS d, round(percent_rank() OVER v, 6) AS p, round(cume_dist() OVER v, 6) AS c, ntile(4) OVER {WIN} AS q FROM e WINDOW v AS (PARTITION BY w ORDER BY round(value))")
def _(spark, sf):
    v = Window.partitionBy("w").orderBy(F.round("value"))
    return events(spark, sf).select("event_id", F.rank().over(v).cast("long").alias("r"), F.dense_rank().over(v).cast("long").alias("d"), r6(F.percent_rank().over(v), "p"), r6(F.cume_dist().over(v), "c"), F.ntile(4).over(by_worker()).cast("long").alias("q"))


@query("r53_offsets", f"WITH {EV} SELECT event_id, lag(value) OVER {WIN} AS b, lead(value, 2) OVER {WIN} AS a FROM e")
def _(spark, sf):
    return events(spark, sf).select("event_id", F.lag("value").over(by_worker()).alias("b"), F.lead("value", 2).over(by_worker()).alias("a"))


@query("r54_ends", f"WITH {EV} SELECT event_id, first_value(value) OVER f AS a, last_value(value) OVER f AS z, nth_value(value, 3) OVER f AS third FROM e WINDOW f AS (PARTITION BY w ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def _(spark, sf):
    f = by_worker().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return events(spark, sf).select("event_id", F.first_value("value").over(f).alias("a"), F.last_value("value").over(f).alias("z"), F.nth_value("value", 3).over(f).alias("third"))


for name, (a, b, frame) in {"r55_preceding_frame": (-10, -1, "10 PRECEDING AND 1 PRECEDING"), "r56_trailing_frame": (-9, 0, "9 PRECEDING AND CURRENT ROW"), "r57_all_before": (Window.unboundedPreceding, -1, "UNBOUNDED PRECEDING AND 1 PRECEDING"), "r59_whole_partition": (Window.unboundedPreceding, Window.unboundedFollowing, "UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING")}.items():

    @query(name, f"WITH {EV} SELECT event_id, round(sum(value) OVER f, 4) AS s, count(*) OVER f AS n, max(value) OVER f AS hi FROM e WINDOW f AS (PARTITION BY w ORDER BY ts, event_id ROWS BETWEEN {frame})")
    def _(spark, sf, a=a, b=b):
        f = by_worker().rowsBetween(a, b)
        return events(spark, sf).select("event_id", F.round(F.sum("value").over(f), 4).alias("s"), F.count(F.lit(1)).over(f).alias("n"), F.max("value").over(f).alias("hi"))


@query("r58_since_best", f"WITH {EV}, b AS (SELECT event_id, ts, w, min(value) OVER {WIN} AS best FROM e) SELECT event_id, best, count(*) OVER (PARTITION BY w, best ORDER BY ts, event_id) - 1 AS since FROM b")
def _(spark, sf):
    b = events(spark, sf).withColumn("best", F.min("value").over(by_worker()))
    return b.select("event_id", "best", (F.count(F.lit(1)).over(Window.partitionBy("w", "best").orderBy("ts", "event_id")) - 1).alias("since"))


@query("r60_time_range_frame", f"WITH {EV} SELECT event_id, count(*) OVER f AS n, round(sum(value) OVER f, 4) AS s FROM (SELECT *, epoch_us(ts) // 1000000 AS sec FROM e) WINDOW f AS (PARTITION BY w ORDER BY sec RANGE BETWEEN 21600 PRECEDING AND CURRENT ROW)")
def _(spark, sf):
    e = events(spark, sf).withColumn("sec", F.floor(F.unix_micros(C("ts").cast("timestamp")) / 1000000))
    f = Window.partitionBy("w").orderBy("sec").rangeBetween(-21600, 0)
    return e.select("event_id", F.count(F.lit(1)).over(f).alias("n"), F.round(F.sum("value").over(f), 4).alias("s"))


@query("r61_exponential_smoothing", f"""WITH RECURSIVE {EV}, n AS (SELECT w, value, row_number() OVER {WIN} AS k FROM e), s AS (SELECT w, k, value AS x FROM n WHERE k = 1 UNION ALL SELECT n.w, n.k, 0.8::DOUBLE * s.x + 0.2::DOUBLE * n.value FROM s JOIN n ON n.w = s.w AND n.k = s.k + 1)
SELECT w, round(arg_max(x, k), 6) AS smoothed FROM s GROUP BY 1""")
def _(spark, sf):
    g = events(spark, sf).groupBy("w").agg(F.sort_array(F.collect_list(F.struct("ts", "event_id", "value"))).alias("l"))
    fold = F.aggregate(F.slice("l", 2, F.size("l")), C("l")[0]["value"], lambda s, x: 0.8 * s + 0.2 * x["value"])
    return g.select("w", r6(fold, "smoothed"))


# ---- sorts, limits, sets -----------------------------------------------------------------------------------------


@query("r62_global_sort", "SELECT event_id, value FROM events ORDER BY value DESC, event_id")
def _(spark, sf):
    return load(spark, sf, "events", ["event_id", "value"]).orderBy(F.desc("value"), "event_id")


@query("r63_sort_within_partitions", "SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY 1")
def _(spark, sf):
    rows = load(spark, sf, "lineitem", ["l_suppkey", "l_orderkey"]).repartition("l_suppkey").sortWithinPartitions("l_suppkey", "l_orderkey")

    def runs(batches):
        for b in batches:
            yield b.groupby("l_suppkey").size().rename("n").reset_index()

    return rows.mapInPandas(runs, "l_suppkey long, n long").groupBy("l_suppkey").agg(F.sum("n").alias("n"))


@query("r64_limit_offset", "SELECT event_id, ts FROM events ORDER BY ts, event_id LIMIT 20 OFFSET 10")
def _(spark, sf):
    return load(spark, sf, "events", ["event_id", "ts"]).orderBy("ts", "event_id").offset(10).limit(20)


@query("r65_top_k", "SELECT s_suppkey, s_acctbal FROM supplier ORDER BY s_acctbal DESC, s_suppkey LIMIT 5")
def _(spark, sf):
    return load(spark, sf, "supplier", ["s_suppkey", "s_acctbal"]).orderBy(F.desc("s_acctbal"), "s_suppkey").limit(5)


@query("r66_top_k_per_group", f"WITH {EV}, n AS (SELECT w, event_id, value, row_number() OVER (PARTITION BY w ORDER BY value DESC, event_id) AS k FROM e) SELECT w, event_id, value, k FROM n WHERE k <= 3")
def _(spark, sf):
    v = Window.partitionBy("w").orderBy(F.desc("value"), "event_id")
    return events(spark, sf).withColumn("k", F.row_number().over(v).cast("long")).where("k <= 3").select("w", "event_id", "value", "k")


PAIR = "a AS (SELECT user_id, event_type FROM events WHERE value > 100), b AS (SELECT user_id, event_type FROM events WHERE value < 20)"


def pair(spark, sf):
    e = events(spark, sf)
    return e.where("value > 100").select("user_id", "event_type"), e.where("value < 20").select("user_id", "event_type")


SETS = {
    "r67_union_all": ("UNION ALL", lambda a, b: a.unionByName(b)),
    "r67_union": ("UNION", lambda a, b: a.union(b).distinct()),
    "r68_intersect": ("INTERSECT", lambda a, b: a.intersect(b)),
    "r68_intersect_all": ("INTERSECT ALL", lambda a, b: a.intersectAll(b)),
    "r69_except": ("EXCEPT", lambda a, b: a.subtract(b)),
    "r69_except_all": ("EXCEPT ALL", lambda a, b: a.exceptAll(b)),
}
for name, (word, f) in SETS.items():

    @query(name, f"WITH {PAIR} SELECT * FROM a {word} SELECT * FROM b")
    def _(spark, sf, f=f):
        return f(*pair(spark, sf))


@query("r70_dedup_by_key", "SELECT DISTINCT user_id, event_type FROM events")
def _(spark, sf):
    return events(spark, sf).dropDuplicates(["user_id", "event_type"]).select("user_id", "event_type")


# ---- functions ---------------------------------------------------------------------------------------------------


@query("r71_math", "SELECT event_id, round(exp(-value / 50), 6) AS e, round(ln(1 + value), 6) AS l, round(log2(1 + value), 6) AS l2, round(sqrt(value), 6) AS s, floor(value) AS f, ceil(value) AS c, greatest(value, 10) AS g, least(value, 10) AS m, sign(value - 10) AS sg, (user_id % 7 + 7) % 7 AS p, CAST(1 AS BIGINT) << CAST(user_id % 8 AS INTEGER) AS sh FROM events")
def _(spark, sf):
    v = C("value")
    return events(spark, sf).select(
        "event_id", r6(F.exp(-v / 50), "e"), r6(F.ln(1 + v), "l"), r6(F.log2(1 + v), "l2"), r6(F.sqrt(v), "s"), F.floor(v).cast("double").alias("f"), F.ceil(v).cast("double").alias("c"),
        F.greatest(v, F.lit(10.0)).alias("g"), F.least(v, F.lit(10.0)).alias("m"), F.signum(v - 10).alias("sg"), F.pmod("user_id", F.lit(7)).alias("p"), F.expr("shiftleft(1L, CAST(user_id % 8 AS INT))").alias("sh"),
    )


@query("r72_strings", "SELECT doc_id, lower(lang) AS a, split_part(source, 'c', 2) AS b, substr(text, 2, 5) AS c, length(text) AS n, translate(lang, 'en', 'ne') AS t, regexp_replace(source, '[0-9]+', '#') AS r, regexp_extract(source, '([0-9]+)', 1) AS x, concat_ws('-', lang, source) AS j, lpad(CAST(doc_id AS VARCHAR), 6, '0') AS p FROM documents")
def _(spark, sf):
    return load(spark, sf, "documents").select(
        "doc_id", F.lower("lang").alias("a"), F.split_part("source", F.lit("c"), F.lit(2)).alias("b"), F.substring("text", 2, 5).alias("c"), F.length("text").cast("long").alias("n"), F.translate("lang", "en", "ne").alias("t"),
        F.regexp_replace("source", "[0-9]+", "#").alias("r"), F.regexp_extract("source", "([0-9]+)", 1).alias("x"), F.concat_ws("-", "lang", "source").alias("j"), F.lpad(C("doc_id").cast("string"), 6, "0").alias("p"),
    )


@query("r73_dates", "SELECT event_id, date_trunc('hour', ts) AS h, ts + INTERVAL 90 MINUTE AS later, date_diff('minute', date_trunc('day', ts), date_trunc('minute', ts)) AS m, epoch_us(ts) AS us, CAST(hour(ts) AS INTEGER) AS hr FROM events")
def _(spark, sf):
    return events(spark, sf).select("event_id", F.date_trunc("hour", "ts").cast("timestamp_ntz").alias("h"), F.expr("ts + INTERVAL 90 MINUTES").alias("later"), F.expr("timestampdiff(MINUTE, date_trunc('day', ts), date_trunc('minute', ts))").alias("m"), F.unix_micros(C("ts").cast("timestamp")).alias("us"), F.hour("ts").alias("hr"))


@query("r74_arrays", """SELECT vec_id, round(list_sum([x::DOUBLE * 2 FOR x IN embedding]), 5) AS doubled, len(list_filter(embedding, lambda x: x > 0)) AS positive, list_position(embedding, list_max(embedding)) AS at, list_max(embedding) > 0.3 AS some, round(list_sum([x::DOUBLE FOR x IN embedding[3:7]]), 6) AS part FROM embeddings""")
def _(spark, sf):
    add = lambda a: F.aggregate(a, F.lit(0.0), lambda s, x: s + x.cast("double"))
    return load(spark, sf, "embeddings").select(
        "vec_id", F.round(add(F.transform("embedding", lambda x: x.cast("double") * 2)), 5).alias("doubled"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"),
        F.array_position("embedding", F.array_max("embedding")).alias("at"), F.exists("embedding", lambda x: x > F.lit(0.3).cast("double")).alias("some"), r6(add(F.slice("embedding", 3, 5)), "part"),
    )


@query("r75_vectors", "SELECT a.vec_id, round(list_sum([a.embedding[i]::DOUBLE * b.embedding[i]::DOUBLE FOR i IN range(1, 65)]), 5) AS dot, round(list_sum([x::DOUBLE * x::DOUBLE FOR x IN a.embedding]), 5) AS norm2, round(list_cosine_similarity([x::DOUBLE FOR x IN a.embedding], [x::DOUBLE FOR x IN b.embedding]), 5) AS cos FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
def _(spark, sf):
    e = load(spark, sf, "embeddings", ["vec_id", "embedding"])
    j = e.alias("a").join(e.alias("b"), C("b.vec_id") == C("a.vec_id") + 1)
    a, b = C("a.embedding"), C("b.embedding")
    return j.select("a.vec_id", F.round(dot(a, b), 5).alias("dot"), F.round(squared_norm(a), 5).alias("norm2"), F.round(cosine(a, b), 5).alias("cos"))


@query("r76_maps", f"WITH {EV}, c AS (SELECT w, event_type, count(*) AS n FROM e GROUP BY 1, 2) SELECT w, count(*) AS kinds, max(n) FILTER (event_type = 'view') AS views, CAST(sum(n) FILTER (n > 150) AS BIGINT) AS many FROM c GROUP BY 1")
def _(spark, sf):
    g = events(spark, sf).groupBy("w", "event_type").agg(count_all().alias("n")).groupBy("w").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    many = F.aggregate(F.map_values(F.map_filter("m", lambda k, v: v > 150)), F.lit(0).cast("long"), lambda s, x: s + x)
    return g.select("w", F.size(F.map_keys("m")).cast("long").alias("kinds"), F.element_at("m", "view").alias("views"), F.nullif(many, F.lit(0)).alias("many"))


@query("r77_json", "SELECT event_id, CAST(props ->> '$.k' AS BIGINT) AS k, '{\"k\":' || (props ->> '$.k') || '}' AS back FROM events")
def _(spark, sf):
    e = events(spark, sf, "props").withColumn("j", F.from_json("props", "k long"))
    return e.select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"), F.to_json("j").alias("back"))


@query("r78_structs", "SELECT event_id, value + 1 AS v, event_type AS t FROM events")
def _(spark, sf):
    s = events(spark, sf).select("event_id", F.struct("value", "event_type").alias("s"))
    s = s.withColumn("s", C("s").withField("value", C("s.value") + 1))
    return s.select("event_id", C("s.value").alias("v"), C("s.event_type").alias("t"))


@query("r79_arithmetic_hash", "SELECT event_id, ((event_id % 2147483647) * 2654435761) % 4294967296 AS h FROM events")
def _(spark, sf):
    return load(spark, sf, "events", ["event_id"]).select("event_id", arithmetic_hash(C("event_id")).alias("h"))


@query("r79_xxhash")
def _(spark, sf):
    return load(spark, sf, "events", ["event_id"]).select("event_id", F.xxhash64("event_id").alias("h"))


# ---- user functions and SQL --------------------------------------------------------------------------------------


@query("r92_grouped_aggregate_udf", "SELECT label, round(avg(embedding[1]::DOUBLE), 6) AS m FROM embeddings GROUP BY 1")
def _(spark, sf):
    @F.pandas_udf("double")
    def mean(v: pd.Series) -> float:
        return float(v.mean())

    return load(spark, sf, "embeddings").groupBy("label").agg(r6(mean(C("embedding")[0].cast("double")), "m"))


@query("r95_finishes_udtf", "SELECT worker_id, k, round(k * d, 6) AS finish FROM (SELECT CAST(s_suppkey AS INTEGER) AS worker_id, 0.001::DOUBLE * (1 + s_suppkey % 97) AS d FROM supplier), range(1, 6) t(k)")
def _(spark, sf):
    @F.udtf(returnType="k: long, finish: double")
    class Finishes:
        def eval(self, d: float, count: int):
            for k in range(1, count + 1):
                yield k, round(k * d, 6)

    spark.udtf.register("future_finishes", Finishes)
    view = "workers_" + uuid.uuid4().hex
    tables.big_fleet(load(spark, sf, "supplier")).createOrReplaceTempView(view)
    return spark.sql(f"SELECT w.worker_id, f.k, f.finish FROM {view} w, LATERAL future_finishes(w.sec_per_batch, 5) f")


@query("r96_sql_functions", "SELECT s_suppkey, round(0.001::DOUBLE * (1 + s_suppkey % 97) * 2500 / 16, 6) AS t, round(-1.3::DOUBLE * pow(0.9, 3), 6) AS cut, round(greatest(s_acctbal, 100), 4) AS it FROM supplier")
def _(spark, sf):
    register(spark)
    view = "s_" + uuid.uuid4().hex
    load(spark, sf, "supplier").createOrReplaceTempView(view)
    return spark.sql(f"SELECT s_suppkey, round(predict_time(2500, 16, 1, 0.001D * (1 + s_suppkey % 97)), 6) AS t, round(relaxed_cut(-1.3D, 0.1D, 3), 6) AS cut, round(iteration_time(s_acctbal, 100, true), 4) AS it FROM {view}")


RELAXED = "s AS (SELECT DISTINCT l_linenumber AS n FROM {lines}), r(n, k, cut) AS (SELECT n, 0, CAST(-1.3 AS DOUBLE) FROM s UNION ALL SELECT n, k + 1, cut * (1 - n / CAST(100 AS DOUBLE)) FROM r WHERE k < 20) SELECT n, k, round(cut, 9) AS cut FROM r"


@query("r97_recursive_sql", "WITH RECURSIVE " + RELAXED.format(lines="lineitem"))
def _(spark, sf):
    """A cut relaxed twenty times, by as many percent as each line number says."""
    return spark.sql("WITH RECURSIVE " + RELAXED.format(lines="{lines}"), lines=load(spark, sf, "lineitem", ["l_linenumber"]))

