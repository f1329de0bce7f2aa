"""Registered queries of the sizing."""

from __future__ import annotations

from pyspark.sql import functions as F

from tidegate.functions.scalar import predict_time
from tidegate.operators import sizing
from tidegate.registry import query
from tidegate.sources import tables

FLEET = "f AS (SELECT CAST(s_suppkey AS INTEGER) AS worker_id, 'N' || s_nationkey AS family, 0.001::DOUBLE * (1 + s_suppkey % 97) AS k FROM supplier)"
TIMES = f"{FLEET}, o AS (SELECT worker_id, family, k, k * (2500::DOUBLE / 16) AS t FROM f)"
BOUNDS = "q AS (SELECT quantile_cont(t, 0.25) AS q1, quantile_cont(t, 0.75) AS q3, median(t) AS target FROM o), b AS (SELECT q1, q3, q3 - q1 AS iqr, q1 - 1.5 * (q3 - q1) AS lo, q3 + 1.5 * (q3 - q1) AS hi, target FROM q)"
TOTAL = 60_000


def fleet(spark, sf):
    return tables.big_fleet(tables.load(spark, sf, "supplier", ["s_suppkey", "s_nationkey"]))


def timed(spark, sf):
    return fleet(spark, sf).withColumn("t_train", predict_time(2500, 16, 1, F.col("sec_per_batch")))


def searched(spark, sf, cap=TOTAL):
    t = timed(spark, sf)
    return t.crossJoin(F.broadcast(sizing.target_time(t))).withColumn("batch_rows", F.lit(16)).withColumn("cap_rows", F.lit(cap).cast("long"))  # one row


def most_rows(b: str, cap: str = str(TOTAL)) -> str:
    """SQL: most rows whose time does not pass the target, at least 1 and at most the cap."""
    n = f"CAST(floor(target * {b} / k) AS BIGINT)"
    exact = f"CASE WHEN k * (({n} + 1)::DOUBLE / {b}) <= target THEN {n} + 1 WHEN k * ({n}::DOUBLE / {b}) <= target THEN {n} ELSE {n} - 1 END"
    return f"least(greatest({exact}, 1), {cap})"


def batch_sql(cap: str) -> str:
    return f"coalesce(list_max(list_filter([2, 4, 8, 16, 32, 64, 128, 256], lambda x: k * ({cap}::DOUBLE / x) >= target)), 2)"


@query("s1_predict_time", f"WITH {FLEET} SELECT worker_id, round(k * (2500::DOUBLE / 16), 6) AS ratio, round(k * ceil(2500::DOUBLE / 16), 6) AS whole, round(k * (2500::DOUBLE / 16) + 0.00001::DOUBLE * 2500, 6) AS affine FROM f")
def _(spark, sf):
    k = F.col("sec_per_batch")
    return fleet(spark, sf).select("worker_id", F.round(predict_time(2500, 16, 1, k), 6).alias("ratio"), F.round(predict_time(2500, 16, 1, k, "ceil"), 6).alias("whole"), F.round(predict_time(2500, 16, 1, k, row_cost=0.00001), 6).alias("affine"))


OBS = "ob AS (SELECT CAST(l_suppkey AS INTEGER) AS worker_id, l_linenumber AS iter, sum(l_quantity) AS t, count(*) AS n FROM lineitem GROUP BY 1, 2), kk AS (SELECT worker_id, iter, t, t * 16 / n AS k FROM ob)"


def observed(spark, sf):
    rows = tables.load(spark, sf, "lineitem", ["l_suppkey", "l_linenumber", "l_quantity"])
    o = rows.groupBy(F.col("l_suppkey").cast("int").alias("worker_id"), F.col("l_linenumber").cast("long").alias("iter")).agg(F.sum("l_quantity").alias("t_train"), F.count(F.lit(1)).alias("n_rows"))
    return o.withColumns({"batch_rows": F.lit(16), "epochs": F.lit(1)})


for source, pick in (("latest", "arg_max"), ("initial", "arg_min")):

    @query(f"s2_fit_k_{source}", f"WITH {OBS} SELECT worker_id, round({pick}(k, iter), 6) AS sec_per_batch, round({pick}(t, iter), 6) AS t_train FROM kk GROUP BY 1")
    def _(spark, sf, source=source):
        return sizing.fit_sec_per_batch(observed(spark, sf), source).select("worker_id", F.round("sec_per_batch", 6).alias("sec_per_batch"), F.round("t_train", 6).alias("t_train"))


@query("s2_fit_k_ewma", f"""WITH RECURSIVE {OBS}, n AS (SELECT *, row_number() OVER (PARTITION BY worker_id ORDER BY iter) AS nth FROM kk),
e AS (SELECT worker_id, nth, k FROM n WHERE nth = 1 UNION ALL SELECT n.worker_id, n.nth, 0.5::DOUBLE * e.k + 0.5::DOUBLE * n.k FROM e JOIN n ON n.worker_id = e.worker_id AND n.nth = e.nth + 1)
SELECT worker_id, round(arg_max(k, nth), 6) AS sec_per_batch FROM e GROUP BY 1""")
def _(spark, sf):
    return sizing.fit_sec_per_batch(observed(spark, sf), "ewma").select("worker_id", F.round("sec_per_batch", 6).alias("sec_per_batch"))


@query("s3_iqr_bounds", f"WITH {TIMES}, {BOUNDS} SELECT round(q1, 6) AS q1, round(q3, 6) AS q3, round(iqr, 6) AS iqr, round(lo, 6) AS lo, round(hi, 6) AS hi FROM b")
def _(spark, sf):
    return sizing.iqr_bounds(timed(spark, sf), "t_train").select(*[F.round(c, 6).alias(c) for c in ("q1", "q3", "iqr", "lo", "hi")])


@query("s3_iqr_bounds_nearest", f"WITH {TIMES} SELECT round(quantile_disc(t, 0.25), 6) AS q1, round(quantile_disc(t, 0.75), 6) AS q3 FROM o")
def _(spark, sf):
    return sizing.iqr_bounds(timed(spark, sf), "t_train", quartiles="nearest").select(F.round("q1", 6).alias("q1"), F.round("q3", 6).alias("q3"))


@query("s3_iqr_bounds_approximate", f"WITH {TIMES}, q AS (SELECT quantile_disc(t, 0.25) AS q1, quantile_disc(t, 0.75) AS q3 FROM o) SELECT round(q1, 6) AS q1, round(q3, 6) AS q3, round(q3 - q1, 6) AS iqr, round(q1 - 1.5 * (q3 - q1), 6) AS lo, round(q3 + 1.5 * (q3 - q1), 6) AS hi FROM q")
def _(spark, sf):
    """As exact as the nearest row while there are fewer rows than the sketch's accuracy."""
    bounds = sizing.iqr_bounds(timed(spark, sf), "t_train", quartiles="approximate")
    return bounds.select(*[F.round(c, 6).alias(c) for c in ("q1", "q3", "iqr", "lo", "hi")])


@query("s3_iqr_bounds_by_family", f"WITH {TIMES} SELECT family, round(quantile_cont(t, 0.25), 6) AS q1, round(quantile_cont(t, 0.75), 6) AS q3 FROM o GROUP BY 1")
def _(spark, sf):
    return sizing.iqr_bounds(timed(spark, sf), "t_train", by=["family"]).select("family", F.round("q1", 6).alias("q1"), F.round("q3", 6).alias("q3"))


#: times with a heavy tail, so that there are outliers
LINE_T = "o AS (SELECT CAST(l_suppkey AS INTEGER) AS worker_id, sum(l_quantity) * (CASE WHEN l_suppkey % 17 = 0 THEN 3 WHEN l_suppkey % 19 = 0 THEN 0.2 ELSE 1 END)::DOUBLE AS t FROM lineitem GROUP BY l_suppkey)"


@query("s4_flag_outliers", f"WITH {LINE_T}, {BOUNDS} SELECT worker_id, round(t, 6) AS t_train, CASE WHEN t > hi THEN 'straggler' WHEN t < lo THEN 'underused' ELSE 'normal' END AS status FROM o, b")
def _(spark, sf):
    factor = F.when(F.col("l_suppkey") % 17 == 0, 3.0).when(F.col("l_suppkey") % 19 == 0, 0.2).otherwise(1.0)
    t = tables.load(spark, sf, "lineitem", ["l_suppkey", "l_quantity"]).groupBy("l_suppkey").agg(F.sum("l_quantity").alias("q"))
    return sizing.flag_outliers(t.select(F.col("l_suppkey").cast("int").alias("worker_id"), (F.col("q") * factor).alias("t_train"))).select("worker_id", F.round("t_train", 6).alias("t_train"), "status")


@query("s5_target_time", f"WITH {TIMES} SELECT round(median(t), 6) AS t_target FROM o")
def _(spark, sf):
    return sizing.target_time(timed(spark, sf)).select(F.round("t_target", 6).alias("t_target"))


@query("s6_search_rows", f"WITH {TIMES}, {BOUNDS}, c AS (SELECT worker_id, k, target, unnest([2, 4, 8, 16, 32, 64, 128, 256]) AS bs FROM o, b) SELECT worker_id, bs AS batch_rows, {most_rows('bs')} AS n_rows FROM c")
def _(spark, sf):
    rows = searched(spark, sf).withColumn("batch_rows", F.explode(F.array(*[F.lit(2**e) for e in range(1, 9)])))
    n = sizing.search_rows(F.col("t_target"), F.col("sec_per_batch"), F.lit(1), F.col("batch_rows"), F.col("cap_rows"))
    return rows.select("worker_id", "batch_rows", F.greatest(n, F.lit(1).cast("long")).alias("n_rows"))


@query("s7_search_batch", f"WITH {TIMES}, {BOUNDS} SELECT worker_id, {batch_sql('3000')} AS largest, CASE WHEN k * (3000::DOUBLE / 16) >= target THEN 16 ELSE least(16, {batch_sql('3000')}) END AS kept FROM o, b")
def _(spark, sf):
    rows = searched(spark, sf, 3000)
    search = lambda prefer: sizing.search_batch(F.col("t_target"), F.col("sec_per_batch"), F.lit(1), F.col("cap_rows"), F.col("batch_rows"), prefer)
    return rows.select("worker_id", search("largest").alias("largest"), search("current").alias("kept"))


SEARCHED = f"SELECT worker_id, 16 AS batch_rows, {most_rows('16')} AS n_rows FROM o, b"


@query("s8_dual_search", f"WITH {TIMES}, {BOUNDS} SELECT worker_id, batch_rows, n_rows FROM (SELECT worker_id, k, target, CASE WHEN k * ({TOTAL}::DOUBLE / 16) >= target THEN 16 ELSE least(16, {batch_sql(str(TOTAL))}) END AS batch_rows FROM o, b) x, LATERAL (SELECT {most_rows('x.batch_rows')} AS n_rows) y")
def _(spark, sf):
    return sizing.dual_search(searched(spark, sf), TOTAL).select("worker_id", "batch_rows", "n_rows")


@query("s8_dual_search_largest", f"WITH {TIMES}, {BOUNDS} SELECT worker_id, batch_rows, n_rows FROM (SELECT worker_id, k, target, {batch_sql('3000')} AS batch_rows FROM o, b) x, LATERAL (SELECT {most_rows('x.batch_rows', '3000')} AS n_rows) y")
def _(spark, sf):
    return sizing.dual_search(searched(spark, sf, 3000), TOTAL, prefer="largest").select("worker_id", "batch_rows", "n_rows")


CAP = "CAST(greatest(floor((8 * 0.5::DOUBLE * 1073741824 - 2 * 110000 * {bytes}) / (4096 * 2.0::DOUBLE)), 0) AS BIGINT)"


@query("s9_row_cap", f"WITH {FLEET} SELECT worker_id, {CAP.format(bytes=4)} AS cap_fp32, {CAP.format(bytes=2)} AS cap_mixed FROM f")
def _(spark, sf):
    f = fleet(spark, sf)
    cap = lambda precision: sizing.row_cap(F.col("mem_gb") * 0.5 * 2**30, 4096, 110_000, precision)
    return f.select("worker_id", cap("fp32").alias("cap_fp32"), cap("mixed").alias("cap_mixed"))


@query("s10_initial_allocation", f"WITH {FLEET} SELECT worker_id, 2500::BIGINT AS n_rows, 16 AS batch_rows, round(k * (2500::DOUBLE / 16), 6) AS t_pred FROM f")
def _(spark, sf):
    return sizing.initial_allocation(sizing.with_caps(fleet(spark, sf))).withColumn("t_pred", F.round("t_pred", 6))


SLOWED = f"{FLEET}, o0 AS (SELECT worker_id, k * (CASE WHEN worker_id % 25 = 0 THEN 8 ELSE 1 END)::DOUBLE * (2500::DOUBLE / 16) AS t FROM f), o AS (SELECT worker_id, t, t * 16 / 2500::DOUBLE AS k FROM o0)"


def slowed(spark, sf):
    k = F.col("sec_per_batch") * F.when(F.col("worker_id") % 25 == 0, 8.0).otherwise(1.0)
    f = fleet(spark, sf).withColumn("sec_per_batch", k)
    return f, f.select("worker_id", F.lit(1).cast("long").alias("iter"), F.lit(2500).cast("long").alias("n_rows"), F.lit(16).alias("batch_rows"), F.lit(1).alias("epochs"), predict_time(2500, 16, 1, F.col("sec_per_batch")).alias("t_train"))


for resize, change in (("outliers", "t > hi OR t < lo"), ("all", "TRUE")):

    @query(f"s11_reallocate_{resize}", f"""WITH {SLOWED}, {BOUNDS} SELECT worker_id, CASE WHEN t > hi THEN 'straggler' WHEN t < lo THEN 'underused' ELSE 'normal' END AS status,
CAST(CASE WHEN {change} THEN {most_rows('bs')} ELSE 2500 END AS BIGINT) AS n_rows
FROM (SELECT *, CASE WHEN k * ({TOTAL}::DOUBLE / 16) >= target THEN 16 ELSE least(16, {batch_sql(str(TOTAL))}) END AS bs FROM o, b)""")
    def _(spark, sf, resize=resize):
        f, obs = slowed(spark, sf)
        caps = f.select("worker_id", F.lit(TOTAL).cast("long").alias("cap_rows"))
        return sizing.reallocate(obs, caps, TOTAL, resize).select("worker_id", "status", "n_rows")


HASH = "(((({key}) * 1009 + 42) % 2147483647) * 2654435761) % 4294967296"
LINE_KEY = "l_orderkey * 7 + l_partkey * 31 + l_suppkey * 131 + l_linenumber * 1031"


@query("s13_deal_rows", f"""WITH a AS (SELECT CAST(worker_id AS INTEGER) AS worker_id, CAST(500 + 300 * worker_id AS BIGINT) AS n FROM range(12) t(worker_id)),
c AS (SELECT worker_id, n, CAST(sum(n) OVER (ORDER BY worker_id) AS BIGINT) AS upto, CAST(sum(n) OVER () AS BIGINT) AS total FROM a),
e AS (SELECT worker_id, n, CAST(floor((upto - n) * 1012 / total::DOUBLE) AS BIGINT) + worker_id AS lo, CAST(floor(upto * 1012 / total::DOUBLE) AS BIGINT) + worker_id + 1 AS hi FROM c),
d AS (SELECT ({HASH.format(key=LINE_KEY)}) % 1024 AS bucket FROM lineitem)
SELECT e.worker_id, least(count(*), any_value(n)) AS dealt FROM d JOIN e ON bucket >= lo AND bucket < hi GROUP BY 1""")
def _(spark, sf):
    alloc = spark.range(12).select(F.col("id").cast("int").alias("worker_id"), (500 + 300 * F.col("id")).alias("n_rows"), F.lit(16).alias("batch_rows"))
    rows = tables.load(spark, sf, "lineitem", ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"])
    return sizing.deal_rows(rows, F.expr(tables.LINE_KEY), alloc).groupBy("worker_id").agg(F.count(F.lit(1)).alias("dealt"))


HASHED = "(((doc_id * 1009 + 42) % 2147483647) * 2654435761) % 4294967296"


@query("s13_deal_rows_by_label", f"""WITH d AS (SELECT doc_id, CASE lang WHEN 'de' THEN 0 WHEN 'en' THEN 1 WHEN 'es' THEN 2 WHEN 'fr' THEN 3 ELSE -1 END AS label, CAST({HASHED} AS BIGINT) AS h FROM documents),
n AS (SELECT label, count(*) AS n FROM d GROUP BY 1), t AS (SELECT label, n, CAST(sum(n) OVER (ORDER BY label) AS BIGINT) AS upto, CAST(sum(n) OVER () AS BIGINT) AS total FROM n),
r AS (SELECT label, least(CAST(floor((upto - n) * 1024 / total::DOUBLE) AS BIGINT), 1023) AS lo, greatest(CAST(floor(upto * 1024 / total::DOUBLE) AS BIGINT) - CAST(floor((upto - n) * 1024 / total::DOUBLE) AS BIGINT), 1) AS width FROM t),
b AS (SELECT doc_id, d.label, h, lo + h % width AS bucket FROM d JOIN r ON d.label = r.label),
e AS (SELECT w AS worker_id, CAST(floor(200 * w * 1012 / 2400::DOUBLE) AS BIGINT) + w AS lo, CAST(floor(200 * (w + 1) * 1012 / 2400::DOUBLE) AS BIGINT) + w + 1 AS hi FROM range(12) q(w)),
p AS (SELECT worker_id, label, row_number() OVER (PARTITION BY worker_id ORDER BY bucket, h, doc_id) AS pos FROM b JOIN e ON bucket >= e.lo AND bucket < e.hi)
SELECT CAST(worker_id AS INTEGER) AS worker_id, nullif(label, -1) AS label, count(*) AS dealt FROM p WHERE pos <= 200 GROUP BY 1, 2""")
def _(spark, sf):
    alloc = tables.fleet(spark).select("worker_id", F.lit(200).cast("long").alias("n_rows"), F.lit(16).alias("batch_rows"))
    rows = tables.text_rows(tables.load(spark, sf, "documents"))
    dealt = sizing.deal_rows(rows, F.col("key"), alloc, skew=F.col("label"))
    return dealt.groupBy("worker_id", "label").agg(F.count(F.lit(1)).alias("dealt"))


@query("s14_exhaustive_search", f"WITH {TIMES}, {BOUNDS} SELECT worker_id, batch_rows, least(3000, greatest(1, CAST(floor(target * batch_rows / k + 1e-9) AS BIGINT))) AS n_rows FROM (SELECT worker_id, k, target, {batch_sql('3000')} AS batch_rows FROM o, b)")
def _(spark, sf):
    return sizing.dual_search_brute(searched(spark, sf, 3000), TOTAL).select("worker_id", "batch_rows", "n_rows")


@query("s15_static_allocation", f"WITH {FLEET} SELECT worker_id, 2500::BIGINT AS n_rows, 16 AS batch_rows, round(k * (2500::DOUBLE / 16), 6) AS t_pred FROM f")
def _(spark, sf):
    return sizing.static_allocation(fleet(spark, sf), 2500, 16).withColumn("t_pred", F.round("t_pred", 6))


@query("s16_benchmark_sizing", f"WITH {FLEET} SELECT worker_id, round(k * (2500::DOUBLE / 16), 6) AS t_train, round(list_sum(list_transform([2, 4, 8, 16, 32, 64, 128, 256], lambda b: k * (2500::DOUBLE / b))), 6) AS cost, 8::BIGINT AS probes FROM f")
def _(spark, sf):
    return sizing.benchmark_workers(fleet(spark, sf)).withColumns({"t_train": F.round("t_train", 6), "cost": F.round("cost", 6)})


SIZES = (60_000, 6_000_000, 600_000_000)


def _probes_sql() -> str:
    """Binary searches as a recursion over (worker, table size)."""
    every = ", ".join(f"({n}::BIGINT)" for n in SIZES)
    return f"""WITH RECURSIVE {TIMES}, {BOUNDS}, w AS (SELECT worker_id, k, target, total FROM o, b, (VALUES {every}) n(total)),
s AS (SELECT worker_id, total, k, target, CASE WHEN k * (total::DOUBLE / 16) >= target THEN 16 ELSE least(16, {batch_sql('total')}) END AS bs FROM w),
h(worker_id, total, k, target, bs, lo, hi, probes) AS (SELECT worker_id, total, k, target, bs, 0::BIGINT, total, 0 FROM s
  UNION ALL SELECT worker_id, total, k, target, bs, CASE WHEN k * (mid::DOUBLE / bs) <= target THEN mid ELSE lo END, CASE WHEN k * (mid::DOUBLE / bs) <= target THEN hi ELSE mid - 1 END, probes + 1
  FROM (SELECT *, (lo + hi + 1) // 2 AS mid FROM h WHERE lo < hi)),
p AS (SELECT worker_id, total, max(probes) + 3 AS probes, any_value(k) AS k FROM h GROUP BY 1, 2)
SELECT total AS total_rows, count(*) AS workers, CAST(sum(probes) AS BIGINT) AS search_probes, CAST(count(*) * 8 AS BIGINT) AS brute_probes, CAST(count(*) * 8 AS BIGINT) AS benchmark_probes,
  round(sum(list_sum(list_transform([2, 4, 8, 16, 32, 64, 128, 256], lambda x: k * (2500::DOUBLE / x)))), 4) AS benchmark_seconds FROM p GROUP BY 1"""


@query("x12_search_cost", _probes_sql())
def _(spark, sf):
    """What sizing looks at: predicted times by the dual search (log of rows and of batch sizes) and by trying all batch sizes in closed form, and runs
    of a probe, with the seconds they take, by benchmarking."""
    out = None
    for total in SIZES:
        w = searched(spark, sf, total)
        looked = sizing.search_probes(w, total).agg(F.count(F.lit(1)).alias("workers"), F.sum("probes").alias("search_probes"))
        tried = w.join(sizing.dual_search_brute(w, total).select("worker_id"), "worker_id").agg((F.count(F.lit(1)) * (sizing.HIGH_EXP - sizing.LOW_EXP + 1)).alias("brute_probes"))
        timed_ = sizing.benchmark_workers(fleet(spark, sf)).agg(F.sum("probes").alias("benchmark_probes"), F.round(F.sum("cost"), 4).alias("benchmark_seconds"))
        one = looked.crossJoin(F.broadcast(tried)).crossJoin(F.broadcast(timed_)).select(F.lit(total).cast("long").alias("total_rows"), "*")  # one row each
        out = one if out is None else out.unionByName(one)
    return out


FLEETS = (12, 100, 1000)


@query("x13_fleet_spread", f"""WITH f AS (SELECT n AS fleet, i AS worker_id, 0.001::DOUBLE * (1 + (i * 37) % (n // 2)) AS k FROM (VALUES (12), (100), (1000)) q(n), (SELECT DISTINCT o_custkey % 1000 AS i FROM orders) WHERE i < n),
o AS (SELECT *, k * (2500::DOUBLE / 16) AS t FROM f), b AS (SELECT fleet, median(t) AS target FROM o GROUP BY 1),
s AS (SELECT o.*, target, CASE WHEN k * ({TOTAL}::DOUBLE / 16) >= target THEN 16 ELSE least(16, {batch_sql(str(TOTAL))}) END AS bs FROM o JOIN b ON o.fleet = b.fleet)
SELECT fleet AS workers, round(stddev_pop(t) / avg(t), 6) AS cv_before, round(stddev_pop(t2) / avg(t2), 4) AS cv_after FROM (SELECT *, k * ({most_rows('bs')}::DOUBLE / bs) AS t2 FROM s) GROUP BY 1""")
def _(spark, sf):
    """Spread of times before and after sizing, in fleets of more workers and wider ranges of speed: workers are customers of orders, their keys modulo 1000."""
    out = None
    for n in FLEETS:
        w = tables.load(spark, sf, "orders", ["o_custkey"]).select(F.pmod("o_custkey", F.lit(1000)).alias("id")).distinct().where(F.col("id") < n).select(F.col("id").cast("int").alias("worker_id"), (0.001 * (1 + F.pmod(F.col("id") * 37, F.lit(n // 2)))).alias("sec_per_batch"))
        t = w.withColumn("t_train", predict_time(2500, 16, 1, F.col("sec_per_batch")))
        s = t.crossJoin(F.broadcast(sizing.target_time(t))).withColumn("batch_rows", F.lit(16)).withColumn("cap_rows", F.lit(TOTAL).cast("long"))  # one row
        both = t.select("worker_id", "t_train").join(sizing.dual_search(s, TOTAL), "worker_id")
        one = both.agg(F.round(F.stddev_pop("t_train") / F.avg("t_train"), 6).alias("cv_before"), F.round(F.stddev_pop("t_pred") / F.avg("t_pred"), 4).alias("cv_after"))
        one = one.select(F.lit(n).alias("workers"), "*")
        out = one if out is None else out.unionByName(one)
    return out
