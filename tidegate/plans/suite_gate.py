"""Registered queries of the gate."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import functions as F

from tidegate.functions.scalar import normal_tail, relaxed_cut, z_for_tail
from tidegate.operators import gate
from tidegate.operators.gate import GateParams
from tidegate.registry import query
from tidegate.sources import tables

R6 = "round({}, 6)"
SERIES = """s AS (SELECT CAST(user_id % 12 AS INTEGER) AS worker_id, row_number() OVER (PARTITION BY user_id % 12 ORDER BY ts, event_id) AS iter, ts, event_id, value FROM events),
l AS (SELECT worker_id, iter, ts, event_id, 0.1::DOUBLE + 2.2::DOUBLE * exp(-iter::DOUBLE / 40.0::DOUBLE) + 0.002::DOUBLE * value AS loss FROM s)"""


def stats_sql(p: GateParams) -> str:
    """CTEs up to z: worker_id, iter, loss, mu, sigma, z."""
    last = "CURRENT ROW" if p.include_current else "1 PRECEDING"
    first = "UNBOUNDED PRECEDING" if p.history is None else f"{p.history - (1 if p.include_current else 0)} PRECEDING"
    sd = "stddev_pop" if p.sigma == "pop" else "stddev_samp"
    return f"""{SERIES},
w AS (SELECT worker_id, iter, loss, count(loss) OVER f AS n, avg(loss) OVER f AS m, {sd}(loss) OVER f AS s, min(loss) OVER f AS lo, max(loss) OVER f AS hi
      FROM l WINDOW f AS (PARTITION BY worker_id ORDER BY ts, event_id ROWS BETWEEN {first} AND {last})),
z AS (SELECT worker_id, iter, loss, CASE WHEN n >= {p.needed} THEN m END AS mu, CASE WHEN n >= {p.needed} THEN CASE WHEN lo = hi THEN 0 ELSE s END END AS sigma,
             CASE WHEN n >= {p.needed} AND lo < hi THEN (loss - m) / s END AS z FROM w)"""


def adaptive_sql(p: GateParams) -> str:
    """CTEs up to g: the gate iteration by iteration."""
    fired = "coalesce((z.z <= {c} AND z.z < 0) OR (z.z IS NULL AND z.sigma = 0 AND z.loss < z.mu), FALSE)"
    counts = "TRUE" if p.count_warmup else "z.sigma IS NOT NULL"

    def step(cut: str, quiet: str) -> str:
        f = fired.format(c=cut)
        q = f"CASE WHEN {f} THEN 0 WHEN {counts} THEN {quiet} + 1 ELSE {quiet} END"
        due = f"({q}) = {p.quiet_limit}" if p.relax_mode == "once" else f"({q}) >= {p.quiet_limit}"
        relaxes = f"(({due}) AND NOT {f} AND {counts})"
        kept = f"CASE WHEN {f} THEN {p.z_cut}::DOUBLE ELSE {cut} END" if p.reset_on_push else cut
        after = f"CASE WHEN {relaxes} THEN 0 ELSE {q} END" if p.relax_mode == "restart" else q
        return f"z.worker_id, z.iter, {cut} AS used, CASE WHEN {relaxes} THEN ({kept}) * (1 - {p.relax}::DOUBLE) ELSE {kept} END AS cut, CAST({after} AS BIGINT) AS quiet, {f} AS push, {relaxes} AS relaxed"

    start = f"{p.z_cut}::DOUBLE"
    return f"""WITH RECURSIVE {stats_sql(p)},
g AS (SELECT {step(start, '0::BIGINT')} FROM z WHERE z.iter = 1
      UNION ALL SELECT {step('g.cut', 'g.quiet')} FROM g JOIN z ON z.worker_id = g.worker_id AND z.iter = g.iter + 1)"""


def losses(spark, sf):
    return tables.loss_series(tables.load(spark, sf, "events", ["event_id", "ts", "user_id", "value"]))


def rounded(df, *names):
    return df.withColumns({n: F.round(n, 6) for n in names})


@query("g1_loss_history", f"WITH {SERIES} SELECT worker_id, iter, CAST(count(loss) OVER f AS BIGINT) AS n, round(sum(loss) OVER f, 6) AS queue_sum FROM l WINDOW f AS (PARTITION BY worker_id ORDER BY ts, event_id ROWS BETWEEN 10 PRECEDING AND 1 PRECEDING)")
def _(spark, sf):
    q = gate.loss_history(losses(spark, sf), 10)
    total = F.when(F.size("queue") > 0, F.aggregate("queue", F.lit(0.0), lambda s, x: s + x))
    return q.select("worker_id", "iter", F.size("queue").cast("long").alias("n"), F.round(total, 6).alias("queue_sum"))


VARIANTS = {
    "g2_rolling_stats": GateParams(),
    "g2_rolling_with_current": GateParams(include_current=True),
    "g2_rolling_sample_sigma": GateParams(sigma="sample"),
    "g2_rolling_short_history": GateParams(history=5, min_history=3),
}
for name, p in VARIANTS.items():
    sql = f"WITH {stats_sql(p)} SELECT worker_id, iter, round(loss, 6) AS loss, round(mu, 6) AS mu, round(sigma, 6) AS sigma FROM z"

    @query(name, sql)
    def _(spark, sf, p=p):
        return rounded(gate.rolling_stats(losses(spark, sf), p), "loss", "mu", "sigma").select("worker_id", "iter", "loss", "mu", "sigma")


@query("g2_rolling_chunked", f"WITH {stats_sql(GateParams())} SELECT worker_id, iter, round(loss, 6) AS loss, round(mu, 6) AS mu, round(sigma, 6) AS sigma FROM z")
def _(spark, sf):
    """Numbered by days and rolled over pieces of 200 iterations: what a series too long for one task goes through."""
    e = tables.load(spark, sf, "events", ["event_id", "ts", "user_id", "value"]).withColumn("worker_id", F.pmod("user_id", F.lit(12)).cast("int"))
    n = gate.numbered(e, F.date_trunc("day", "ts")).withColumn("loss", 0.1 + 2.2 * F.exp(-F.col("iter") / 40.0) + 0.002 * F.col("value"))
    return rounded(gate.rolling_stats_chunked(n, GateParams(), 200), "loss", "mu", "sigma").select("worker_id", "iter", "loss", "mu", "sigma")


@query("g3_z_score", f"WITH {stats_sql(GateParams())} SELECT worker_id, iter, round(z, 4) AS z FROM z")
def _(spark, sf):
    return gate.rolling_stats(losses(spark, sf)).select("worker_id", "iter", F.round("z", 4).alias("z"))


for name, p in {"g4_gate_fixed_09": GateParams(z_cut=-0.9), "g4_gate_fixed_13": GateParams(z_cut=-1.3), "g4_gate_fixed_16": GateParams(z_cut=-1.6), "g14_gate_whole_history": GateParams(history=None)}.items():
    sql = f"WITH {stats_sql(p)} SELECT worker_id, count(*) AS iterations, count(*) FILTER (coalesce((z <= {p.z_cut}::DOUBLE AND z < 0) OR (z IS NULL AND sigma = 0 AND loss < mu), FALSE)) AS pushes FROM z GROUP BY 1"

    @query(name, sql)
    def _(spark, sf, p=p):
        return gate.gate_fixed(losses(spark, sf), p).groupBy("worker_id").agg(F.count(F.lit(1)).alias("iterations"), F.count_if("push").alias("pushes"))


ADAPTIVE = {
    "g5_gate_adaptive": GateParams(),
    "g5_adaptive_16_015": GateParams(z_cut=-1.6, relax=0.15),
    "g5_adaptive_09": GateParams(z_cut=-0.9),
    "g5_with_current": GateParams(include_current=True),
    "g5_sample_sigma": GateParams(sigma="sample"),
    "g5_min_history": GateParams(min_history=3),
    "g5_no_warmup_count": GateParams(count_warmup=False),
    "g5_relax_once": GateParams(relax_mode="once"),
    "g5_relax_restart": GateParams(relax_mode="restart"),
    "g5_reset_on_push": GateParams(reset_on_push=True),
    "g5_quiet_15": GateParams(quiet_limit=15),
}
for name, p in ADAPTIVE.items():
    sql = adaptive_sql(p) + " SELECT worker_id, count(*) AS iterations, count(*) FILTER (push) AS pushes, count(*) FILTER (relaxed) AS relaxed, round(arg_max(cut, iter), 6) AS z_cut, arg_max(quiet, iter) AS quiet_run FROM g GROUP BY 1"

    @query(name, sql)
    def _(spark, sf, p=p):
        return rounded(gate.gate_adaptive(losses(spark, sf), p), "z_cut")


@query("g6_gate_decisions", adaptive_sql(GateParams()) + " SELECT g.worker_id, g.iter, round(z.loss, 6) AS loss, round(g.used, 6) AS z_cut, g.quiet AS quiet_run, g.push FROM g JOIN z USING (worker_id, iter)")
def _(spark, sf):
    return rounded(gate.gate_adaptive_arrow(losses(spark, sf)), "loss", "z_cut").select("worker_id", "iter", "loss", "z_cut", "quiet_run", "push")


@query("g8_relaxed_cut", "SELECT r, round(-1.3::DOUBLE * pow(0.9::DOUBLE, r), 9) AS cut FROM (SELECT CAST(l_linenumber AS BIGINT) AS r FROM lineitem GROUP BY 1)")
def _(spark, sf):
    r = tables.load(spark, sf, "lineitem", ["l_linenumber"]).select(F.col("l_linenumber").cast("long").alias("r")).distinct()
    return r.select("r", F.round(relaxed_cut(-1.3, 0.1, F.col("r")), 9).alias("cut"))


#: share of a normal distribution below -z, by Simpson's rule in 400 steps
TAIL = "(0.5::DOUBLE - {z} / 1200 / sqrt(2 * pi()) * list_sum(list_transform(range(401), lambda i: (CASE WHEN i IN (0, 400) THEN 1 WHEN i % 2 = 1 THEN 4 ELSE 2 END) * exp(-({z} * i / 400) * ({z} * i / 400) / 2))))"


#: tests/test_reads_tables.py has the published shares at three cuts
@query("g9_normal_tail", f"SELECT -z AS z_cut, round(100 * {TAIL.format(z='z')}, 6) AS tail_pct FROM (SELECT DISTINCT l_quantity / 10 AS z FROM lineitem)")
def _(spark, sf):
    """The shares below cuts of a tenth of each quantity."""
    cuts = tables.load(spark, sf, "lineitem", ["l_quantity"]).select((-F.col("l_quantity") / 10).alias("z_cut")).distinct()
    return cuts.select("z_cut", F.round(100 * normal_tail(F.col("z_cut")), 6).alias("tail_pct"))


@query("g10_cut_for_tail", f"""WITH RECURSIVE p AS (SELECT DISTINCT 1 + round(100 * l_discount) AS pct FROM lineitem),
h(pct, k, lo, hi) AS (SELECT pct, 0, 0::DOUBLE, 8::DOUBLE FROM p UNION ALL SELECT pct, k + 1, CASE WHEN share > pct / 100 THEN mid ELSE lo END, CASE WHEN share > pct / 100 THEN hi ELSE mid END
  FROM (SELECT *, {TAIL.format(z='mid')} AS share FROM (SELECT *, (lo + hi) / 2 AS mid FROM h WHERE k < 45)))
SELECT pct AS tail_pct, round(-lo, 5) AS z_cut FROM h WHERE k = 45""")
def _(spark, sf):
    """The cuts for a percent more than each discount, which SQL halves its way to."""
    tails = tables.load(spark, sf, "lineitem", ["l_discount"]).select((1 + F.round(100 * F.col("l_discount"))).alias("tail_pct")).distinct()
    return tails.select("tail_pct", F.round(z_for_tail(F.col("tail_pct") / 100), 5).alias("z_cut"))


@query("g11_param_check", "SELECT z_cut, relax, z_cut BETWEEN -3 AND 0 AND relax >= 0 AND relax < 1 AS valid, relax BETWEEN 0.01::DOUBLE AND 0.15::DOUBLE AS advised FROM (SELECT DISTINCT -l_quantity / 10 AS z_cut, 2 * l_discount AS relax FROM lineitem)")
def _(spark, sf):
    """Settings of a tenth of each quantity and twice each discount."""
    grid = tables.load(spark, sf, "lineitem", ["l_quantity", "l_discount"]).select((-F.col("l_quantity") / 10).alias("z"), (2 * F.col("l_discount")).alias("r")).distinct().collect()  # a few hundred
    rows = []
    for z, r in grid:
        try:
            GateParams(z_cut=z, relax=r).validate()
            rows.append((z, r, True, 0.01 <= r <= 0.15))
        except ValueError:
            rows.append((z, r, False, 0.01 <= r <= 0.15))
    return spark.createDataFrame(rows, "z_cut double, relax double, valid boolean, advised boolean")


@query("g12_gate_diagnostics", f"""WITH {SERIES}, d AS (SELECT worker_id, loss, lag(loss) OVER (PARTITION BY worker_id ORDER BY ts, event_id) AS b FROM l)
SELECT worker_id, count(loss) AS n, round(corr(loss, b), 6) AS loss_autocorr, round(avg(loss - b), 6) AS drift FROM d GROUP BY 1""")
def _(spark, sf):
    return rounded(gate.gate_diagnostics(losses(spark, sf)), "loss_autocorr", "drift").select("worker_id", "n", "loss_autocorr", "drift")


@query("g12_normality", f"""WITH {SERIES}, m AS (SELECT worker_id, avg(loss) AS mu FROM l GROUP BY 1), d AS (SELECT worker_id, loss - mu AS e FROM l JOIN m USING (worker_id))
SELECT worker_id, round(avg(e ** 3) / avg(e ** 2) ** 1.5, 6) AS skewness, round(avg(e ** 4) / avg(e ** 2) ** 2 - 3, 6) AS kurtosis FROM d GROUP BY 1""")
def _(spark, sf):
    return rounded(gate.gate_diagnostics(losses(spark, sf)), "skewness", "kurtosis").select("worker_id", "skewness", "kurtosis")


@query("g13_gate_every", f"WITH {SERIES} SELECT worker_id, count(*) AS pushes FROM l GROUP BY 1")
def _(spark, sf):
    return gate.gate_every(losses(spark, sf)).groupBy("worker_id").agg(F.count_if("push").alias("pushes"))


@query("g15_gate_gradient_change", f"""WITH {SERIES}, d AS (SELECT worker_id, iter, loss AS x, lag(loss) OVER (PARTITION BY worker_id ORDER BY ts, event_id) AS b FROM l)
SELECT worker_id, iter, round(abs(x - b) / nullif(b, 0), 6) AS change, coalesce(abs(x - b) / nullif(b, 0) >= 0.2::DOUBLE, FALSE) AS push FROM d""")
def _(spark, sf):
    norms = losses(spark, sf).withColumn("norm2", F.col("loss"))
    return rounded(gate.gate_gradient_change(norms, 0.2), "change").select("worker_id", "iter", "change", "push")


#: marks on the loss curve by cut, and that they nest
@query("x9_marks_by_cut", f"WITH {stats_sql(GateParams())} " + " UNION ALL ".join(f"SELECT {c}::DOUBLE AS z_cut, worker_id, iter FROM z WHERE z <= {c}::DOUBLE" for c in (-0.9, -1.3, -1.6)))
def _(spark, sf):
    stats = gate.rolling_stats(losses(spark, sf))
    cuts = F.filter(F.array(*[F.lit(c) for c in (-0.9, -1.3, -1.6)]), lambda c: F.col("z") <= c)
    return stats.select(F.explode(cuts).alias("z_cut"), "worker_id", "iter")


def _grid_sql() -> str:
    parts = []
    for z, r in tables.GRID:
        p = replace(GateParams(), z_cut=z, relax=r)
        parts.append(f"SELECT {z}::DOUBLE AS z_cut, {r}::DOUBLE AS relax, (SELECT count(*) FILTER (push) FROM ({adaptive_sql(p)} SELECT push FROM g)) AS pushes")
    return " UNION ALL ".join(parts)


@query("x10_push_frequency_grid", _grid_sql())
def _(spark, sf):
    out = None
    for z, r in tables.GRID:
        one = gate.gate_adaptive(losses(spark, sf), replace(GateParams(), z_cut=z, relax=r)).agg(F.sum("pushes").alias("pushes"))
        one = one.select(F.lit(z).alias("z_cut"), F.lit(r).alias("relax"), "pushes")
        out = one if out is None else out.unionByName(one)
    return out


@query("x11_tail_shares", f"""WITH {stats_sql(GateParams())} SELECT c.z_cut::DOUBLE AS z_cut, round(100.0 * count(*) FILTER (z.z <= c.z_cut) / count(z.z), 6) AS firing_pct
FROM z CROSS JOIN (VALUES (-0.9::DOUBLE), (-1.3::DOUBLE), (-1.6::DOUBLE)) c(z_cut) GROUP BY 1""")
def _(spark, sf):
    z = gate.rolling_stats(losses(spark, sf)).agg(F.count("z").alias("n"), *[F.count_if(F.col("z") <= c).alias(f"c{i}") for i, c in enumerate((-0.9, -1.3, -1.6))])
    rows = F.explode(F.array(*[F.struct(F.lit(c).alias("z_cut"), F.col(f"c{i}").alias("k")) for i, c in enumerate((-0.9, -1.3, -1.6))]))
    return z.select("n", rows.alias("r")).select("r.z_cut", F.round(F.col("r.k") * 100.0 / F.col("n"), 6).alias("firing_pct"))
