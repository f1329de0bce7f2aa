"""Registered queries of merging, sufficient statistics, compression and evaluation."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import functions as F

from tidegate.functions.scalar import iteration_time
from tidegate.operators import compress, merge
from tidegate.plans.learners import CNN_110K, CNN_990K, Cnn, Mlp, Softmax, evaluation
from tidegate.registry import query
from tidegate.sources import tables

TABULAR = """st AS (SELECT avg(l_quantity) AS m1, stddev_pop(l_quantity) AS s1, avg(l_extendedprice) AS m2, stddev_pop(l_extendedprice) AS s2, avg(l_discount) AS m3, stddev_pop(l_discount) AS s3 FROM lineitem),
r0 AS (SELECT l_orderkey * 7 + l_partkey * 31 + l_suppkey * 131 + l_linenumber * 1031 AS key, (l_quantity - m1) / s1 AS x1, (l_extendedprice - m2) / s2 AS x2, (l_discount - m3) / s3 AS x3 FROM lineitem, st),
rows AS (SELECT key, x1, x2, x3, 2 + 0.3::DOUBLE * x1 - 0.5::DOUBLE * x2 + 0.1::DOUBLE * x3 + 0.1::DOUBLE * ((((key % 2147483647) * 2654435761) % 4294967296) / 2147483648.0::DOUBLE - 1) AS y,
         CASE WHEN key % 20 >= 17 THEN 'test' ELSE 'train' END AS split FROM r0)"""
GRAM_TERMS = [(f"g{i}{j}", f"({a}) * ({b})") for i, a in enumerate(("1.0::DOUBLE", "x1", "x2", "x3")) for j, b in enumerate(("1.0::DOUBLE", "x1", "x2", "x3")) if j >= i] + [(f"b{i}", f"({a}) * y") for i, a in enumerate(("1.0::DOUBLE", "x1", "x2", "x3"))]


def rows(spark, sf):
    cols = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount"]
    return tables.tabular_rows(tables.load(spark, sf, "lineitem", cols))


@query("a4_loss_weighted_mix", """WITH p AS (SELECT a.vec_id AS id, a.embedding AS u, b.embedding AS v, 1.0::DOUBLE + a.label AS la, 1.0::DOUBLE + b.label AS lb FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1)
SELECT id, round(list_sum([((1 / la) * u[i]::DOUBLE + (1 / lb) * v[i]::DOUBLE) / (1 / la + 1 / lb) FOR i IN range(1, 65)]), 5) AS total, round(((1 / la) * u[1]::DOUBLE + (1 / lb) * v[1]::DOUBLE) / (1 / la + 1 / lb), 6) AS first FROM p""")
def _(spark, sf):
    e = tables.load(spark, sf, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("v"), (1.0 + F.col("label")).alias("l"))
    pairs = e.alias("a").join(e.alias("b"), F.col("b.vec_id") == F.col("a.vec_id") + 1).select(F.col("a.vec_id").alias("id"), F.col("a.v").alias("u"), F.col("b.v").alias("v"), F.col("a.l").alias("la"), F.col("b.l").alias("lb"))
    mixed = merge.mix_columns(pairs, "u", "v", "la", "lb")
    return mixed.select("id", F.round(F.aggregate("mixed", F.lit(0.0), lambda s, x: s + x), 5).alias("total"), F.round(F.col("mixed")[0], 6).alias("first"))


#: gradients of the first orders, as pushes of two numbers around a goal
PUSHES = "p AS (SELECT row_number() OVER (ORDER BY o_orderkey) AS push, -1 - (o_orderkey % 5)::DOUBLE AS x, -1 - (o_custkey % 7)::DOUBLE AS y FROM orders QUALIFY push <= 40)"
GOAL = (2.0, 4.0)


def pushed(spark, sf) -> list[tuple[float, float]]:
    rows = tables.load(spark, sf, "orders", ["o_orderkey", "o_custkey"]).orderBy("o_orderkey").limit(40).collect()
    return [(-1 - r["o_orderkey"] % 5, -1 - r["o_custkey"] % 7) for r in rows]


def _merges_sql() -> str:
    loss = lambda x, y: f"(0.5::DOUBLE * ((-0.5::DOUBLE * {x} - {GOAL[0]}) * (-0.5::DOUBLE * {x} - {GOAL[0]}) + (-0.5::DOUBLE * {y} - {GOAL[1]}) * (-0.5::DOUBLE * {y} - {GOAL[1]})) + 0.5::DOUBLE)"
    return f"""WITH RECURSIVE {PUSHES}, w AS (SELECT *, 1 / {loss('x', 'y')} AS theirs FROM p),
m(push, a, b, w_server, w_worker) AS (SELECT push, x, y, NULL::DOUBLE, NULL::DOUBLE FROM w WHERE push = 1
  UNION ALL SELECT w.push, (mine * a + theirs * x) / (mine + theirs), (mine * b + theirs * y) / (mine + theirs), mine / (mine + theirs), theirs / (mine + theirs) FROM (SELECT *, 1 / {loss('a', 'b')} AS mine FROM m) q JOIN w ON w.push = q.push + 1)
SELECT CAST(push AS INTEGER) AS push, round(w_server, 6) AS w_server, round(w_worker, 6) AS w_worker, round(a, 6) AS acc0, round(b, 6) AS acc1, round({loss('a', 'b')}, 6) AS server_loss FROM m"""


@query("a3_merge_pushes", _merges_sql())
def _(spark, sf):
    """Pushes merged one by one, weighted by the reciprocals of their losses."""
    goal = np.array(GOAL)
    s = merge.ServerState(np.zeros(2), 0.5, lambda p: 0.5 * float(((p - goal) ** 2).sum()) + 0.5)
    out = []
    for k, g in enumerate(pushed(spark, sf), 1):
        a, b = s.merge(np.array(g, float))
        out.append((k, None if k == 1 else round(a, 6), None if k == 1 else round(b, 6), *[round(float(x), 6) for x in s.acc], round(s.loss, 6)))
    return spark.createDataFrame(out, "push int, w_server double, w_worker double, acc0 double, acc1 double, server_loss double")


@query("a5_async_sgd", f"WITH {PUSHES} SELECT CAST(push AS INTEGER) AS push, -0.5::DOUBLE * sum(x) OVER (ORDER BY push) AS p0, -0.5::DOUBLE * sum(y) OVER (ORDER BY push) AS p1 FROM p")
def _(spark, sf):
    s, out = merge.AsyncSGD(np.zeros(2), 0.5), []
    for k, g in enumerate(pushed(spark, sf), 1):
        s.apply(np.array(g, float))
        out.append((k, float(s.params[0]), float(s.params[1])))
    return spark.createDataFrame(out, "push int, p0 double, p1 double")


@query("a6_mean_gradient", "SELECT label, CAST(i - 1 AS INTEGER) AS pos, round(avg(embedding[i]::DOUBLE), 6) AS mean FROM embeddings, range(1, 65) t(i) GROUP BY 1, 2")
def _(spark, sf):
    e = tables.load(spark, sf, "embeddings", ["label", "embedding"])
    return merge.mean_vector(e, "label", F.col("embedding")).withColumn("mean", F.round("mean", 6))


@query("a12_gram_stats", f"WITH {TABULAR} SELECT split, count(*) AS n, round(sum(y * y), 4) AS yy, {', '.join(f'round(sum({e}), 4) AS {n}' for n, e in GRAM_TERMS)} FROM rows GROUP BY 1")
def _(spark, sf):
    g = merge.gram_stats(rows(spark, sf), ["x1", "x2", "x3"], "y", [F.col("split")])
    return g.withColumns({c: F.round(c, 4) for c in g.columns if c not in ("split", "n")})


#: k steps of full-batch descent on the sums; the oracle takes the same steps over rows' sums in SQL
K_STEPS = 5


def _descent_sql() -> str:
    d = 4
    g = lambda i, j: f"g{min(i, j)}{max(i, j)}"
    step = ", ".join(f"p{i} - 0.1::DOUBLE * ({' + '.join(f'{g(i, j)} * p{j}' for j in range(d))} - b{i}) / n AS p{i}" for i in range(d))
    loss = "(yy - 2 * (" + " + ".join(f"p{i} * b{i}" for i in range(d)) + ") + " + " + ".join(f"p{i} * {g(i, j)} * p{j}" for i in range(d) for j in range(d)) + ") / (2 * n)"
    return f"""WITH RECURSIVE {TABULAR}, s AS (SELECT count(*)::DOUBLE AS n, sum(y * y) AS yy, {', '.join(f'sum({e}) AS {n}' for n, e in GRAM_TERMS)} FROM rows WHERE split = 'train'),
d(k, p0, p1, p2, p3) AS (SELECT 0, 0::DOUBLE, 0::DOUBLE, 0::DOUBLE, 0::DOUBLE UNION ALL SELECT k + 1, {step} FROM d, s WHERE k < {K_STEPS})
SELECT k, round(p0, 6) AS p0, round(p1, 6) AS p1, round(p2, 6) AS p2, round(p3, 6) AS p3, round({loss}, 6) AS loss FROM d, s"""


@query("a12_descent_on_sums", _descent_sql())
def _(spark, sf):
    row = merge.gram_stats(rows(spark, sf).where("split = 'train'"), ["x1", "x2", "x3"], "y", [F.lit(1).alias("one")]).first()
    g, p, out = merge.Gram.of_row(row, 4), np.zeros(4), []
    for k in range(K_STEPS + 1):
        out.append((k, *[round(float(x), 6) for x in p], round(g.loss(p), 6)))
        p = p - 0.1 * g.gradient(p)
    return spark.createDataFrame(out, "k int, p0 double, p1 double, p2 double, p3 double, loss double")


def _zero_loss(n: int) -> str:
    return f"round(ln({n}::DOUBLE), 6)"


@query("a7_evaluate_start", f"SELECT count(*) AS n, {_zero_loss(4)} AS loss, round(avg(CASE WHEN lang = 'de' THEN 1.0::DOUBLE ELSE 0 END), 6) AS accuracy FROM documents WHERE doc_id % 20 >= 17")
def _(spark, sf):
    test = tables.text_rows(tables.load(spark, sf, "documents")).where("split = 'test'")
    model = Softmax(len(tables.LETTERS), 4)
    return evaluation(model, model.init(0), test).select("n", F.round("loss", 6).alias("loss"), F.round("accuracy", 6).alias("accuracy"))


#: parameters of the models; the two sizes of the published models are reached by width
def _sizes_sql() -> str:
    deep = lambda a, b, h: f"10 * {a} + (9 * {a} + 1) * {b} + ((s // 4) * (s // 4) * {b} + 1) * {h} + ({h} + 1) * 10"
    models = {"cnn": deep(16, 32, 757), "deep_cnn": deep(64, 128, 1750), "softmax": "(d + 1) * 10", "mlp": "(d + 1) * 32 + 33 * 10"}
    return "WITH e AS (SELECT max(len(embedding)) AS d, CAST(sqrt(max(len(embedding))) AS BIGINT) AS s FROM embeddings) " + " UNION ALL ".join(f"SELECT '{m}' AS model, CAST({n} AS BIGINT) AS parameters FROM e" for m, n in models.items())


@query("a10_model_sizes", _sizes_sql())
def _(spark, sf):
    """Parameters of the models on pictures of the table's width."""
    d = tables.load(spark, sf, "embeddings", ["embedding"]).agg(F.max(F.size("embedding"))).first()[0]
    cnn, deep = (Cnn(math.isqrt(d), c.k, c.filters, c.hidden) for c in (CNN_110K, CNN_990K))
    sizes = {"cnn": cnn.size, "deep_cnn": deep.size, "softmax": Softmax(d, 10).size, "mlp": Mlp(d, 10, 32).size}
    return spark.createDataFrame(list(sizes.items()), "model string, parameters long")


def _half_sql() -> str:
    """Half precision by arithmetic: eleven significant bits, in steps of 2^-24 below 2^-14, halves to even."""
    step = "pow(2.0::DOUBLE, greatest(floor(log2(greatest(abs(v), 1e-30::DOUBLE))), -14) - 10)"
    return f"""WITH e AS (SELECT vec_id, unnest(embedding)::DOUBLE AS v FROM embeddings), h AS (SELECT vec_id, v, round_even(v / {step}, 0) * {step} AS b FROM e)
SELECT vec_id, CAST(2 * count(*) AS BIGINT) AS packed_bytes, round(sum(b), 6) AS total, round(max(abs(v - b)), 9) AS largest_error FROM h GROUP BY 1"""


@query("c1_half_precision", _half_sql())
def _(spark, sf):
    e = tables.load(spark, sf, "embeddings", ["vec_id", "embedding"]).withColumn("packed", compress.pack_half(F.col("embedding")))
    back = e.withColumn("back", compress.unpack_half(F.col("packed")))
    total = F.aggregate(F.transform("back", lambda x: x.cast("double")), F.lit(0.0), lambda s, x: s + x)
    error = F.array_max(F.zip_with("embedding", "back", lambda a, b: F.abs(a.cast("double") - b.cast("double"))))
    return back.select("vec_id", F.length("packed").cast("long").alias("packed_bytes"), F.round(total, 6).alias("total"), F.round(error, 9).alias("largest_error"))


@query("c3_half_row_cap", "SELECT CAST(s_suppkey AS INTEGER) AS worker_id, CAST(floor((1073741824 * 0.5::DOUBLE - 2 * 990000 * 2) / 8192.0::DOUBLE) AS BIGINT) - CAST(floor((1073741824 * 0.5::DOUBLE - 2 * 990000 * 4) / 8192.0::DOUBLE) AS BIGINT) AS rows_gained FROM supplier")
def _(spark, sf):
    from tidegate.operators.sizing import row_cap

    s = tables.load(spark, sf, "supplier", ["s_suppkey"])
    mem = F.lit(2**30 * 0.5)
    return s.select(F.col("s_suppkey").cast("int").alias("worker_id"), (row_cap(mem, 4096, 990_000, "fp16") - row_cap(mem, 4096, 990_000, "fp32")).alias("rows_gained"))


@query("p2_prefetch_time", "SELECT l_suppkey AS worker_id, round(greatest(sum(l_quantity), sum(l_extendedprice) / 1000), 4) AS hidden, round(sum(l_quantity) + sum(l_extendedprice) / 1000, 4) AS plain FROM lineitem GROUP BY 1")
def _(spark, sf):
    s = tables.load(spark, sf, "lineitem", ["l_suppkey", "l_quantity", "l_extendedprice"]).groupBy(F.col("l_suppkey").alias("worker_id")).agg(F.sum("l_quantity").alias("a"), (F.sum("l_extendedprice") / 1000).alias("b"))
    return s.select("worker_id", F.round(iteration_time(F.col("a"), F.col("b")), 4).alias("hidden"), F.round(iteration_time(F.col("a"), F.col("b"), False), 4).alias("plain"))


@query("t2_patience", """WITH l AS (SELECT worker_id, iter, loss FROM (SELECT CAST(user_id % 12 AS INTEGER) AS worker_id, row_number() OVER (PARTITION BY user_id % 12 ORDER BY ts, event_id) AS iter, value AS loss FROM events)),
b AS (SELECT *, min(loss) OVER (PARTITION BY worker_id ORDER BY iter) AS best FROM l), g AS (SELECT worker_id, iter, count(*) OVER (PARTITION BY worker_id, best ORDER BY iter) - 1 AS since FROM b)
SELECT worker_id, min(iter) AS stop_at FROM g WHERE since >= 25 GROUP BY 1""")
def _(spark, sf):
    from pyspark.sql import Window

    from tidegate.plans.suite_gate import losses

    by = Window.partitionBy("worker_id").orderBy("iter")
    raw = losses(spark, sf).select("worker_id", "iter", ((F.col("loss") - 0.1 - 2.2 * F.exp(-F.col("iter") / 40.0)) / 0.002).alias("loss")).withColumn("loss", F.round("loss", 2))
    since = raw.withColumn("best", F.min("loss").over(by)).withColumn("since", F.count(F.lit(1)).over(Window.partitionBy("worker_id", "best").orderBy("iter")) - 1)
    return since.where("since >= 25").groupBy("worker_id").agg(F.min("iter").alias("stop_at"))
