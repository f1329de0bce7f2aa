"""Rows and mini-batch size for each worker, so that all train about as long as the cluster's median."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tidegate.functions.scalar import predict_time

#: mini-batch sizes tried: powers of two
LOW_EXP, HIGH_EXP = 1, 8


def fit_sec_per_batch(obs: DataFrame, k_source: str = "latest", alpha: float = 0.5) -> DataFrame:
    """worker_id, sec_per_batch and t_train from observed times. k_source: latest or initial run, or ewma over runs."""
    k = obs.withColumn("_k", F.col("t_train") * F.col("batch_rows") / (F.col("epochs") * F.col("n_rows")))
    if k_source == "ewma":
        rows = k.groupBy("worker_id").agg(F.sort_array(F.collect_list(F.struct("iter", "_k", "t_train"))).alias("r"))
        first = F.col("r")[0]
        fold = F.aggregate(F.slice("r", 2, F.greatest(F.size("r") - 1, F.lit(0))), first["_k"], lambda s, x: (1 - alpha) * s + alpha * x["_k"])
        return rows.select("worker_id", fold.alias("sec_per_batch"), F.element_at("r", -1)["t_train"].alias("t_train"))
    pick = F.max_by if k_source == "latest" else F.min_by
    return k.groupBy("worker_id").agg(pick("_k", "iter").alias("sec_per_batch"), pick("t_train", "iter").alias("t_train"))


def iqr_bounds(df: DataFrame, col: str, k: float = 1.5, by: list[str] | None = None, quartiles: str = "linear") -> DataFrame:
    """q1, q3, iqr, lo and hi of a column, by groups if wished. quartiles: "linear" between rows, "nearest" row, or
    "approximate" for very many rows."""
    q = {
        "linear": lambda: F.percentile(col, F.array(F.lit(0.25), F.lit(0.75))),
        "nearest": lambda: F.array(*[F.expr(f"percentile_disc({x}) WITHIN GROUP (ORDER BY `{col}`)") for x in (0.25, 0.75)]),
        "approximate": lambda: F.percentile_approx(col, [0.25, 0.75], 10_000),
    }[quartiles]()
    out = df.groupBy(*(by or [])).agg(q.alias("_q"))
    out = out.withColumns({"q1": F.col("_q")[0], "q3": F.col("_q")[1]}).withColumn("iqr", F.col("q3") - F.col("q1"))
    return out.withColumns({"lo": F.col("q1") - k * F.col("iqr"), "hi": F.col("q3") + k * F.col("iqr")}).drop("_q")


def flag_outliers(df: DataFrame, col: str = "t_train", k: float = 1.5, quartiles: str = "linear") -> DataFrame:
    """df with the bounds and `status`: straggler above them, underused below, else normal."""
    t = F.col(col)
    status = F.when(t > F.col("hi"), "straggler").when(t < F.col("lo"), "underused").otherwise("normal")
    return df.crossJoin(F.broadcast(iqr_bounds(df, col, k, quartiles=quartiles))).withColumn("status", status)  # one row of bounds


def target_time(df: DataFrame, col: str = "t_train") -> DataFrame:
    """One row: the median time."""
    return df.agg(F.median(col).alias("t_target"))


def _time(n: Column, k: Column, epochs: Column, b: Column) -> Column:
    return predict_time(n, b, epochs, k)


def search_rows(target: Column, k: Column, epochs: Column, batch_rows: Column, cap: Column, max_log: int = 40) -> Column:
    """Most rows, at most cap, whose time at this batch size does not pass the target: a binary search."""
    return _searched_rows(target, k, epochs, batch_rows, cap, max_log)["lo"]


def _searched_rows(target: Column, k: Column, epochs: Column, batch_rows: Column, cap: Column, max_log: int = 40) -> Column:
    """struct<lo, hi, probes>: where the binary search ends, and how many times it looked."""
    zero = F.struct(F.lit(0).cast("long").alias("lo"), cap.cast("long").alias("hi"), F.lit(0).alias("probes"))

    def halve(s, _):
        mid = ((s["lo"] + s["hi"] + 1) / 2).cast("long")
        fits = (_time(mid, k, epochs, batch_rows) <= target) & (mid <= s["hi"])
        looks = s["probes"] + F.when(s["lo"] < s["hi"], 1).otherwise(0)
        return F.struct(F.when(fits, mid).otherwise(s["lo"]).alias("lo"), F.when(fits, s["hi"]).otherwise(F.least(s["hi"], mid - 1)).alias("hi"), looks.alias("probes"))

    steps = F.least(F.ceil(F.log2(F.greatest(cap, F.lit(1)).cast("double"))) + 1, F.lit(max_log)).cast("int")
    return F.aggregate(F.sequence(F.lit(1), F.greatest(steps, F.lit(1))), zero, halve)


def search_probes(workers: DataFrame, total_rows: int, epochs: int = 1, prefer: str = "current") -> DataFrame:
    """worker_id and `probes`: how many times the dual search looks at a predicted time for a worker, of batch sizes and of rows."""
    cap, e, k, t = F.least(F.col("cap_rows"), F.lit(total_rows)).cast("long"), F.lit(epochs), F.col("sec_per_batch"), F.col("t_target")
    sized = workers.withColumn("_cap", cap).withColumn("_b", search_batch(t, k, e, F.col("_cap"), F.col("batch_rows"), prefer))
    outer = (HIGH_EXP - LOW_EXP + 1).bit_length() - 1
    return sized.select("worker_id", (_searched_rows(t, k, e, F.col("_b"), F.col("_cap"))["probes"] + outer).alias("probes"))


def _feasible(target: Column, k: Column, epochs: Column, b: Column, cap: Column) -> Column:
    """Whether the cap's rows at this batch size reach the target: false from some batch size on."""
    return _time(cap, k, epochs, b) >= target


def search_batch(target: Column, k: Column, epochs: Column, cap: Column, current: Column, prefer: str = "current") -> Column:
    """Batch size out of the powers of two: the largest that reaches the target within the cap, by binary search on the
    exponent; "current" keeps the worker's own where it reaches it, "smallest" takes the least."""
    zero = F.struct(F.lit(LOW_EXP).alias("lo"), F.lit(HIGH_EXP).alias("hi"))

    def halve(s, _):
        mid = ((s["lo"] + s["hi"] + 1) / 2).cast("int")
        ok = _feasible(target, k, epochs, F.pow(F.lit(2.0), mid), cap)
        open_ = s["lo"] < s["hi"]
        return F.struct(F.when(open_ & ok, mid).otherwise(s["lo"]).alias("lo"), F.when(open_ & ~ok, mid - 1).otherwise(s["hi"]).alias("hi"))

    largest = F.aggregate(F.sequence(F.lit(1), F.lit(4)), zero, halve, lambda s: F.pow(F.lit(2.0), s["lo"]).cast("int"))
    if prefer == "largest":
        return largest
    if prefer == "smallest":
        return F.lit(2**LOW_EXP)
    return F.when(_feasible(target, k, epochs, current, cap), current).otherwise(F.least(current, largest)).cast("int")


def dual_search(workers: DataFrame, total_rows: int, epochs: int = 1, prefer: str = "current", min_rows: int = 1) -> DataFrame:
    """worker_id, batch_rows, n_rows, t_pred and `reached` for workers with sec_per_batch, t_target, batch_rows and cap_rows.

    One projection: the outer search finds the batch size, the inner one the rows.
    """
    cap = F.least(F.col("cap_rows"), F.lit(total_rows)).cast("long")
    e, k, t = F.lit(epochs), F.col("sec_per_batch"), F.col("t_target")
    sized = workers.withColumn("_cap", cap).withColumn("_b", search_batch(t, k, e, F.col("_cap"), F.col("batch_rows"), prefer))
    rows = search_rows(t, k, e, F.col("_b"), F.col("_cap"))
    sized = sized.withColumn("_n", F.least(F.col("_cap"), F.greatest(rows, F.lit(min_rows).cast("long"), F.lit(1).cast("long"))))
    pred = _time(F.col("_n"), k, e, F.col("_b"))
    reached = F.abs(pred - t) <= k * e / F.col("_b") + 1e-12
    return sized.select("worker_id", F.col("_b").cast("int").alias("batch_rows"), F.col("_n").alias("n_rows"), pred.alias("t_pred"), reached.alias("reached"))


def dual_search_brute(workers: DataFrame, total_rows: int, epochs: int = 1) -> DataFrame:
    """The same allocation by trying every batch size in closed form, largest that reaches the target first."""
    cap = F.least(F.col("cap_rows"), F.lit(total_rows)).cast("long")
    tried = workers.withColumn("_cap", cap).withColumn("_b", F.explode(F.array(*[F.lit(2**e) for e in range(LOW_EXP, HIGH_EXP + 1)])))
    want = F.floor(F.col("t_target") * F.col("_b") / (F.col("sec_per_batch") * epochs) + 1e-9).cast("long")
    ok = _feasible(F.col("t_target"), F.col("sec_per_batch"), F.lit(epochs), F.col("_b"), F.col("_cap"))
    tried = tried.withColumn("_n", F.least("_cap", F.greatest(want, F.lit(1).cast("long")))).withColumn("_ok", ok)
    best = tried.groupBy("worker_id").agg(F.max_by(F.struct("_b", "_n", "sec_per_batch"), F.when(F.col("_ok"), F.col("_b")).otherwise(-F.col("_b"))).alias("r"))
    r = F.col("r")
    return best.select("worker_id", r["_b"].cast("int").alias("batch_rows"), r["_n"].alias("n_rows"), predict_time(r["_n"], r["_b"], epochs, r["sec_per_batch"]).alias("t_pred"))


PRECISION_BYTES = {"fp32": 4, "fp16": 2, "mixed": 2}


def row_cap(mem_bytes: Column, row_bytes, model_params, precision: str = "mixed", activation: float = 1.0) -> Column:
    """Rows that fit a worker's memory beside its model and gradient; activations take `activation` times a row."""
    model = 2 * model_params * PRECISION_BYTES[precision]
    return F.greatest(F.floor((mem_bytes - model) / (row_bytes * (1 + activation))), F.lit(0)).cast("long")


def with_caps(workers: DataFrame, row_bytes: int = 4096, model_params: int = 110_000, precision: str = "mixed", share: float = 0.5) -> DataFrame:
    """workers with cap_rows from `share` of their memory."""
    return workers.withColumn("cap_rows", row_cap(F.col("mem_gb") * share * 2**30, row_bytes, model_params, precision))


def initial_allocation(workers: DataFrame, n0: int = 2500, b0: int = 16) -> DataFrame:
    """One size for all, bounded by the weakest memory. workers has cap_rows."""
    least = workers.agg(F.min("cap_rows").alias("_least"))
    n = F.least(F.lit(n0), F.col("_least")).cast("long")
    return workers.crossJoin(F.broadcast(least)).select("worker_id", n.alias("n_rows"), F.lit(b0).alias("batch_rows"), predict_time(n, b0, 1, F.col("sec_per_batch")).alias("t_pred"))


def static_allocation(workers: DataFrame, n_rows: int, batch_rows: int) -> DataFrame:
    """Baseline: the same rows and batch size for all, whatever they can do."""
    return workers.select("worker_id", F.lit(n_rows).cast("long").alias("n_rows"), F.lit(batch_rows).alias("batch_rows"), predict_time(n_rows, batch_rows, 1, F.col("sec_per_batch")).alias("t_pred"))


def benchmark_workers(workers: DataFrame, probe_rows: int = 2500, batch_rows: int = 16, epochs: int = 1) -> DataFrame:
    """Baseline sizing: each worker is timed on a probe at every batch size before training; `cost` is the time it takes."""
    tried = workers.withColumn("b", F.explode(F.array(*[F.lit(2**e) for e in range(LOW_EXP, HIGH_EXP + 1)])))
    timed = tried.withColumn("t", predict_time(probe_rows, F.col("b"), epochs, F.col("sec_per_batch")))
    return timed.groupBy("worker_id").agg(F.max_by("t", F.when(F.col("b") == batch_rows, 1).otherwise(0)).alias("t_train"), F.sum("t").alias("cost"), F.count(F.lit(1)).alias("probes"))


def reallocate(obs: DataFrame, caps: DataFrame, total_rows: int, resize: str = "outliers", k_source: str = "latest", prefer: str = "current", epochs: int = 1) -> DataFrame:
    """A new allocation from observed times: outliers (or all) get the sizes that reach the median time.

    obs: worker_id, iter, n_rows, batch_rows, epochs, t_train. caps: worker_id, cap_rows.
    """
    latest = obs.groupBy("worker_id").agg(F.max_by("n_rows", "iter").alias("old_n"), F.max_by("batch_rows", "iter").alias("batch_rows"))
    fitted = fit_sec_per_batch(obs, k_source).join(latest, "worker_id")
    flagged = flag_outliers(fitted).crossJoin(F.broadcast(target_time(fitted)))  # one row
    sized = dual_search(flagged.join(caps.select("worker_id", "cap_rows"), "worker_id"), total_rows, epochs, prefer).withColumnsRenamed({"batch_rows": "new_b", "n_rows": "new_n", "t_pred": "new_t"})
    j = flagged.join(sized, "worker_id")
    change = F.lit(True) if resize == "all" else F.col("status") != "normal"
    pick = lambda new, old: F.when(change, F.col(new)).otherwise(F.col(old))
    return j.select("worker_id", "status", pick("new_n", "old_n").cast("long").alias("n_rows"), pick("new_b", "batch_rows").cast("int").alias("batch_rows"), pick("new_t", "t_train").alias("t_pred"), "t_target")


def with_buckets(df: DataFrame, key: Column, buckets: int, seed: int = 42, skew: Column | None = None) -> DataFrame:
    """df with `bucket`, below `buckets`, by a hash of key. With `skew`, a value of few kinds such as a label, two rows of five
    lie in buckets that their value has in proportion to its rows, the others anywhere, so that neighbouring buckets hold
    few kinds for the most part, and none lacks one."""
    from tidegate.functions.scalar import arithmetic_hash

    h = arithmetic_hash(key * 1009 + seed)
    if skew is None:
        return df.withColumn("bucket", F.pmod(h, F.lit(buckets)).cast("long"))
    regions = _regions(df, skew, buckets)
    tagged = df.withColumn("_label", skew).join(F.broadcast(regions), F.col("_label").eqNullSafe(F.col("_skew")))  # a row a label
    own = F.col("_lo") + F.pmod(h, F.col("_width"))
    anywhere = F.pmod(F.floor(h / 7), F.lit(buckets))
    return tagged.withColumn("bucket", F.when(F.pmod(key, F.lit(5)) < 2, own).otherwise(anywhere).cast("long")).drop("_label", "_skew", "_lo", "_width")


def _regions(df: DataFrame, skew: Column, buckets: int) -> DataFrame:
    """(_skew, _lo, _width): neighbouring buckets of each value, in proportion to its rows."""
    before = Window.orderBy("_skew").rowsBetween(Window.unboundedPreceding, 0)  # a row a label
    counts = df.groupBy(skew.alias("_skew")).agg(F.count(F.lit(1)).alias("_n")).withColumns({"_to": F.sum("_n").over(before), "_of": F.sum("_n").over(Window.partitionBy())})
    lo, hi = (F.floor(c * buckets / F.col("_of")) for c in (F.col("_to") - F.col("_n"), F.col("_to")))
    return counts.select("_skew", F.least(lo, F.lit(buckets - 1)).alias("_lo"), F.greatest(hi - lo, F.lit(1)).alias("_width"))


def owned_buckets(alloc: DataFrame, buckets: int) -> DataFrame:
    """alloc (worker_id, n_rows, batch_rows) with a row for each bucket of a worker: neighbouring ones, one at least and the others in
    proportion to its rows. `buckets` must be no fewer than the workers."""
    every = Window.orderBy("worker_id").rowsBetween(Window.unboundedPreceding, 0)  # a row a worker
    shares = alloc.select("worker_id", "n_rows", "batch_rows", F.sum("n_rows").over(every).alias("_upto"), F.sum("n_rows").over(Window.partitionBy()).alias("_all"), F.row_number().over(Window.orderBy("worker_id")).alias("_no"), F.count(F.lit(1)).over(Window.partitionBy()).alias("_w"))
    edge = lambda c, no: F.floor(c * (buckets - F.col("_w")) / F.col("_all")) + no
    return shares.select("worker_id", "n_rows", "batch_rows", F.explode(F.sequence(edge(F.col("_upto") - F.col("n_rows"), F.col("_no") - 1), edge(F.col("_upto"), F.col("_no")) - 1)).alias("bucket"))


def deal_rows(df: DataFrame, key: Column, alloc: DataFrame, iteration: int = 0, seed: int = 42, skew: Column | None = None, buckets: int | None = None, counts: DataFrame | None = None) -> DataFrame:
    """df's rows that go to a worker in this iteration, with worker_id, pos and batch_no.

    A row's bucket is a hash of its key and the iteration; with `skew`, a value of few kinds such as a label, every value has
    buckets of its own in proportion to its rows, so that shards hold few of them. Workers own neighbouring buckets, at least one each, in
    proportion to their rows. Within a worker, rows are numbered by hash. Where the workers ask for more rows than there are, each
    gets its share of them. buckets: by default 1024, or 64 a worker if that is more.

    With `counts` (bucket, _rows), df already has a `bucket`, such as one that it is stored by: then buckets go round the
    workers by iteration, and of df only those that are dealt are read.
    """
    from tidegate.functions.scalar import arithmetic_hash

    if buckets is None:
        buckets = max(1024, 64 * alloc.count())  # a row a worker
    tagged = df.withColumn("_h", arithmetic_hash(key * 1009 + (iteration * 31 + seed)))
    turn = lambda c: c
    if counts is not None:
        turn = lambda c: F.pmod(c + iteration * (buckets // 3 + 1), F.lit(buckets))
    elif skew is None:
        tagged = tagged.withColumn("bucket", F.pmod("_h", F.lit(buckets)).cast("long"))
    else:
        tagged = tagged.withColumn("_label", skew).join(F.broadcast(_regions(df, skew, buckets)), F.col("_label").eqNullSafe(F.col("_skew")))
        tagged = tagged.withColumn("bucket", F.col("_lo") + F.pmod("_h", F.col("_width"))).drop("_label", "_skew", "_lo", "_width")
    owned = owned_buckets(alloc, buckets).withColumnRenamed("bucket", "_place")
    # buckets are counted first, and a worker takes no more of its buckets than its rows need: the rest is not read or shuffled
    counted = tagged.groupBy("bucket").agg(F.count(F.lit(1)).alias("_rows")) if counts is None else counts
    first = Window.partitionBy("worker_id").orderBy("_place").rowsBetween(Window.unboundedPreceding, -1)
    taken = counted.withColumn("_place", turn(F.col("bucket"))).join(F.broadcast(owned), "_place").withColumn("_before", F.coalesce(F.sum("_rows").over(first), F.lit(0)))
    taken = taken.where(F.col("_before") < F.col("n_rows")).select("bucket", "_place", "worker_id", "n_rows", "batch_rows")
    tagged = tagged.join(F.broadcast(taken), "bucket")  # at most `buckets` rows
    w = Window.partitionBy("worker_id").orderBy("_place", "_h", key)
    numbered = tagged.withColumn("pos", F.row_number().over(w).cast("long") - 1).where(F.col("pos") < F.col("n_rows"))
    return numbered.withColumn("batch_no", F.floor(F.col("pos") / F.col("batch_rows")).cast("long")).drop("_h", "_place", "n_rows", "batch_rows")
