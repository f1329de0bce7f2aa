"""Column functions of the engine; register() makes them callable from SQL."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

C = F.col


def predict_time(n_rows, batch_rows, epochs, sec_per_batch, steps: str = "ratio", row_cost=None) -> Column:
    """Training time: time of a mini-batch, times epochs, times mini-batches.

    steps "ratio" takes rows / batch as it is, "ceil" whole mini-batches. row_cost adds a cost a row (affine model).
    """
    n, b, e, k = (x if isinstance(x, Column) else F.lit(x) for x in (n_rows, batch_rows, epochs, sec_per_batch))
    count = n.cast("double") / b
    t = k * e * (F.ceil(count) if steps == "ceil" else count)
    return t if row_cost is None else t + e * (row_cost if isinstance(row_cost, Column) else F.lit(row_cost)) * n


def z_score(loss: Column, mu: Column, sigma: Column) -> Column:
    """Deviations of a loss from the mean; null where sigma is 0 or unknown."""
    return F.try_divide(loss - mu, sigma)


def relaxed_cut(z_cut, relax, times) -> Column:
    """The gate's cut after it has been relaxed so many times."""
    z, r, t = (x if isinstance(x, Column) else F.lit(float(x)) for x in (z_cut, relax, times))
    return z * F.pow(1 - r, t)


def normal_tail(z: Column) -> Column:
    """Share of a normal distribution below z.

    exp(-z^2/2) times a rational function of |z|; the error is below 1e-14 or so.
    """
    x = F.abs(z)
    # fixed values: numerator and denominator, highest power first, and the continued fraction's start for large |z|
    top = (0.0352624965998911, 0.700383064443688, 6.37396220353165, 33.912866078383, 112.079291497871, 221.213596169931, 220.206867912376)
    low = (0.0883883476483184, 1.75566716318264, 16.064177579207, 86.7807322029461, 296.564248779674, 637.333633378831, 793.826512519948, 440.413735824752)

    def poly(values):
        out = F.lit(values[0])
        for v in values[1:]:
            out = out * x + v
        return out

    density = F.exp(-x * x / 2)
    near = density * poly(top) / poly(low)
    far = density / (x + 1 / (x + 2 / (x + 3 / (x + 4 / (x + 0.65))))) / 2.506628274631
    below = F.when(x < 7.07106781186547, near).otherwise(far)
    return F.when(z <= 0, below).otherwise(1 - below)


def z_for_tail(p: Column) -> Column:
    """The z below which a share p of a normal distribution lies, by a rational function in three ranges (1e-9)."""
    # fixed values of the approximation
    a = (-3.969683028665376e01, 2.209460984245205e02, -2.759285104469687e02, 1.383577518672690e02, -3.066479806614716e01, 2.506628277459239e00)
    b = (-5.447609879822406e01, 1.615858368580409e02, -1.556989798598866e02, 6.680131188771972e01, -1.328068155288572e01, 1.0)
    c = (-7.784894002430293e-03, -3.223964580411365e-01, -2.400758277161838e00, -2.549732539343734e00, 4.374664141464968e00, 2.938163982698783e00)
    d = (7.784695709041462e-03, 3.224671290700398e-01, 2.445134137142996e00, 3.754408661907416e00, 1.0)

    def poly(values, x):
        out = F.lit(values[0])
        for v in values[1:]:
            out = out * x + v
        return out

    def tail(q):
        s = F.sqrt(-2 * F.ln(q))
        return poly(c, s) / poly(d, s)

    m = p - 0.5
    middle = m * poly(a, m * m) / poly(b, m * m)
    return F.when((p <= 0) | (p >= 1), F.lit(None).cast("double")).when(p < 0.02425, tail(p)).when(p > 0.97575, -tail(1 - p)).otherwise(middle)


def arithmetic_hash(key: Column) -> Column:
    """A hash that DuckDB can repeat: 0 to 2^32 - 1."""
    return F.pmod(F.pmod(key.cast("long"), F.lit(2147483647)) * 2654435761, F.lit(4294967296))


def loss_weighted_mix(a: Column, b: Column, loss_a: Column, loss_b: Column) -> Column:
    """Element-wise mean of two arrays, weighted by the reciprocals of their losses."""
    wa, wb = 1 / loss_a, 1 / loss_b
    return F.zip_with(a, b, lambda x, y: (wa * x + wb * y) / (wa + wb))


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def squared_norm(a: Column) -> Column:
    return dot(a, a)


def cosine(a: Column, b: Column) -> Column:
    return F.try_divide(dot(a, b), F.sqrt(squared_norm(a)) * F.sqrt(squared_norm(b)))


def iteration_time(train: Column, fetch: Column, prefetch: bool = True) -> Column:
    """Time of an iteration: fetching the next data hides behind training when prefetched."""
    return F.greatest(train, fetch) if prefetch else train + fetch


def register(spark: SparkSession) -> None:
    """SQL functions predict_time, relaxed_cut, normal_tail_approx and iteration_time for this session."""
    for text in (
        "predict_time(n DOUBLE, b DOUBLE, e DOUBLE, k DOUBLE) RETURNS DOUBLE RETURN k * e * n / b",
        "relaxed_cut(z DOUBLE, relax DOUBLE, times DOUBLE) RETURNS DOUBLE RETURN z * pow(1 - relax, times)",
        "iteration_time(train DOUBLE, fetch DOUBLE, prefetch BOOLEAN) RETURNS DOUBLE RETURN CASE WHEN prefetch THEN greatest(train, fetch) ELSE train + fetch END",
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {text}")
