"""Quality by hierarchical empirical Bayes.

A document's own evidence is the log odds of a logistic regression on the make-up of its bytes (shares of each ASCII
character and of the rest, length of words and lines) and how much its words and lines repeat, fitted on a bounded sample of
labelled rows: at most `max_rows`, those with the least hash of doc_id. All else is over all rows. Grouped sums of the
documents' probabilities give hosts, and paths within hosts, a mean; a path's is drawn towards its host's and a host's towards
the whole's, by the noise within groups against the spread between them (nested analysis of variance), so sparse sites say
little. For each document its own probability is taken out of the sums first, so it is not counted twice: a path with no
other document says what its host says. The posterior log odds are the evidence plus what the path's posterior differs from
the whole's, in log odds.

Defined results: null and empty texts are rejected (posterior 0) and say nothing of their site; a null host or path is a group
of its own; with no usable labels the evidence is 0 and everything with words is kept; repeated rows count each time; an
empty table gives no rows; extra columns are kept by good_documents, whatever their names, and left out by quality_table.
"""

from __future__ import annotations

from dataclasses import dataclass
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tidegate.llm.common import arrow_function, as_bytes, give_back, stored

BROADCAST_SITES = 200_000  # paths (a name and some numbers each) that are sent to all; more are joined by a shuffle
FEATURES = 136
LOW = 0.001  # probabilities are kept this far from 0 and 1
LEAST, MOST = 1.0, 1e6  # limits of the level above's weight


def features(text: bytes) -> np.ndarray:
    """Square roots of byte shares (ASCII one by one, all other bytes together), lengths, and how much words repeat: the share
    of words that equal the one before, of different words, and of different lines."""
    n = len(text)
    if not n:
        return np.zeros(FEATURES)
    said, rows = text.split(), text.split(b"\n")
    again = sum(map(eq, said, said[1:])) / max(1, len(said))
    repeats = [again, again > 0.2, np.log1p(len(set(said))) / np.log1p(len(said) + 1), len(set(rows)) / len(rows)]
    count = np.bincount(np.frombuffer(text, np.uint8), minlength=256).astype(float)
    words, lines = count[[9, 10, 11, 12, 13, 32]].sum() + 1, count[10] + 1
    upper = count[65:91].sum()
    return np.concatenate((np.sqrt(count[:128] / n), [np.sqrt(count[128:].sum() / n), np.log1p(n / words) / 4, np.log1p(words / lines) / 8, upper / max(1.0, upper + count[97:123].sum())], repeats))


@arrow_function("array<double>")
def feature_rows(text: pa.Array) -> pa.Array:
    return pa.array([features(t).tolist() for t in as_bytes(text)], pa.list_(pa.float64()))


def fit_logistic(x: np.ndarray, y: np.ndarray, steps: int = 60, ridge: float = 1e-3) -> np.ndarray:
    """Weights with the constant last, by Newton steps on the ridge-penalised likelihood, classes weighted alike."""
    x = np.hstack((x, np.ones((len(x), 1))))
    w = np.zeros(x.shape[1])
    if not len(y) or y.min() == y.max():
        return w
    share = np.where(y == 1, 0.5 / y.mean(), 0.5 / (1 - y.mean()))
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        grad = x.T @ (share * (p - y)) / len(y) + ridge * w
        curve = (x * (share * p * (1 - p))[:, None]).T @ x / len(y) + (ridge + 1e-9) * np.eye(len(w))
        step = np.linalg.solve(curve, grad)
        w -= step
        if np.abs(step).max() < 1e-7:
            break
    return w


def fit(docs: DataFrame, labels: DataFrame, max_rows: int = 8000) -> np.ndarray:
    """Weights from at most max_rows labelled documents."""
    few = labels.select(F.col("doc_id").alias("_doc"), F.col("quality").cast("double").alias("_y")).where("_doc is not null and _y in (0, 1)")
    few = few.orderBy(F.xxhash64("_doc"), "_doc", "_y").limit(max_rows)  # bounded, so it may be sent to all
    seen = docs.select("doc_id", "text").join(F.broadcast(few), F.col("doc_id") == F.col("_doc"))
    rows = seen.select(F.xxhash64("doc_id", "text").alias("_h"), "_y", feature_rows("text").alias("_x")).orderBy("_h", "_y").limit(max_rows).collect()
    return fit_logistic(np.array([r["_x"] for r in rows]).reshape(len(rows), -1 if rows else FEATURES), np.array([r["_y"] for r in rows]))


def evidence(text: Column, weights: np.ndarray) -> Column:
    """Log odds that a text is good; null where it has no bytes."""
    w, constant = weights[:-1], float(weights[-1])

    @F.arrow_udf("double")
    def score(column: pa.Array) -> pa.Array:
        out = pa.array([float(np.clip(features(t) @ w + constant, -30, 30)) if t else None for t in as_bytes(column)], pa.float64())
        give_back()
        return out

    return score(text)


@dataclass(frozen=True)
class Sites:
    """A row a path (host, path, n, s, host_n, host_s: documents and sums of their probabilities), and the whole."""

    table: DataFrame
    n: int
    s: float
    host_weight: float  # documents that the whole counts for against a host's own, and a host against a path's
    path_weight: float


def site_sums(scored: DataFrame) -> Sites:
    """scored: host, path and p, null where a document says nothing.

    Sums are pre-aggregated and stored; only their moments reach the driver, as one row a level.
    """
    total = lambda c: F.coalesce(F.sum(c), F.lit(0.0))
    paths = stored(scored.groupBy("host", "path").agg(F.count("p").alias("n"), total("p").alias("s"), total(F.col("p") * F.col("p")).alias("q")), "sites")
    hosts = paths.groupBy("host").agg(F.sum("n").alias("host_n"), F.sum("s").alias("host_s"), F.sum("q").alias("host_q"))
    both = paths.join(hosts.select(F.col("host").alias("of"), "host_n", "host_s"), F.col("host").eqNullSafe(F.col("of"))).drop("of")
    h = hosts.where("host_n > 0").agg(
        F.count(F.lit(1)).alias("groups"), F.sum("host_n").alias("n"), F.sum("host_s").alias("s"), F.sum(F.col("host_s") ** 2 / F.col("host_n")).alias("means"),
        F.sum("host_q").alias("q"), F.sum(F.col("host_n").cast("double") ** 2).alias("squares"),
    ).first()
    p = both.where("n > 0").agg(F.count(F.lit(1)).alias("groups"), F.sum(F.col("s") ** 2 / F.col("n")).alias("means"), F.sum(F.col("n").cast("double") ** 2 / F.col("host_n")).alias("squares")).first()
    if not h["groups"]:
        return Sites(both, 0, 0.0, MOST, MOST)
    # host level: groups are hosts within the whole; path level: paths within hosts
    host_weight = weight(h["n"], h["q"], h["means"], h["s"] ** 2 / h["n"], h["groups"], 1, h["n"] - h["squares"] / h["n"])
    path_weight = weight(h["n"], h["q"], p["means"], h["means"], p["groups"], h["groups"], h["n"] - p["squares"])
    return Sites(both, h["n"], h["s"], host_weight, path_weight)


def weight(n: int, q: float, means: float, above: float, groups: int, parents: int, room: float) -> float:
    """Noise within groups over variance between them: so many documents does the level above count for.

    q: sum of squares; means, above: sums of size times squared mean of the groups and of the level above.
    """
    noise = max(0.0, q - means) / max(1, n - groups)
    between = max(0.0, (means - above - (groups - parents) * noise) / room) if room > 1e-9 else 0.0
    return float(min(max(noise / between, LEAST), MOST)) if between > 1e-12 else MOST


def scored(docs: DataFrame, keep: Column, weights: np.ndarray, host: str, path: str) -> DataFrame:
    """(row, host, path, evidence, p) of each document, written once; row is the `keep` struct."""
    said = docs.select(keep.alias("row"), F.col(host).alias("host"), F.col(path).alias("path"), evidence(F.col("text"), weights).alias("evidence"))
    return stored(said.withColumn("p", 1 / (1 + F.exp(-F.col("evidence")))), "evidence")


def judged(said: DataFrame, sites: Sites) -> DataFrame:
    """said with host_posterior, path_posterior and posterior, each without the document's own probability."""
    table = sites.table.select(F.col("host").alias("_host"), F.col("path").alias("_path"), "n", "s", "host_n", "host_s")
    if table.count() <= BROADCAST_SITES:
        table = F.broadcast(table)
    j = said.join(table, F.col("host").eqNullSafe(F.col("_host")) & F.col("path").eqNullSafe(F.col("_path")), "left")
    own, one = F.coalesce("p", F.lit(0.0)), F.when(F.col("p").isNull(), 0).otherwise(1)
    inside = lambda c: F.least(F.greatest(c, F.lit(LOW)), F.lit(1 - LOW))
    mean = inside((F.lit(sites.s) - own + 0.5) / (F.lit(sites.n) - one + 1))
    hosted = (F.col("host_s") - own + sites.host_weight * mean) / (F.col("host_n") - one + sites.host_weight)
    pathed = (F.col("s") - own + sites.path_weight * F.col("host_posterior")) / (F.col("n") - one + sites.path_weight)
    odds = lambda c: F.log(inside(c) / (1 - inside(c)))
    j = j.withColumn("mean", mean).withColumn("host_posterior", hosted).withColumn("path_posterior", pathed)
    shift = odds(F.col("path_posterior")) - odds(F.col("mean"))
    return j.withColumn("posterior", F.coalesce(1 / (1 + F.exp(-(F.col("evidence") + shift))), F.lit(0.0)))


def quality_table(docs: DataFrame, labels: DataFrame, host: str = "source", path: str = "lang", threshold: float = 0.5, max_rows: int = 8000) -> DataFrame:
    """doc_id, evidence, host_posterior, path_posterior, posterior and keep of each document."""
    said = scored(docs, F.struct("doc_id"), fit(docs, labels, max_rows), host, path)
    j = judged(said, site_sums(said))
    return j.select("row.doc_id", "evidence", "host_posterior", "path_posterior", "posterior", (F.col("posterior") >= threshold).alias("keep"))


def good_documents(docs: DataFrame, labels: DataFrame, host: str = "source", path: str = "lang", threshold: float = 0.5, max_rows: int = 8000) -> DataFrame:
    """The documents that are kept, with their own columns."""
    said = scored(docs, F.struct(*docs.columns), fit(docs, labels, max_rows), host, path)
    return judged(said, site_sums(said)).where(F.col("posterior") >= threshold).select("row.*")
