"""Nearest neighbours by an inverted file of coarse centroids with product-quantised residuals.

Fit     centroids and codebooks by k-means on a bounded sample: at most `sample` vectors, those with the least hash of id.
Index   every vector goes to its nearest list and is stored with its code, its residual's nearest codeword in each of
        `parts` slices of the dimensions. A list of over `block` vectors is kept in several blocks, dealt by a hash of id.
Search  a query visits the `probes` lists whose centroids have the largest inner product with it. In a block, queries and
        codes meet by asymmetric distance tables (query slice times codeword); the `shortlist` best, and all others that
        the tables' errors could hide, are rescored exactly, in double precision on the original vectors, and each
        block returns its k best of each query.
Probes  are set by measuring: the least number that finds `recall` of the sample's own true neighbours. A query whose lists
        hold fewer than k candidates visits further ones, in order, until they hold k or there are no more.

Equal codes and equal scores go by id, so copies of a vector come in order of id. Queries that probe a list come in blocks
too. Defined results: vectors that are null, zero or hold null or non-finite components, whose id is null, or whose length is not
the most frequent one (of equals: the longest), take no part, neither as queries nor as candidates; a query with fewer candidates
than k gets all that there are; of repeated ids each row counts as a candidate, and what rows of one query id find is ranked together; an empty table gives no rows; extra columns are
left out, whatever their names.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tidegate.llm.common import stored


MARGIN = 2.5  # deviations of the rough scores' errors


def usable(v: Column) -> Column:
    """Whether a vector takes part."""
    numbers = F.transform(v, lambda x: x.cast("double"))
    bad = F.exists(numbers, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return v.isNotNull() & ~F.coalesce(bad, F.lit(True)) & F.coalesce(F.exists(numbers, lambda x: x != 0), F.lit(False))


def kmeans(x: np.ndarray, k: int, rounds: int, seed: int) -> np.ndarray:
    """k centres of the rows of x (fewer if there are fewer rows); empty ones start again at the row farthest off."""
    k = max(1, min(k, len(x)))
    centres = x[np.random.default_rng(seed).permutation(len(x))[:k]].copy()
    for _ in range(rounds):
        d = (centres**2).sum(1)[None, :] - 2 * x @ centres.T
        own = d.argmin(1)
        n = np.bincount(own, minlength=k)
        sums = np.zeros_like(centres)
        np.add.at(sums, own, x)
        centres[n > 0] = sums[n > 0] / n[n > 0, None]
        for e in np.flatnonzero(n == 0):
            centres[e] = x[d.min(1).argmax()]
    return centres


class Model:
    """Centroids, codebooks and the number of lists that a query visits."""

    def __init__(self, x: np.ndarray, lists: int, parts: int, words: int, recall: float, k: int, shortlist: int, seed: int):
        self.lists = kmeans(x, lists, 12, seed)
        self.parts = parts if x.shape[1] % parts == 0 else 1
        rest = x - self.lists[self.assign(x)]
        self.books = [kmeans(np.ascontiguousarray(s), words, 8, seed + 1 + i) for i, s in enumerate(np.split(rest, self.parts, axis=1))]
        self.probes = self._probes(x, recall, k)

    def assign(self, x: np.ndarray) -> np.ndarray:
        return ((self.lists**2).sum(1)[None, :] - 2 * x @ self.lists.T).argmin(1)

    def codes(self, x: np.ndarray, own: np.ndarray) -> np.ndarray:
        rest = np.split(x - self.lists[own], self.parts, axis=1)
        return np.stack([((b**2).sum(1)[None, :] - 2 * r @ b.T).argmin(1) for r, b in zip(rest, self.books, strict=True)], axis=1).astype(np.uint8)

    def ranked(self, q: np.ndarray) -> np.ndarray:
        return np.argsort(-(q @ self.lists.T), axis=1, kind="stable")

    def approximate(self, q: np.ndarray, codes: np.ndarray, own: int) -> np.ndarray:
        """Scores (queries, rows) of one list's codes by table lookups."""
        out = np.repeat((q @ self.lists[own])[:, None], len(codes), axis=1)
        for p, (s, b) in enumerate(zip(np.split(q, self.parts, axis=1), self.books, strict=True)):
            out += (s @ b.T)[:, codes[:, p]]
        return out

    def _probes(self, x: np.ndarray, recall: float, k: int) -> int:
        """Lists to visit so that `recall` of the k true neighbours of sample rows lie in them."""
        n = len(self.lists)
        q = x[: min(len(x), 512)]
        score = q @ x.T
        score[np.arange(len(q)), np.arange(len(q))] = -np.inf
        best = np.argsort(-score, axis=1)[:, : min(k, max(1, len(x) - 1))]
        place = np.argsort(self.ranked(q), axis=1)
        own = self.assign(x)
        needed = np.sort(np.take_along_axis(place, own[best], axis=1), axis=None)
        return int(min(n, needed[min(len(needed) - 1, int(np.ceil(recall * len(needed))))] + 1))


def rescored(rough: np.ndarray, q: np.ndarray, who: np.ndarray, ids: np.ndarray, x: np.ndarray, shortlist: int, k: int) -> tuple:
    """Query, vector and exact score of the k best of each query, from rough scores (queries, rows in order of id).

    The `shortlist` best are scored exactly. How far rough scores are off there tells which others could still be among the k
    best (MARGIN deviations below the k-th); those are scored too, so a tight cluster of near copies is not cut by its codes.
    """
    width = min(shortlist, len(ids))
    best = np.argsort(-rough, axis=1, kind="stable")[:, :width]
    near = np.take_along_axis(rough, best, axis=1)
    exact = (q[:, None, :] * x[best]).sum(-1)
    known = near > -np.inf
    exact[~known] = -np.inf
    off = np.where(known, exact - np.where(known, near, 0), 0)
    spread = np.sqrt((off**2).sum(1) / np.maximum(1, known.sum(1)))
    limit = np.sort(exact, axis=1)[:, -k] if width >= k else np.full(len(q), -np.inf)
    more = rough >= (limit - MARGIN * spread)[:, None]
    more &= rough > -np.inf
    np.put_along_axis(more, best, False, axis=1)
    qi, ri = np.nonzero(more)
    scores = [(q[a] * x[b]).sum(-1) for a, b in ((qi[c : c + 50_000], ri[c : c + 50_000]) for c in range(0, len(qi), 50_000))]
    of = np.concatenate((np.repeat(np.arange(len(q)), known.sum(1)), qi))
    vec = np.concatenate((ids[best][known], ids[ri]))
    score = np.concatenate((exact[known], *scores))
    order = np.lexsort((vec, -score, of))
    of, vec, score = of[order], vec[order], score[order]
    place = np.arange(len(of)) - np.searchsorted(of, of)
    top = place < k
    return who[of[top]], vec[top], score[top]


def fit(vectors: DataFrame, lists: int, parts: int = 16, words: int = 64, sample: int = 16_000, recall: float = 0.97, k: int = 20, shortlist: int = 100, seed: int = 42) -> Model | None:
    rows = vectors.select("vec_id", "v").orderBy(F.xxhash64("vec_id", "v"), "vec_id").limit(sample).toArrow()
    if not rows.num_rows:
        return None
    flat = np.array(rows.column("v").to_pylist(), np.float64)
    # copies of one vector would draw centroids to themselves, and as queries pass for found neighbours
    flat = flat[np.sort(np.unique(flat, axis=0, return_index=True)[1])]
    return Model(flat, lists, parts, words, recall, k, shortlist, seed)


def search(vectors: DataFrame, is_query: Column, vector_col: str = "embedding", id_col: str = "vec_id", k: int = 20, lists: int | None = None, shortlist: int = 100, block: int = 4096, **how) -> DataFrame:
    """query_id, rank, vec_id and score of the k nearest found, by inner product, of each query row."""
    schema = "query_id long, rank int, vec_id long, score double"
    spark = vectors.sparkSession
    element = vectors.schema[vector_col].dataType.elementType.simpleString()
    number = "float" if element == "float" else "double"  # vectors are kept as they are, and reckoned with in double precision
    v = F.transform(F.col(vector_col), lambda x: x.cast(number))
    rows = vectors.where(usable(F.col(vector_col)) & F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("vec_id"), v.alias("v"), is_query.alias("is_query"))
    lengths = rows.groupBy(F.size("v").alias("d")).agg(F.count(F.lit(1)).alias("n"), F.count_if("is_query").alias("asked")).orderBy(F.desc("n"), F.desc("d")).first()
    if lengths is None:
        return spark.createDataFrame([], schema)
    rows, n = rows.where(F.size("v") == lengths["d"]), lengths["n"]
    lists = lists or int(min(4096, max(16, n**0.5 / 3)))
    model = fit(rows, lists, k=k, shortlist=shortlist, **how)
    if model is None:
        return spark.createDataFrame([], schema)
    shared = spark.sparkContext.broadcast(model)

    def indexed(batches):
        m = shared.value
        for b in batches:
            if b.num_rows:
                x = b.column(1).flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(b.num_rows, -1)
                own = m.assign(x)
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(2), pa.array(own.astype(np.int32)), pa.array([c.tobytes() for c in m.codes(x, own)], pa.binary())], names=["vec_id", "v", "is_query", "list", "code"])

    index = stored(rows.mapInArrow(indexed, f"vec_id long, v array<{number}>, is_query boolean, list int, code binary"), "ivf-index")

    # a row a list, at most 4096; a query's own rows are no candidates: as many as its id's most frequent copies
    counts = np.zeros(len(model.lists), np.int64)
    for r in index.groupBy("list").count().collect():
        counts[r["list"]] = r["count"]
    own_rows = index.where("is_query").groupBy("vec_id").count().agg(F.max("count")).first()[0] or 1

    def probing(batches):
        m = shared.value
        for b in batches:
            if b.num_rows:
                q = b.column(1).flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(b.num_rows, -1)
                to = m.ranked(q).astype(np.int32)
                short = np.cumsum(counts[to], axis=1) - counts[to] < k + own_rows  # lists before hold too few
                short[:, : m.probes] = True
                at = np.concatenate(([0], np.cumsum(short.sum(1)))).astype(np.int32)
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.ListArray.from_arrays(pa.array(at), pa.array(to[short]))], names=["vec_id", "v", "lists"])

    asked = index.where("is_query").select("vec_id", "v").mapInArrow(probing, f"vec_id long, v array<{number}>, lists array<int>")
    asked = asked.select(F.col("vec_id").alias("query_id"), F.col("v").alias("q"), F.explode("lists").alias("list"))
    # blocks of lists and of their queries: a list's size and its queries' number decide into how many
    sizes = index.groupBy("list").agg(F.count(F.lit(1)).alias("rows"), F.count_if("is_query").alias("queries")).select("list", F.expr(f"1 + rows div {block}").cast("int").alias("parts"))
    asks = asked.groupBy("list").agg(F.expr(f"1 + count(1) div {block}").cast("int").alias("turns"))
    deal = F.broadcast(sizes.join(asks, "list").select(F.col("list").alias("l"), "parts", "turns"))  # a row a list: at most 4096
    left = index.join(deal, F.col("list") == F.col("l")).select(
        "list", F.pmod(F.xxhash64("vec_id"), F.col("parts")).cast("int").alias("part"), F.explode(F.sequence(F.lit(0), F.col("turns") - 1)).alias("turn"), "vec_id", "v", "code"
    )
    right = asked.join(deal, F.col("list") == F.col("l")).select(
        "list", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), F.pmod(F.xxhash64("query_id"), F.col("turns")).cast("int").alias("turn"), "query_id", "q"
    )

    def compare(a: pa.Table, b: pa.Table) -> pa.Table:
        m = shared.value
        empty = pa.table({"query_id": pa.array([], pa.int64()), "vec_id": pa.array([], pa.int64()), "score": pa.array([], pa.float64())})
        if not a.num_rows or not b.num_rows:
            return empty
        a = a.sort_by("vec_id")
        own = a.column("list")[0].as_py()
        ids, asking = (t.to_numpy() for t in (a.column("vec_id"), b.column("query_id")))
        x, q = (t.combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(i), -1) for t, i in ((a.column("v"), ids), (b.column("q"), asking)))
        codes = np.frombuffer(b"".join(a.column("code").to_pylist()), np.uint8).reshape(len(ids), -1)
        out = []
        for s in range(0, len(q), 128):
            part, who = q[s : s + 128], asking[s : s + 128]
            rough = m.approximate(part, codes, own)
            rough[who[:, None] == ids[None, :]] = -np.inf
            out.append(rescored(rough, part, who, ids, x, shortlist, k))
        return pa.table({name: np.concatenate(c) for name, c in zip(empty.column_names, zip(*out, strict=True), strict=True)})

    keys = ["list", "part", "turn"]
    found = left.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInArrow(compare, "query_id long, vec_id long, score double")
    by = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    ranked = found.withColumn("rank", F.row_number().over(by)).where(F.col("rank") <= k)
    return ranked.select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
