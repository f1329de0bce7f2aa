"""Mixing sources to target weights over fixed-length token blocks. DataFrame functions only.

1. Sizes: words of each document; targets by water filling over the sources (a few numbers a source).
2. Pack: the documents of a source lie end to end in one stream of words, cut into blocks of `block` words. Identical rows are
   one row with a count until they have their places. Offsets come from prefix sums on three levels (within a chunk, over
   the chunks of a span, over a source's spans), so that no task holds a source.
3. Draw: a source takes `target` words, which is so many slots of a block each: whole passes over its blocks, and a part of a
   last one. Every slot draws an output shard; the counts of these draws, multinomial for each source, say how many
   slots a shard has of a source, and shards take the source's slots in turn, each its count.
4. Permute: slot i of a pass is block p(i), where p is a pseudorandom permutation of the source's full blocks, of its own for each pass: a
   Feistel network whose halves are numbers below a and b, with a times b at or little over the number of blocks, walked again
   from the few places over it. A source's short last block comes last.
5. Join: slots meet the blocks' pieces of documents by (source, block index).

Every number is a function of the rows and the seed: reruns agree. No document is taken more often than `most` times.

Defined results: null text is empty; empty documents are listed and take nothing; a null source is a source, the last by
order; repeated rows are rows of their own; an empty table gives an empty mix; extra columns are kept by mixed_documents,
whatever their names, and left out elsewhere.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tidegate.llm.common import WORD, stored

CHUNK_ROWS = 1_000
SPAN = 4096  # chunks of a span; places that one row is spread over
ROUNDS = 6


def row_key() -> Column:
    """Equal for copies of a row: a hash of its id, source and text."""
    return F.xxhash64("doc_id", F.col("source").cast("string"), "text")


def n_words(text: Column) -> Column:
    return F.regexp_count(F.coalesce(text, F.lit("")), F.lit(WORD)).cast("long")


def fill(sizes: dict, weights: tuple[float, ...], share: float, most: float) -> dict:
    """Targets by source: `share` of all sizes by weight, none above `most` times its size, the excess reshared by weight."""
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {s: weights[i % len(weights)] for i, s in enumerate(order)}
    left, open_, out = share * sum(sizes.values()), set(order), {}
    while open_:
        total = sum(weight[s] for s in order if s in open_)
        over = [s for s in order if s in open_ and left * weight[s] / total > most * sizes[s]]
        if not over:
            out |= {s: left * weight[s] / total for s in open_}
            break
        for s in over:
            out[s] = float(most * sizes[s])
            open_.remove(s)
        left = max(0.0, share * sum(sizes.values()) - sum(out.values()))
    return out


def sides(n: int) -> tuple[int, int]:
    """a and b, both about the root of n, whose product is n or as little over it as such numbers allow."""
    if n < 4:
        return 1, max(1, n)
    root = math.isqrt(n)
    a = np.arange(max(2, root // 2), root + 1, dtype=np.int64)[::-1][:200_000]
    best = int(a[np.argmin(-n % a)])
    return best, -(-n // best)


def scrambled(x: Column, a: Column, b: Column, *key: Column) -> Column:
    """One walk through the network: a bijection of the numbers below a * b."""
    left, right = F.call_function("div", x, b), x % b
    for k in range(ROUNDS):
        if k % 2:
            right = (right + F.pmod(F.xxhash64(F.lit(k), left, *key), b)) % b
        else:
            left = (left + F.pmod(F.xxhash64(F.lit(k), right, *key), a)) % a
    return left * b + right


def permuted(df: DataFrame, place: str, n: str, a: str, b: str, out: str, *key: Column) -> DataFrame:
    """df with `out`: the place that a permutation of the numbers below n has for `place`, which is below n.

    A walk that ends on one of the a * b - n numbers over n goes on from there; it passes each of them once at most.
    """
    n, a, b = F.col(n), F.col(a), F.col(b)
    once = df.withColumn(out, scrambled(F.col(place), a, b, *key))
    further = F.aggregate(F.sequence(F.lit(1).cast("long"), F.greatest(a * b - n, F.lit(1))), F.col(out), lambda x, _: F.when(x < n, x).otherwise(scrambled(x, a, b, *key)))
    return once.withColumn(out, F.when(F.col(out) < n, F.col(out)).otherwise(further))


def plan(docs: DataFrame, weights=(5.0, 2.0, 1.0), share=1.5, most=2.0, block: int = 256) -> DataFrame:
    """A row a source: its size, target, blocks, slots and the sides of its network. The number of sources must fit the driver."""
    sums = {r[0]: r[1] or 0 for r in docs.groupBy("source").agg(F.sum("size")).toLocalIterator()}
    targets = fill(sums, weights, share, most)
    rows = []
    for i, (s, size) in enumerate(sorted(sums.items(), key=lambda x: (x[0] is None, x[0] or ""))):
        words, full = int(targets[s]), size // block
        blocks = full + (size % block > 0)
        passes, rest = divmod(words, size) if size else (0, 0)
        a, b = sides(full)
        rows.append((s, i, size, targets[s], words, full, blocks, passes, rest, passes * blocks + -(-rest // block), a, b))
    kinds = "source string, source_no int, source_size long, target double, words long, full_blocks long, blocks long, passes long, rest long, slots long, a long, b long"
    return docs.sparkSession.createDataFrame(rows, kinds)


def offsets(docs: DataFrame) -> DataFrame:
    """docs (doc_id, source, size, h, k) with `at`, the words of the source before it, `rank`, and `copy`, its number among rows
    of one k: at and rank are unique within a source, but for empty documents' at."""
    d = docs.groupBy("doc_id", "source", "size", "h", "k").agg(F.count(F.lit(1)).alias("copies"))
    d = stored(d, "mix-rows")
    chunks = max(1, d.count() // CHUNK_ROWS)
    d = d.withColumn("chunk", F.pmod(F.xxhash64("doc_id", "h"), F.lit(chunks)).cast("int"))
    sums = d.groupBy("source", "chunk").agg(F.sum(F.col("size") * F.col("copies")).alias("words"), F.sum("copies").alias("n")).withColumn("span", F.expr(f"chunk div {SPAN}"))
    before = lambda c, w: F.coalesce(F.sum(c).over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    in_span, in_source = Window.partitionBy("source", "span").orderBy("chunk"), Window.partitionBy("source").orderBy("span")
    spans = sums.groupBy("source", "span").agg(F.sum("words").alias("w"), F.sum("n").alias("m")).select(F.col("source").alias("s"), F.col("span").alias("p"), before("w", in_source).alias("w"), before("m", in_source).alias("m"))
    local = sums.select("source", "chunk", "span", before("words", in_span).alias("words"), before("n", in_span).alias("n"))
    based = local.join(spans, F.col("source").eqNullSafe(F.col("s")) & (F.col("span") == F.col("p"))).select(
        F.col("source").alias("s"), F.col("chunk").alias("c"), (F.col("words") + F.col("w")).alias("base"), (F.col("n") + F.col("m")).alias("base_n")
    )
    inside = Window.partitionBy("source", "chunk").orderBy("doc_id", "h", "size")
    placed = d.withColumn("ahead", before(F.col("size") * F.col("copies"), inside)).withColumn("nth", before("copies", inside))
    j = placed.join(based, F.col("source").eqNullSafe(F.col("s")) & (F.col("chunk") == F.col("c")))
    many = spread(j, "copies", "copy")
    return many.select("doc_id", "source", "size", "k", (F.col("copy") + 1).alias("copy"), (F.col("base") + F.col("ahead") + F.col("size") * F.col("copy")).alias("at"), (F.col("base_n") + F.col("nth") + F.col("copy")).alias("rank"))


def spread(df: DataFrame, n: str, out: str, *deal: str) -> DataFrame:
    """A row for each number from 0 to n - 1, SPAN of them at a time; with `deal`, these runs are dealt to tasks by the columns."""
    parts = df.withColumn("_span", F.explode(F.sequence(F.lit(0).cast("long"), F.expr(f"greatest({n} - 1, 0) div {SPAN}")))).where(F.col(n) > 0)
    parts = parts.repartition(*deal, "_span") if deal else parts
    first = F.col("_span") * SPAN
    return parts.withColumn(out, F.explode(F.sequence(first, F.least(first + SPAN, F.col(n)) - 1))).drop("_span")


def draws(sources: DataFrame, shards: int, seed: int) -> DataFrame:
    """(source_no, shard, first, n): how many slots of a source an output shard has, and which is the first of them. Each slot
    draws a shard, all alike likely, so the counts of a source are multinomial."""
    asked = spread(sources.select("source_no", "slots"), "slots", "slot", "source_no")
    drawn = asked.groupBy("source_no", F.pmod(F.xxhash64(F.lit(seed), "source_no", "slot"), F.lit(shards)).cast("int").alias("shard")).agg(F.count(F.lit(1)).alias("n"))
    before = Window.partitionBy("source_no").orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    return drawn.withColumn("first", F.coalesce(F.sum("n").over(before), F.lit(0)))


def slots(sources: DataFrame, block: int, shards: int, seed: int) -> DataFrame:
    """(source_no, slot, block_no, pass, upto, shard): the first `upto` words of a block that a slot of a shard takes."""
    s = sources.where("slots > 0").select(F.col("source_no").alias("no"), "source_size", "full_blocks", "blocks", "passes", "rest", "a", "b")
    given = spread(draws(sources.where("slots > 0"), shards, seed), "n", "nth", "source_no", "shard")
    places = given.join(s, F.col("source_no") == F.col("no")).withColumn("slot", F.col("first") + F.col("nth"))
    places = places.withColumn("pass", F.expr("slot div blocks")).withColumn("place", F.col("slot") % F.col("blocks")).withColumn("inner", F.least("place", F.greatest(F.col("full_blocks") - 1, F.lit(0))))
    places = permuted(places, "inner", "full_blocks", "a", "b", "image", F.col("source_no"), F.col("pass"), F.lit(seed))
    tail = F.col("place") == F.col("full_blocks")
    length = F.when(tail, F.col("source_size") - F.col("full_blocks") * block).otherwise(block)
    left = F.when(F.col("pass") < F.col("passes"), length).otherwise(F.least(length, F.col("rest") - F.col("place") * block))
    return places.select("source_no", "slot", F.when(tail, F.col("place")).otherwise(F.col("image")).alias("block_no"), "pass", left.cast("long").alias("upto"), "shard")


def mix(docs: DataFrame, weights=(5.0, 2.0, 1.0), share=1.5, most=2.0, block: int = 256, shard_words: int = 1 << 22, seed: int = 42):
    """(documents, pieces): documents (doc_id, source, size, k, copy, at, rank, source_no, source_size, target), and for each word
    range that the mix takes (source_no, rank, slot, pass, lo, hi, shard), lo and hi counted in words of the document.

    docs needs doc_id, text and source; other columns are left alone.
    """
    sized = stored(docs.select(F.col("doc_id"), F.col("source").cast("string").alias("source"), n_words(F.col("text")).alias("size"), F.xxhash64("text").alias("h"), row_key().alias("k")), "mix-sizes")
    sources = plan(sized, weights, share, most, block)
    total = sum(r["words"] for r in sources.toLocalIterator())
    taken = slots(sources, block, max(1, -(-total // shard_words)), seed)
    known = sources.select(F.col("source").alias("s"), "source_no", "source_size", "target")
    placed = offsets(sized)
    placed = placed.join(known, F.col("source").eqNullSafe(F.col("s"))).drop("s")
    placed = stored(placed, "mix-places")
    first, end = F.expr(f"at div {block}"), F.expr(f"(at + size - 1) div {block}")
    parts = placed.where("size > 0").select("source_no", "rank", "at", "size", F.explode(F.sequence(first, end)).alias("block_no"))
    # slots are made from a few rows, which hides from the planner how many there are: without the hint it would broadcast them
    j = parts.join(taken.hint("merge"), ["source_no", "block_no"])
    lo = F.greatest(F.lit(0), F.col("block_no") * block - F.col("at"))
    hi = F.least(F.col("size"), F.col("block_no") * block + F.col("upto") - F.col("at"))
    return placed, j.select("source_no", "rank", "slot", "pass", lo.cast("long").alias("lo"), hi.cast("long").alias("hi"), "shard").where("hi > lo")


def taken_words(docs: DataFrame, **how) -> DataFrame:
    """doc_id, size, source_size, target and taken of each document, and the least shard that takes words of it."""
    placed, pieces = mix(docs, **how)
    sums = pieces.groupBy("source_no", "rank").agg(F.sum(F.col("hi") - F.col("lo")).alias("taken"), F.min("shard").alias("first_shard"))
    j = placed.join(sums, ["source_no", "rank"], "left")
    return j.select("doc_id", "size", "source_size", "target", F.coalesce("taken", F.lit(0)).cast("long").alias("taken"), "first_shard")


WORDS = r"[\x20\x09-\x0D]+"


def _of_words(made) -> Column:
    """made(words of row.text): words are parted once, as the one element of an array, not again wherever a lambda names them."""
    return F.get(F.transform(F.array(F.filter(F.split("row.text", WORDS), lambda x: x != "")), made), F.lit(0))


def _with_ranges(docs: DataFrame, placed: DataFrame, ranges: DataFrame) -> DataFrame:
    """(row, size, and the columns of ranges) of each document and what is taken of it: ranges has source_no and rank."""
    wanted = placed.select("source_no", "rank", "size", F.col("k").alias("wk"), F.col("copy").alias("wanted")).join(ranges, ["source_no", "rank"])
    mine = docs.select(F.struct(*docs.columns).alias("row"), row_key().alias("k"))
    mine = mine.withColumn("copy", F.row_number().over(Window.partitionBy("k").orderBy("k")))
    # the copy's number stays out of the join's keys, so that texts move once, for the window
    return mine.join(wanted, (F.col("k") == F.col("wk")) & (F.col("copy") >= F.col("wanted")) & (F.col("copy") <= F.col("wanted")))


def mixed_documents(docs: DataFrame, **how) -> DataFrame:
    """The mix as documents: for each pass the text that it takes, whole where it takes all words, else its words by spaces.

    Keeps the columns of docs; text and n_chars are the taken text's. Rows of one document and pass stay together.
    """
    placed, pieces = mix(docs, **how)
    ranges = pieces.groupBy("source_no", "rank", "pass").agg(F.sort_array(F.collect_list(F.struct("lo", "hi"))).alias("ranges"), F.sum(F.col("hi") - F.col("lo")).alias("n"))
    j = _with_ranges(docs, placed, ranges)
    cut = _of_words(lambda words: F.array_join(F.flatten(F.transform("ranges", lambda r: F.slice(words, (r["lo"] + 1).cast("int"), (r["hi"] - r["lo"]).cast("int")))), " "))
    text = F.when(F.col("n") == F.col("size"), F.col("row.text")).otherwise(cut)
    out = j.select("row", text.alias("taken"))
    new = {"text": F.col("taken")}
    if "n_chars" in docs.columns:
        new["n_chars"] = F.length("taken").cast(docs.schema["n_chars"].dataType)
    return out.select(*[new[c].alias(c) if c in new else F.col("row").getField(c).alias(c) for c in docs.columns])


def mixed_blocks(docs: DataFrame, **how) -> DataFrame:
    """The mix as output shards: shard, source_no, slot, words and text, the words of a slot's block that it takes, by spaces."""
    placed, pieces = mix(docs, **how)
    ranges = pieces.groupBy("source_no", "rank").agg(F.collect_list(F.struct("shard", "slot", "lo", "hi")).alias("ranges"))
    said = lambda words, r: F.array_join(F.slice(words, (r["lo"] + 1).cast("int"), (r["hi"] - r["lo"]).cast("int")), " ")
    cut = _of_words(lambda words: F.transform("ranges", lambda r: F.struct(r["shard"].alias("shard"), r["slot"].alias("slot"), (r["hi"] - r["lo"]).alias("n"), said(words, r).alias("text"))))
    j = _with_ranges(docs, placed, ranges).select("source_no", "rank", F.explode(cut).alias("r"))
    parts = j.select("r.shard", "source_no", "r.slot", F.struct("rank", "r.n", "r.text").alias("part"))
    whole = parts.groupBy("shard", "source_no", "slot").agg(F.sum("part.n").alias("words"), F.sort_array(F.collect_list("part")).alias("parts"))
    return whole.select("shard", "source_no", "slot", "words", F.array_join(F.transform("parts", lambda p: p["text"]), " ").alias("text"))
