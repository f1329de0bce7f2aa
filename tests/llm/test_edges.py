"""Each operator and pipeline stage on nulls, empty and long texts, ties, repeated rows, empty tables and extra columns."""

import re

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from tidegate.llm import chat, fixity, ivfpq, mixing, packing, quality, simhash, telephony, token_edits, urls

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
LONG = "word " * 30_000


def rows_of(kind):
    text = "the quick brown fox jumps over the lazy dog and runs far away from here"
    if kind == "empty":
        return []
    return [
        (1, text, "en", "a", len(text)), (1, text, "en", "a", len(text)), (2, text, None, "a", None), (3, None, "en", "a", 0), (4, "", "en", None, 0), (5, "   \n\t ", None, None, 5),
        (None, text + "!", "en", "b", 1), (None, None, None, None, None), (6, LONG, "en", "b", len(LONG)), (7, "one", "en", "b", 3), (8, "One", "en", "b", 3), (9, "ÄÖ <|endoftext|> \x00 \u2003x", "de", "c", 9),
    ]


@pytest.fixture(scope="module")
def docs(spark):
    clash = {n: F.lit(7) for n in ("size", "h", "key", "node", "part", "ids", "group", "rank", "source_no", "_key_", "posterior", "host_posterior", "list", "code", "v",
                                  "_key", "_nth", "_evidence", "_posterior", "_host", "_path", "_hp", "_pp", "_k", "_copy", "_n", "_ranges", "_wk", "_wanted", "_size", "_h", "_s", "_doc", "_y", "_x", "_span",
                                  "row", "k", "nth", "copy", "wk", "wanted", "ranges", "words", "n", "s", "p", "q", "mean", "host", "path", "evidence", "path_posterior", "host_n", "host_s", "taken", "r", "stay", "fp", "keys", "root")}
    return {k: spark.createDataFrame(rows_of(k), DOCS).withColumns(clash) for k in ("empty", "odd")}


@pytest.fixture(scope="module")
def labels(spark):
    return {"empty": spark.createDataFrame([], "doc_id long, quality int, toxic int"), "odd": spark.createDataFrame([(1, 1, 0), (1, 1, 0), (7, 0, 0), (None, 1, 0), (6, None, None), (99, 0, 1)], "doc_id long, quality int, toxic int")}


@pytest.mark.parametrize("kind", ["empty", "odd"])
@pytest.mark.parametrize("labelled", ["empty", "odd"])
def test_quality(docs, labels, kind, labelled):
    got = quality.quality_table(docs[kind], labels[labelled]).collect()
    assert len(got) == len(rows_of(kind))
    assert all(r["posterior"] is not None and r["keep"] is not None for r in got)
    kept = quality.good_documents(docs[kind], labels[labelled])
    assert kind == "empty" or {kept.first()[c] for c in kept.columns[5:]} == {7}
    assert kept.columns == docs[kind].columns and kept.count() == sum(r["keep"] for r in got)
    if kind == "odd":
        assert not any(r["keep"] for r in got if r["doc_id"] in (3, 4))
        if labelled == "empty":
            assert all(r["keep"] for r in got if r["doc_id"] in (1, 2, 6, 7, 8, 9))


@pytest.mark.parametrize("kind", ["empty", "odd"])
def test_token_edits(docs, kind):
    got = token_edits.redacted_token_counts(docs[kind]).collect()
    assert len(got) == len(rows_of(kind))
    assert all(r["n_tokens"] == 0 for r in got if r["doc_id"] in (3, 4))


@pytest.mark.parametrize("kind", ["empty", "odd"])
def test_simhash(docs, kind):
    got = simhash.simhash_classes(docs[kind]).collect()
    assert len(got) == len(rows_of(kind))
    if kind == "odd":
        by = {}
        for r in got:
            by.setdefault(r["doc_id"], r)
        assert by[1]["component_id"] == by[2]["component_id"] == 1 and by[7]["component_id"] == by[8]["component_id"] == 7
        assert by[3]["fingerprint"] == by[4]["fingerprint"] == by[5]["fingerprint"] == "0" * 16 and by[None] is not None
        assert by[3]["component_id"] == by[4]["component_id"] == 3


@pytest.mark.parametrize("kind", ["empty", "odd"])
def test_near_copies(docs, kind):
    got = simhash.near_copies(docs[kind])
    assert kind == "empty" or {got.first()[c] for c in got.columns[5:]} == {7}
    assert got.columns == docs[kind].columns
    ids = sorted((r["doc_id"] if r["doc_id"] is not None else -1) for r in got.collect())
    assert ids == ([] if kind == "empty" else [1, 3, 6, 7, 9]), ids


@pytest.mark.parametrize("kind", ["empty", "odd"])
def test_packing(docs, kind):
    got = packing.pack(docs[kind], window=64).collect()
    assert sum(r["length"] for r in got) == sum({(r["doc_id"], r["doc_tokens"], r["sequence_id"], r["offset"]): r["length"] for r in got}.values())
    assert {r["doc_id"] for r in got} == {r[0] for r in rows_of(kind)}
    ends = {}
    for r in got:
        ends[r["sequence_id"]] = max(ends.get(r["sequence_id"], 0), r["offset"] + r["length"])
    assert all(n == 64 for s, n in ends.items() if s != max(ends))
    if kind == "odd":
        assert sum(r["doc_tokens"] == 1 for r in got) == 4  # nulls and empty texts


@pytest.mark.parametrize("kind", ["empty", "odd"])
def test_mixing(docs, kind):
    got = mixing.taken_words(docs[kind], block=16).collect()
    assert len(got) == len(rows_of(kind))
    assert all(r["taken"] <= 2 * r["size"] for r in got)
    by = {}
    for r in got:
        by.setdefault((r["source_size"], round(r["target"], 6)), []).append(r["taken"])
    assert all(abs(sum(t) - k[1]) <= 1 for k, t in by.items())
    mixed = mixing.mixed_documents(docs[kind], block=16)
    assert mixed.columns == docs[kind].columns and (kind == "empty" or {mixed.first()[c] for c in mixed.columns[5:]} == {7})
    words = sum(len(r["text"].split()) for r in mixed.select("text").collect())
    assert words == sum(r["taken"] for r in got)


@pytest.mark.parametrize("kind", ["empty", "odd"])
def test_media(docs, kind):
    got = telephony.media_digests(docs[kind]).collect()
    assert len(got) == len(rows_of(kind)) and all(r["payload_bytes"] % 192 == 0 and r["payload_bytes"] >= 192 for r in got)
    same = {r["media_sha256"] for r in got if r["doc_id"] in (3, 4)}
    assert len(same) <= 1


def test_chat(spark):
    rows = [(1, 0, "user", "a"), (1, 0, "user", "a"), (1, None, None, None), (None, 1, "assistant", "x<|end|>\\[y"), (2, 5, "assistant", ""), (2, 4, "", "\\<\\")]
    made = chat.format_chats(chat.turns_as_events(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("msg", F.lit("clash"))))
    got = {r["conv_id"]: r for r in chat.read_back(made).collect()}
    assert got[1]["n_turns"] == 3 and got[None]["loss_chars"] == len("x<|end|>\\[y") and got[2]["n_turns"] == 2
    turns = {r["conv_id"]: [(t["role"], t["text"]) for t in r["turns"]] for r in made.select("conv_id", chat.parse(F.col("formatted")).alias("turns")).collect()}
    assert turns[None] == [("assistant", "x<|end|>\\[y")] and turns[2] == [("", "\\<\\"), ("assistant", "")] and turns[1][0] == ("", "")
    empty = chat.format_chats(chat.turns_as_events(spark.createDataFrame([], "conv_id long, turn long, role string, text string")))
    assert chat.read_back(empty).count() == 0


def test_chat_events(spark):
    log = [
        (1, 1, 1, "open", "user", "hi"), (1, 2, 2, "open", "assistant", None), (1, 3, 2, "delta", None, "he"), (1, 4, 2, "delta", None, "llo"), (1, 5, 3, "open", "user", "more"),
        (1, 6, 2, "regenerate", None, ""), (1, 7, 2, "delta", None, "good "), (1, 8, 2, "delta", None, "day"), (1, 9, 4, "open", "user", "thx"), (1, 10, 4, "edit", None, "thanks"), (1, 11, 5, "open", "user", "x"),
        (1, 12, 5, "retract", None, None), (1, 13, 6, "delta", None, "never opened"), (1, 14, 1, "unknown", None, "?"),
    ]
    events = spark.createDataFrame(log, "conv_id long, seq long, msg long, kind string, role string, text string").orderBy(F.rand(3))
    got = chat.format_chats(events).select(chat.parse(F.col("formatted")).alias("t"), "formatted", "loss_spans").first()
    assert [(t["role"], t["text"]) for t in got["t"]] == [("user", "hi"), ("assistant", "good day"), ("user", "thanks")]
    assert [got["formatted"][s["start"] : s["start"] + s["length"]] for s in got["loss_spans"]] == ["good day"]


def test_chat_fold_order(spark):
    """Equal seq go by kind and text; a message opened again after a retraction stays; null seq come first."""
    log = [
        (1, 1, 1, "open", "user", "a"), (1, 2, 1, "edit", None, "FINAL"), (1, 2, 1, "delta", None, "late"),
        (1, 3, 2, "open", "assistant", ""), (1, 4, 2, "edit", None, "b"), (1, 4, 2, "edit", None, "a"), (1, 5, 2, "delta", None, "+"), (1, 5, 2, "delta", None, "+"),
        (1, 6, 3, "open", "user", "x"), (1, 6, 3, "open", "assistant", "x"), (1, 7, 3, "retract", None, None), (1, 8, 3, "open", "assistant", "again"),
        (2, 1, 1, "open", "user", "q"), (2, 2, 2, "open", "assistant", "goes"), (2, 2, 1, "regenerate", None, "Q"), (2, 3, 3, "open", "assistant", "<stays["), (2, None, 3, "delta", None, "early"),
    ]
    events = spark.createDataFrame(log, "conv_id long, seq long, msg long, kind string, role string, text string").withColumns({n: F.lit(1) for n in ("e", "log", "cut", "turn")})
    for seed in (1, 2, 3):
        made = chat.format_chats(events.orderBy(F.rand(seed)))
        got = {r["conv_id"]: r for r in made.select("conv_id", chat.parse(F.col("formatted")).alias("t"), "formatted", "loss_spans").collect()}
        assert [(t["role"], t["text"]) for t in got[1]["t"]] == [("user", "FINAL"), ("assistant", "b++"), ("assistant", "again")]
        assert [(t["role"], t["text"]) for t in got[2]["t"]] == [("user", "Q"), ("assistant", "<stays[")]
        for r in got.values():
            spans = [r["formatted"][s["start"] : s["start"] + s["length"]] for s in r["loss_spans"]]
            assert spans == [re.sub(r"([<\[\\])", r"\1\\", t["text"]) for t in r["t"] if t["role"] == "assistant"]
        assert {r["conv_id"]: r["loss_chars"] for r in chat.read_back(made).collect()} == {1: 8, 2: 7}


RULES = [("org", "/", "allow"), ("b.org", "/x/", "block"), ("b.org", "/x/y", "allow"), ("B.org", "/x/y", "block"), (None, "/", "block"), ("", "", "block")]


@pytest.mark.parametrize("chunk", [1, 100])
def test_urls(spark, chunk):
    pages = [(1, None), (2, "no scheme"), (3, "http://A.B.ORG/x/yz?q#f"), (4, "x://b.org"), (5, "http://xb.org/x/"), (6, "http://b.org?/x/"), (7, "http://ÄA.org/"), (8, ""), (9, "a://b.org/x/1"), (9, "a://b.org/x/1")]
    df = spark.createDataFrame(pages, "page_id long, url string").withColumn("host", F.lit(1)).withColumn("rule", F.lit(1))
    got = urls.apply_rules(df, spark.createDataFrame(RULES, "host string, path string, verdict string"), chunk_rules=chunk).collect()
    by = {r["page_id"]: r for r in got}
    assert len(got) == 10 and (by[1]["host"], by[1]["path"]) == ("", "") and by[1]["verdict"] == "block" and by[1]["rule"] == ""
    assert (by[3]["host"], by[3]["path"], by[3]["rule"], by[3]["verdict"]) == ("a.b.org", "/x/yz", "b.org/x/y", "block")
    assert by[4]["rule"] is None and by[4]["verdict"] == "allow" and by[5]["rule"] == "org/" and by[6]["path"] == "" and by[7]["host"] == "Äa.org" and by[9]["rule"] == "b.org/x/"
    assert urls.apply_rules(df.limit(0), spark.createDataFrame([], "host string, path string, verdict string")).count() == 0


def test_fixity(spark):
    kind = "page_id long, url string, html string"
    mine = [(k, f"u{k}", "x" * (k % 7)) for k in range(3000)] + [(None, None, None), (5, "u5", "x" * 5), (5, "u5", "x" * 5)]
    theirs = [r for r in mine if r[0] != 2999]
    theirs = [(k, u, "CHANGED" if k in (17, 1500) else h) for k, u, h in theirs]
    a, b = (fixity.manifest(spark.createDataFrame(r, kind).withColumn("length", F.lit(0)), 512) for r in (mine, theirs))
    got = fixity.audit(a, b).collect()
    bad = {r["page_id"] for r in got if r["damaged"]}
    assert len(got) == len(mine) and {17, 1500, 2999} <= bad and all(r["damaged"] is False for r in fixity.audit(a, a).collect())
    assert not {k for k in bad if k is not None and k < 17}
    none = fixity.manifest(spark.createDataFrame([], kind))
    assert fixity.audit(none, none).count() == 0
    assert all(r["damaged"] for r in fixity.audit(a, none).collect())


def test_fixity_reads_bytes(spark):
    """Files read back by ranges have the manifest of what was written; flipped, cut and lost bytes are located."""
    kind = "page_id long, url string, html string"
    rows = [(k, f"u{k}", "é" * (k % 7)) for k in range(700)] + [(None, None, None)] * 600 + [(None, "x", str(k)) for k in range(900)] + [(5, "u5", "y")]
    pages = spark.createDataFrame(rows, kind).withColumns({n: F.lit("clash") for n in ("bytes", "start", "records", "all", "digest")})
    files = fixity.write_files(pages, 512)
    mine = fixity.manifest(pages, 512)
    order = ["file_no", "record_no"]
    assert mine.orderBy(*order).collect() == fixity.read_manifest(files).orderBy(*order).collect()
    assert 3 <= mine.where("file_no < 0").select("file_no").distinct().count() <= 4
    text = b"".join(bytes(r["bytes"]) for r in files.where("file_no = 0").orderBy("part_no").collect())
    at = mine.where("file_no = 0 and page_id = 20").first()
    assert text[at["start"] : at["start"] + at["length"]].startswith(b"WARC/1.0\r\nWARC-Type: resource\r\nWARC-Record-ID: <urn:page:20>\r\nWARC-Date: ")
    place = F.col("file_no") == 0
    flipped = F.expr("concat(substring(bytes, 1, 10), X'00', substring(bytes, 12, length(bytes)))")
    bad = files.withColumn("bytes", F.when(place & (F.col("part_no") == 2), flipped).when(place & (F.col("part_no") == 4), F.expr("substring(bytes, 1, length(bytes) - 1)")).otherwise(F.col("bytes")))
    bad = bad.where(~((F.col("file_no") == 1) & (F.col("part_no") == 3)))
    got = fixity.audit(mine, fixity.read_manifest(bad)).where("damaged")
    assert sorted((r["file_no"], r["record_no"]) for r in got.collect()) == [(0, 32), (0, 79), *((1, k) for k in range(48, 64))]


def test_fixity_replica_only(spark):
    """A record at the end of a replica's file and a file of its own are damaged, and nothing else is."""
    kind = "page_id long, url string, html string"
    mine = [(k, f"u{k}", "x") for k in range(1000)]
    theirs = [*mine, (1005, "u1005", "y"), *[(k, f"u{k}", "z") for k in range(4096, 4100)]]
    a, b = (fixity.manifest(spark.createDataFrame(r, kind), 512) for r in (mine, theirs))
    got = fixity.audit(a, b).collect()
    assert sorted(r["page_id"] for r in got) == sorted(r[0] for r in theirs)
    assert {r["page_id"] for r in got if r["damaged"]} == {1005, 4096, 4097, 4098, 4099}


def test_neighbours(spark):
    v = [0.5, 0.25, -1.0, 0.0]
    rows = [(0, v), (1, v), (2, None), (3, [0.0] * 4), (4, [float("nan"), 1.0, 1.0, 1.0]), (5, [float("inf"), 0.0, 0.0, 0.0]), (6, [None, 1.0, 0.0, 0.0]), (7, v), (8, [-x for x in v]), (20, [1.0, 0.0, 0.0, 0.0]), (None, v)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumn("list", F.lit(1)).withColumn("v", F.lit("x"))
    got = ivfpq.search(df, F.pmod("vec_id", F.lit(20)) == 0, k=3).orderBy("query_id", "rank").collect()
    assert [(r["query_id"], r["vec_id"]) for r in got] == [(0, 1), (0, 7), (0, 20), (20, 0), (20, 1), (20, 7)]
    assert got[0]["score"] == 0.25 + 0.0625 + 1.0
    assert ivfpq.search(df.limit(0), F.lit(True)).count() == 0
    assert ivfpq.search(df.where("vec_id = 0"), F.lit(True)).count() == 0


@pytest.mark.parametrize("n", [2, 24, 90])
def test_neighbours_all_found(spark, n):
    """Few candidates: each query gets k of them, or all that there are; vectors of another length take no part."""
    r = np.random.default_rng(n)
    rows = [(i, r.normal(size=64).tolist()) for i in range(n)] + [(1000, [1.0, 2.0]), (1, r.normal(size=64).tolist())]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").withColumn("d", F.lit("x"))
    got = ivfpq.search(df, F.lit(True)).groupBy("query_id").count().collect()
    assert {x["query_id"]: x["count"] for x in got} == {i: min(20, 2 * (n - 1) if i == 1 else n) for i in range(n)}


@pytest.mark.parametrize("kind", ["empty", "odd"])
def test_pipeline(spark, docs, labels, kind, tmp_path):
    docs[kind].select("doc_id", "text", "lang", "source", "n_chars").write.parquet(f"{tmp_path}/documents.parquet")
    labels[kind].write.parquet(f"{tmp_path}/labels.parquet")
    out = corpus_pipeline.run(spark, str(tmp_path)).collect()
    assert (not out) if kind == "empty" else out
    d = spark.read.parquet(f"{tmp_path}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        d = stage(spark, d, str(tmp_path))
        assert d.columns == ["doc_id", "text", "lang", "source", "n_chars"], name
