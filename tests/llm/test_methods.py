"""The operators' inner methods, against plain versions."""

import random

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from tidegate.llm import fixity, ivfpq, mixing, packing, quality, simhash, telephony, token_edits, urls

# ---- bit-sliced comparison


@pytest.mark.parametrize("words", [1, 2, 8])
def test_near_is_popcount(words):
    r = np.random.default_rng(words)
    base = r.integers(0, 2**63, (40, words), dtype=np.uint64)
    rows = np.concatenate([base, base ^ (np.uint64(1) << r.integers(0, 63, (40, words), dtype=np.uint64)), r.integers(0, 2**63, (131, words), dtype=np.uint64)])
    d = np.bitwise_count(rows[:, None, :] ^ rows[None, :, :]).sum(2)
    for radius in (0, 1, 2, 8, 31 * words):
        assert (simhash.near(rows, rows, radius) == (d <= radius)).all(), radius


def plain_components(fps, radius):
    parent = list(range(len(fps)))

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(len(fps)):
        for j in range(i):
            if bin(fps[i] ^ fps[j]).count("1") <= radius:
                a, b = sorted((root(i), root(j)))
                parent[b] = a
    return [root(i) for i in range(len(fps))]


@pytest.mark.parametrize("hot", [4, 4096])
def test_links_miss_nothing(spark, monkeypatch, hot):
    """Also where nearly every key is hot and is dealt out again by finer keys."""
    monkeypatch.setattr(simhash, "HOT", hot)
    r = random.Random(7)
    centres = [r.getrandbits(64) for _ in range(6)]
    fps = {c ^ (1 << r.randrange(64)) ^ (1 << r.randrange(64)) ^ (1 << r.randrange(64)) for c in centres for _ in range(40)} | {r.getrandbits(64) for _ in range(60)} | {0, 1, 3, 7, 2**64 - 1}
    fps = sorted(fps)
    signed = [f - 2**64 if f >= 2**63 else f for f in fps]
    nodes = spark.createDataFrame([(s,) for s in signed], "node long").withColumn("keys", simhash.piece_keys(F.col("node"), 2))
    got = {x["node"]: x["root"] for x in simhash.components(simhash.near_links(nodes, 2)).collect()}
    want = plain_components(fps, 2)
    by = {}
    for s, w in zip(signed, want, strict=True):
        by.setdefault(w, set()).add(s)
    for group in by.values():
        assert {got.get(s, s) for s in group} == {min(group)}


def test_labels_blocks(monkeypatch):
    monkeypatch.setattr(simhash, "LANES", 16)
    r = np.random.default_rng(3)
    chain = np.cumsum(1 << r.permutation(60).astype(np.uint64)[:50], dtype=np.uint64)
    fps = np.concatenate([chain, r.integers(0, 2**63, 100, dtype=np.uint64)])[r.permutation(150)]
    assert simhash.labels(fps[:, None], 1).tolist() == plain_components([int(x) for x in fps], 1)


def test_near_copies_found(spark):
    """Shares of common five-word shingles of 0.9 and more are caught; half and less are left alone."""
    r = random.Random(1)
    vocabulary = [f"w{i}" for i in range(5000)]
    rows, groups = [], []
    for g in range(60):
        text = [r.choice(vocabulary) for _ in range(400)]
        group = [len(rows)]
        rows.append(" ".join(text))
        for _ in range(3):
            near = list(text)
            for _ in range(2):
                near[r.randrange(400)] = "changed"
            group.append(len(rows))
            rows.append(" ".join(near))
        far = [w if i % 12 else r.choice(vocabulary) for i, w in enumerate(text)]
        rows.append(" ".join(far))
        groups.append((group, len(rows) - 1))
    docs = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in enumerate(rows)], "doc_id long, text string, lang string, source string, n_chars long")
    kept = {x["doc_id"] for x in simhash.near_copies(docs).select("doc_id").collect()}
    caught = sum(len(kept & set(g)) == 1 for g, _ in groups)
    assert caught >= 59 and all(f in kept for _, f in groups) and all(g[0] in kept for g, _ in groups)


def test_near_copies_hot_bands(spark, monkeypatch):
    monkeypatch.setattr(simhash, "HOT", 8)
    text = [f"w{i}" for i in range(300)]
    docs = [(i, " ".join([*text[: i % 290], f"x{i}", *text[i % 290 + 1 :]])) for i in range(60)]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    assert [x["doc_id"] for x in simhash.near_copies(df).collect()] == [0]


@pytest.mark.parametrize("hot", [4, 4096])
def test_only_key_is_hot(spark, monkeypatch, hot):
    """Two near rows that share one hot band and no other still meet."""
    monkeypatch.setattr(simhash, "HOT", hot)
    r = np.random.default_rng(9)
    fps = r.integers(0, 2**62, (50, 2)).tolist()
    fps[31] = [fps[17][0] ^ 5, fps[17][1]]
    rows = [(k, fps[k], [7, 1000 + k, 2000 + k]) for k in range(50)]
    nodes = spark.createDataFrame(rows, "node long, fp array<long>, keys array<long>")
    assert {tuple(sorted(x)) for x in simhash.near_links(nodes, 4, 2).collect()} == {(17, 31)}
    assert {x["node"] for x in simhash.near_links(nodes, 4, 2, groups=True).collect()} == {17, 31}


def test_hot_band_pairs(spark):
    """4,200 lone near pairs that share one band and nothing else, over HOT as it is: all of them are found."""
    r = np.random.default_rng(3)
    fps = r.integers(0, 2**62, (4200, 2))
    rows = [(2 * k + side, [int(fps[k, 0]) ^ (side * 9), int(fps[k, 1])], [7, 10_000 + 2 * k + side]) for k in range(4200) for side in (0, 1)]
    nodes = spark.createDataFrame(rows, "node long, fp array<long>, keys array<long>")
    got = {tuple(sorted(x)) for x in simhash.near_links(nodes, 4, 2).collect()}
    assert got == {(2 * k, 2 * k + 1) for k in range(4200)}


def pairs_of_similarity(r, sizes, shares):
    """Lone pairs of texts whose five-word shingle sets have about the given shares, and the exact ones."""
    out = []
    for k in range(len(shares)):
        n, s = sizes[k], shares[k]
        common = max(1, round(s * n))
        base = [f"d{k}w{i}" for i in range(common + 4)]  # common shingles lie in one run of words
        extra = n - common
        left = r.randrange(extra + 1)
        a, b = base + [f"d{k}a{i}" for i in range(left)], base + [f"d{k}b{i}" for i in range(extra - left)]
        sh = [{tuple(x[i : i + 5]) for i in range(len(x) - 4)} for x in (a, b)]
        out.append((" ".join(a), " ".join(b), len(sh[0] & sh[1]) / len(sh[0] | sh[1])))
    return out


@pytest.mark.parametrize("sizes", [(5, 60), (100, 400)])
def test_near_copies_exact_limit(spark, sizes):
    """Lone pairs at 0.72 to 0.88: removed at 0.8 and above, kept below, as brute force has it."""
    r = random.Random(11)
    pairs = pairs_of_similarity(r, [r.randrange(*sizes) for _ in range(400)], [r.uniform(0.72, 0.88) for _ in range(400)])
    rows = [(2 * k + side, x[side]) for k, x in enumerate(pairs) for side in (0, 1)]
    kept = {x["doc_id"] for x in simhash.near_copies(spark.createDataFrame(rows, "doc_id long, text string")).select("doc_id").collect()}
    for k, (_, _, s) in enumerate(pairs):
        assert 2 * k in kept and (2 * k + 1 in kept) == (s < 0.8), (k, s)


def test_alike_is_brute():
    r = np.random.default_rng(5)
    base = r.integers(0, 300, (6, 40))
    sets = [np.unique(np.where(r.random(40) < r.choice([0.02, 0.1, 0.2]), r.integers(0, 10**6, 40), base[k % 6])) for k in range(90)]
    parent = list(range(90))
    for i in range(90):
        for j in range(i):
            if len(np.intersect1d(sets[i], sets[j])) / len(np.union1d(sets[i], sets[j])) >= 0.8:
                x, y = sorted((parent[i], parent[j]))
                parent = [x if p == y else p for p in parent]
    assert simhash.alike(sets, 0.8).tolist() == parent and 6 < len(set(parent)) < 90


# ---- token edits


@pytest.fixture(scope="module")
def count():
    return token_edits.counter(token_edits.default_vocabulary())


PIECES = ["a", " ", "  ", "\n", "'", "'re", "r", "e", "s", "é", "日本", "12", "3", "!", "..", "\t", " the", "don't", " ", "🙂", "_"]


def sums_hold(node):
    if node is None:
        return [0, 0, 0, 0]
    below = [a + b for a, b in zip(sums_hold(node.left), sums_hold(node.right), strict=True)]
    own = [1, sum(map(len, node.pieces)), len(node.pieces), sum(node.counts)]
    assert [node.size, node.chars, node.segments, node.tokens] == [a + b for a, b in zip(below, own, strict=True)]
    return [node.size, node.chars, node.segments, node.tokens]


@pytest.mark.parametrize("leaf,look", [(2, 1), (64, 256)])
@settings(max_examples=300, deadline=None)
@given(st.lists(st.sampled_from(PIECES), max_size=40), st.lists(st.tuples(st.integers(0, 60), st.integers(0, 8), st.lists(st.sampled_from(PIECES), max_size=4)), max_size=4))
def test_edits_equal_recount(leaf, look, text, edits):
    count = token_edits.counter(token_edits.default_vocabulary())
    before = token_edits.LEAF, token_edits.LOOK
    token_edits.LEAF, token_edits.LOOK = leaf, look
    try:
        text = "".join(text)
        tree = token_edits.CountTree(text, count)
        for start, length, new in edits:
            tree.edit(start, length, "".join(new))
            at = min(start, len(text))
            text = text[:at] + "".join(new) + text[at + length :]
            assert tree.text == text and tree.total == len(count.encoding.encode_ordinary(text))
            assert tree.pieces == count.pieces(text)
            sums_hold(tree.root)
    finally:
        token_edits.LEAF, token_edits.LOOK = before


def test_edits_stay_local(count):
    """Leaves added and taken away: little is encoded, few nodes are touched, whatever the text's length."""
    for words in (2_000, 50_000):
        tree = token_edits.CountTree("some words here " * words, count)
        tree.touched = 0
        for k in range(50):
            tree.edit(16 * (words // 60) * (k + 5), 4 + k % 3, "more and more, or" if k % 2 else "")
        assert tree.encoded < 50 * 100 and tree.touched < 50 * 120
        assert tree.total == len(count.encoding.encode_ordinary(tree.text))


def test_overlapping_edits(count):
    tree = token_edits.CountTree("0123456789", count)
    token_edits.apply_edits(tree, [(2, 4, "x"), (4, 3, "y"), (9, 50, "z"), (-3, 1, "s")])
    assert tree.text == "s01xy78z"


# ---- urls


@settings(max_examples=200, deadline=None)
@given(st.lists(st.text("abc", max_size=4), max_size=12), st.text("abc", max_size=6))
def test_longest_prefix(prefixes, path):
    prefixes = sorted(set(prefixes))
    i = urls.longest_prefix(prefixes, path)
    want = max((p for p in prefixes if path.startswith(p)), key=len, default=None)
    assert (prefixes[i] if i >= 0 else None) == want


def test_sweep_is_brute():
    r = random.Random(5)
    host = lambda: ".".join(r.choice("ab") for _ in range(r.randrange(1, 5)))
    path = lambda: "/" + "".join(r.choice("xy/") for _ in range(r.randrange(4)))
    rules = [(host(), path(), r.choice(["allow", "block"])) for _ in range(60)]
    hosts, paths = zip(*[(host(), path()) for _ in range(500)], strict=True)
    rule, verdict = urls.sweep(list(hosts), list(paths), urls.prepare(rules))
    for h, p, x, v in zip(hosts, paths, rule, verdict, strict=True):
        fit = [(len(a + b), len(a), c == "block", a + b, c) for a, b, c in rules if (h == a or h.endswith("." + a)) and p.startswith(b)]
        assert (x, v) == (max(fit)[3:] if fit else (None, None))


def test_ranges_are_brute(spark):
    """Many rules: dealt in ranges with the URLs, a third of which are of one host; hosts nest over ranges' edges."""
    r = random.Random(6)
    host = lambda: ".".join(r.choice("abc") for _ in range(r.randrange(1, 5)))
    path = lambda: "/" + "".join(r.choice("xy/") for _ in range(r.randrange(4)))
    rules = [(host(), path(), r.choice(["allow", "block"])) for _ in range(150)] + [("a", "/", "block"), ("A", "/", "allow")]
    rows = [(k, "h://" + ("a.b.a" if k % 3 == 0 else host()) + path()) for k in range(1500)]
    df, given = spark.createDataFrame(rows, "page_id long, url string"), spark.createDataFrame(rules, "host string, path string, verdict string")
    got = {x["page_id"]: (x["rule"], x["verdict"]) for x in urls.apply_rules(df, given, chunk_rules=10, default="none").collect()}
    assert len(got) == 1500 and got == {x["page_id"]: (x["rule"], x["verdict"]) for x in urls.apply_rules(df, given, default="none").collect()}
    for k, u in rows:
        h, p = u[4:].split("/", 1)
        fit = [(len(a + b), len(a), c == "block", a.lower() + b, c) for a, b, c in rules if (h == a.lower() or h.endswith("." + a.lower())) and ("/" + p).startswith(b)]
        assert got[k] == (max(fit)[3:] if fit else (None, "none")), u


# ---- telephony


def test_laws():
    mu, a = telephony.MU_TABLE, telephony.A_TABLE
    assert (mu[0xFF], mu[0x7F], mu[0x00], mu[0x80]) == (0, 0, -32124, 32124)
    assert (a[0xD5], a[0x55], a[0xAA], a[0x2A]) == (8, -8, 32256, -32256)
    assert len(set(mu.tolist())) == 255 and len(set(a.tolist())) == 256


def test_adpcm_blocks():
    r = np.random.default_rng(1)
    block = 36
    data = bytearray(r.integers(0, 256, block * 5, dtype=np.uint8).tobytes())
    for k in range(5):
        data[k * block + 2] %= 89
    got, want = telephony.decode_adpcm(bytes(data), block), []
    for k in range(5):
        b = data[k * block : (k + 1) * block]
        value, index = int.from_bytes(b[:2], "little", signed=True), b[2]
        want.append(value)
        for byte in b[4:]:
            for code in (byte & 15, byte >> 4):
                step = int(telephony.IMA_STEP[index])
                move = (step >> 3) + (step if code & 4 else 0) + (step >> 1 if code & 2 else 0) + (step >> 2 if code & 1 else 0)
                value = max(-32768, min(32767, value - move if code & 8 else value + move))
                index = max(0, min(88, index + int(telephony.IMA_MOVE[code])))
                want.append(value)
    assert got.tolist() == want


@pytest.mark.parametrize("form", [telephony.A_LAW, telephony.MU_LAW])
def test_wave_round_trip(form):
    for payload in (b"\x00\xff" * 96, b"x" * 193):
        assert telephony.read_wave(telephony.wave(payload, form)) == (form, 8000, 1, payload)
    blocks = bytes(range(36)) * 3
    assert telephony.read_wave(telephony.wave(blocks, telephony.IMA_ADPCM, block=36))[2:] == (36, blocks)
    with pytest.raises(ValueError):
        telephony.read_wave(b"RIFFxxxxAVI ")


def test_resampled(spark):
    assert telephony.doubled(np.array([0, 10, -3], np.int16)).tolist() == [0, 5, 10, 3, -3, -3]
    for form, n in ((telephony.MU_LAW, 192), (telephony.A_LAW, 192), (telephony.IMA_ADPCM, 370)):
        media = spark.createDataFrame([("ab",), (None,)], "t string").select(telephony.decoded_pcm(telephony.stored_media(F.col("t"), form)).alias("p")).collect()
        assert [len(m["p"]) for m in media] == [n * 4] * 2


def test_pcm_is_stored(spark, tmp_path, monkeypatch):
    """Stored PCM is what each medium decodes to by itself, though ADPCM blocks are decoded across media."""
    docs = spark.createDataFrame([(i, "some text " * (i * 7 % 90)) for i in range(60)], "doc_id long, text string")
    telephony.store_pcm(docs, f"{tmp_path}/pcm")
    got = {r["doc_id"]: r["pcm"] for r in spark.read.parquet(f"{tmp_path}/pcm").collect()}
    forms = set()
    for r in telephony.media_table(docs).collect():
        form, _, block, payload = telephony.read_wave(bytes(r["media"]))
        forms.add(form)
        assert bytes(got[r["doc_id"]]) == telephony.doubled(telephony.pcm(form, block, payload)).astype("<i2").tobytes()
    assert len(got) == 60 and forms == {6, 7, 17}
    monkeypatch.setattr(telephony, "STRETCH", 300)
    media = [bytes(r["media"]) for r in telephony.media_table(docs).collect()] + [None]
    assert [None if x is None else x.tolist() for _, x in telephony.decoded(media)] == [None if m is None else telephony.pcm(f[0], f[2], f[3]).tolist() for m in media for f in [m and telephony.read_wave(m)]]


# ---- packing and mixing


def test_encoder_special_runs():
    e = packing.encoder(packing.os.path.join(packing.local_tokenizers(), "word_bpe_49k.json"))
    texts = ["it's we'RE <|endoftext|> x<|startoftext|>y", "a\x1cb c　d \x85e", "Été ΣΑΣ İstanbul ﬁx H̱ ẖ", "!!!''' ''s don't. 3rd,, a_b ́x", "", "ß² ½a", "  lead trail  ", "\n\t", "THE!! the!! The,$%"]
    for t, got in zip(texts, e.texts(pa.array(texts), 2), strict=True):
        assert got.tolist() == [*e.tokenizer.encode(t, add_special_tokens=False).ids, 2], t


HARD = [*"İıŞßẞÉéΣσςﬁK Å\u0958\ufb1d\u0307\u0301\u0345ªºǅ𝐀ᄀ\u1161가½²٣日ー々'’_-.,!?()<>|~^$\x1c\x85\xa0\u3000 \tabXYZ09", "'s", "<|endoftext|>", "İ,", "i\u0307"]


@settings(max_examples=500, deadline=None)
@given(st.lists(st.one_of(st.sampled_from(HARD), st.characters(blacklist_categories=["Cs"])), max_size=14))
def test_encoder_is_tokenizer(parts):
    e, text = packing.encoder(packing.os.path.join(packing.local_tokenizers(), "word_bpe_49k.json")), "".join(parts)
    assert e.texts(pa.array([text]), 2)[0].tolist() == [*e.tokenizer.encode(text, add_special_tokens=False).ids, 2]


def test_encoder_letters_before_marks():
    """Each letter there is, before marks: some are normalised into a letter and a mark, which the marks join."""
    e = packing.encoder(packing.os.path.join(packing.local_tokenizers(), "word_bpe_49k.json"))
    texts = [f"x{c}!? {c}," for c in map(chr, range(0x80, 0x30000)) if c.isalpha()]
    for t, got, want in zip(texts, e.texts(pa.array(texts), 2), e.tokenizer.encode_batch_fast(texts, add_special_tokens=False), strict=True):
        assert got.tolist() == [*want.ids, 2], t


def test_wide_ids(spark):
    """Ids of 65,536 and more are kept in four bytes."""
    docs = spark.createDataFrame([(1, "a b c"), (2, None)], "doc_id long, text string")
    got = {r["doc_id"]: np.frombuffer(r["ids"], "<u4").tolist() for r in packing.pack(docs, end_id=70_000).collect()}
    assert got[1][-1] == got[2][-1] == 70_000 and len(got[1]) == 4
    with pytest.raises(ValueError):
        packing.pack(docs, end_id=2**32)


def test_generations_turn_over(monkeypatch):
    monkeypatch.setattr(packing, "REMEMBER", 10)
    e = packing.WordEncoder(packing.os.path.join(packing.local_tokenizers(), "word_bpe_49k.json"))
    r = random.Random(2)
    texts = [" ".join("".join(r.choice("abcde") for _ in range(r.randrange(1, 7))) + r.choice(["", ".", "'s"]) for _ in range(30)) for _ in range(40)]
    for _ in range(2):
        for t in texts:
            assert e.texts(pa.array([t]), 2)[0].tolist() == [*e.tokenizer.encode(t, add_special_tokens=False).ids, 2]


@pytest.mark.parametrize("words,length", [(128, 128), (100, 100)])
def test_tail_padding(spark, words, length):
    docs = spark.createDataFrame([(1, "a " * (words - 1))], "doc_id long, text string")
    got = packing.pack(docs, window=4096).first()
    assert got["length"] == length and got["padding"] == (0 if words == 128 else 4096 - 100)


def test_water_filling():
    t = mixing.fill({"a": 100, "b": 100, "c": 100, None: 10}, (5.0, 2.0, 1.0), 1.5, 2.0)
    assert t["a"] == 200 and t[None] == 20 and abs(sum(t.values()) - 465) < 1e-9 and abs(t["b"] / t["c"] - 2) < 0.7
    assert mixing.fill({}, (1.0,), 1.5, 2.0) == {} and mixing.fill({"a": 0}, (1.0,), 1.5, 2.0) == {"a": 0.0}


def test_permutation(spark):
    """Every place has one image, also where the network's numbers go over n, and neighbours scatter."""
    for n in (1, 2, 3, 4, 5, 7, 11, 64, 997, 10_007):
        a, b = mixing.sides(n)
        assert a * b >= n and (n < 50 or a * b - n < 3)
        rows = spark.range(n).select("id", F.lit(n).cast("long").alias("n"), F.lit(a).cast("long").alias("a"), F.lit(b).cast("long").alias("b"))
        got = [r["image"] for r in mixing.permuted(rows, "id", "n", "a", "b", "image", F.lit(3)).orderBy("id").collect()]
        assert sorted(got) == list(range(n))
    assert len(set(np.diff(got).tolist())) > 5000 and abs(np.corrcoef(np.arange(n), got)[0, 1]) < 0.05


def test_draws_are_multinomial(spark):
    """Counts by shard sum to a source's slots, spread as a multinomial's do, and the slots follow one another."""
    sources = spark.createDataFrame([(0, 20_000), (1, 300), (2, 0)], "source_no int, slots long")
    got = mixing.draws(sources, 100, 42).toPandas().sort_values(["source_no", "shard"])
    by = {s: g for s, g in got.groupby("source_no")}
    assert set(by) == {0, 1} and by[0].n.sum() == 20_000 and by[1].n.sum() == 300
    assert all(g["first"].tolist() == [0, *g.n.cumsum().tolist()[:-1]] for g in by.values())
    assert abs(((by[0].n - 200) ** 2 / 200).sum() - 99) < 5 * (2 * 99) ** 0.5


def test_mixed_blocks(spark):
    """Shards hold their drawn slots, every slot the words of its block, and all of them the documents' taken words."""
    docs = spark.createDataFrame([(i, " ".join(f"d{i}w{k}" for k in range(i % 41)), "s" if i % 3 else "t") for i in range(400)], "doc_id long, text string, source string")
    how = {"block": 16, "shard_words": 900}
    blocks = mixing.mixed_blocks(docs, **how).toPandas()
    assert (blocks.text.str.split().map(len) == blocks.words).all() and blocks.shard.nunique() > 5
    for _, g in blocks.sort_values(["shard", "slot"]).groupby("source_no"):
        assert g.slot.tolist() == list(range(len(g))) and (g.words == 16).sum() >= len(g) - 4
    said = sorted(w for t in blocks.text for w in t.split())
    assert said == sorted(w for r in mixing.mixed_documents(docs, **how).collect() for w in r["text"].split())


def test_mix_copies(spark):
    """Hundreds of identical rows have places of their own."""
    rows = [(None, "a b c", "s")] * 700 + [(1, "x y", "s")] * 2 + [(2, "z", None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    placed, _ = mixing.mix(docs, block=8)
    got = placed.where("source = 's'").orderBy("rank").collect()
    assert [r["rank"] for r in got] == list(range(702)) and [r["at"] for r in got] == np.concatenate(([0], np.cumsum([r["size"] for r in got])[:-1])).tolist()
    assert sorted(r["copy"] for r in got if r["doc_id"] is None) == list(range(1, 701))
    assert mixing.mixed_documents(docs, block=8).count() >= 703


def test_mix_places_are_a_stream(spark):
    docs = spark.createDataFrame([(i, "w " * (i % 23), "s" if i % 3 else "t") for i in range(500)], "doc_id long, text string, source string")
    placed, pieces = mixing.mix(docs, block=8)
    by = {}
    for r in placed.collect():
        by.setdefault(r["source"], []).append((r["at"], r["rank"], r["size"]))
    for rows in by.values():
        rows.sort(key=lambda x: x[1])
        assert [r[1] for r in rows] == list(range(len(rows)))
        at = 0
        for a, _, n in rows:
            assert a == at
            at += n
    assert pieces.where("lo < 0 or hi <= lo").count() == 0


# ---- quality, neighbours, fixity


def test_shrinkage(spark):
    rows = [("big", "p", 0.9)] * 2000 + [("big", "q", 0.1)] * 2000 + [("bad", "p", 0.05)] * 1000 + [("bad", "p", 0.15)] * 1000 + [("tiny", "p", 0.0)] + [("new", "z", 1.0)] + [("mute", "m", None)]
    said = spark.createDataFrame(rows, "host string, path string, p double").withColumn("evidence", F.log((F.col("p") + 1e-9) / (1 - F.col("p") + 1e-9)))
    sites = quality.site_sums(said)
    assert sites.n == 6002 and abs(sites.s - 2201) < 1e-6 and sites.host_weight < 100 and sites.path_weight < 100
    got = {(r["host"], r["path"]): r for r in quality.judged(said, sites).collect()}
    assert abs(got["big", "p"]["path_posterior"] - 0.9) < 0.02 and abs(got["big", "q"]["path_posterior"] - 0.1) < 0.02 and abs(got["bad", "p"]["path_posterior"] - 0.1) < 0.02
    # alone on their site: its own probability does not come back
    assert abs(got["tiny", "p"]["path_posterior"] - 2201 / 6002) < 1e-3 and abs(got["new", "z"]["path_posterior"] - 2201 / 6002) < 1e-3 and got["mute", "m"]["posterior"] == 0


def test_weight_is_moments():
    """The weight of the level above, from groups drawn with known variances."""
    r = np.random.default_rng(1)
    groups = [r.normal(m, 0.3, r.integers(20, 60)) for m in r.normal(0.5, 0.1, 3000)]
    x, n = np.concatenate(groups), np.array([len(g) for g in groups])
    means = sum(len(g) * g.mean() ** 2 for g in groups)
    assert abs(quality.weight(len(x), (x**2).sum(), means, len(x) * x.mean() ** 2, len(n), 1, len(x) - (n**2).sum() / len(x)) - 9) < 1.5


def test_logistic():
    r = np.random.default_rng(0)
    x = r.normal(size=(400, 3))
    y = (x[:, 0] - x[:, 1] > 0).astype(float)
    w = quality.fit_logistic(x, y)
    assert (((x @ w[:3] + w[3]) > 0) == (y == 1)).mean() > 0.97
    assert not quality.fit_logistic(x, np.ones(400)).any()


@pytest.mark.parametrize("block", [64, 4096])
def test_hot_vector(spark, block):
    """A third of all vectors are the same: they fill several blocks of one list, and ties still go by id."""
    r = np.random.default_rng(4)
    v = r.normal(size=(600, 16)).astype(np.float32)
    v[::3] = v[0]
    df = spark.createDataFrame([(i, [float(a) for a in x]) for i, x in enumerate(v)], "vec_id long, embedding array<float>")
    got = ivfpq.search(df, F.pmod("vec_id", F.lit(20)) == 0, k=5, block=block).collect()
    d, hit, n = v.astype(float), 0, 0
    for q in range(0, 600, 20):
        s = d @ d[q]
        s[q] = -np.inf
        if q % 3 == 0:
            s[::3] = np.where(np.arange(0, 600, 3) == q, -np.inf, s[3 if q == 0 else 0])
        best = np.lexsort((np.arange(600), -np.round(s, 9)))[:5].tolist()
        mine = [x["vec_id"] for x in sorted((x for x in got if x["query_id"] == q), key=lambda x: x["rank"])]
        hit, n = hit + len(set(best) & set(mine)), n + 5
        if q % 3 == 0 and best == sorted(best):
            assert mine == best
    assert hit / n >= 0.9


def test_merkle_levels(spark):
    pages = spark.createDataFrame([(i, f"u{i}", "h") for i in range(300)], "page_id long, url string, html string")
    t = fixity.tree(fixity.manifest(pages, 512))
    sizes = {r["level"]: r["count"] for r in t.groupBy("level").count().collect()}
    assert sizes == {0: 300, 1: 19, 2: 2, 3: 1}


def test_tight_cluster(spark):
    """Vectors so close that their codes are alike are still ranked exactly."""
    r = np.random.default_rng(9)
    v = r.normal(size=(900, 32))
    v[:300] = v[0] + 0.01 * r.normal(size=(300, 32))
    v = (v / np.linalg.norm(v, axis=1, keepdims=True)).astype(np.float32)
    df = spark.createDataFrame([(i, [float(a) for a in x]) for i, x in enumerate(v)], "vec_id long, embedding array<float>")
    got = ivfpq.search(df, F.col("vec_id") < 300, k=10, shortlist=20).where("query_id % 20 = 0").collect()
    d, hit = v.astype(float), 0
    for q in range(0, 300, 20):
        s = d @ d[q]
        s[q] = -np.inf
        hit += len(set(np.lexsort((np.arange(900), -s))[:10].tolist()) & {x["vec_id"] for x in got if x["query_id"] == q})
    assert hit / 150 >= 0.95


def test_rescored_is_exact():
    r = np.random.default_rng(2)
    x, q = r.normal(size=(200, 8)), r.normal(size=(5, 8))
    ids = np.arange(200) * 3
    rough = q @ x.T + 0.1 * r.normal(size=(5, 200))
    rough[0, 7] = -np.inf
    who, vec, score = ivfpq.rescored(rough, q, np.arange(5), ids, x, 20, 6)
    for k in range(5):
        s = q[k] @ x.T
        if k == 0:
            s[7] = -np.inf
        assert len(set(vec[who == k].tolist()) & set(ids[np.argsort(-s)[:6]].tolist())) >= 5
        assert np.allclose(score[who == k], sorted(s[vec[who == k] // 3], reverse=True))
    few = ivfpq.rescored(rough[:, :3], q, np.arange(5), ids[:3], x[:3], 20, 6)
    assert len(few[0]) == 15
