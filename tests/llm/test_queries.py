"""The registered queries on the given tables, against SQL or brute force."""

import hashlib
import re
import struct
import zlib

import numpy as np
import pandas as pd
import pytest
import xxhash
from pyspark.sql import functions as F

from tests.oracle import same
from tidegate.llm import quality, telephony
from tidegate.llm import queries as q

SF = "/root/testdata/sf0.01"


@pytest.mark.parametrize("name", sorted(q.ORACLES))
def test_against_sql(spark, name):
    same(q.QUERIES[name](spark, SF), SF, q.ORACLES[name])


def test_quality_held_out(spark):
    """Fitted on one half of the labels, judged on the other."""
    docs, labels = (spark.read.parquet(f"{SF}/{t}.parquet") for t in ("documents", "labels"))
    mine = F.pmod(F.xxhash64("doc_id"), F.lit(2)) == 0
    got = quality.quality_table(docs, labels.where(mine)).toPandas().merge(labels.where(~mine).toPandas(), on="doc_id")
    assert (got.keep == (got.quality == 1)).mean() > 0.95
    assert got[got.quality == 1].keep.mean() > 0.97


def test_quality_brute(spark):
    """The query against plain loops: evidence, and posteriors that leave the document out."""
    docs, labels = (spark.read.parquet(f"{SF}/{t}.parquet").toPandas() for t in ("documents", "labels"))
    x = {d: quality.features((t or "").encode()) for d, t in zip(docs.doc_id, docs.text, strict=True)}
    known = labels[labels.quality.isin([0, 1])]
    w = quality.fit_logistic(np.array([x[d] for d in known.doc_id]), known.quality.to_numpy(float))
    docs["evidence"] = [float(np.clip(x[d] @ w[:-1] + w[-1], -30, 30)) if t else np.nan for d, t in zip(docs.doc_id, docs.text, strict=True)]
    docs["p"] = 1 / (1 + np.exp(-docs.evidence))
    docs["lang"] = docs.lang.fillna("none")
    docs["source"] = docs.source.fillna("none")
    good = docs[docs.p.notna()]
    hosts, paths = [g.p.to_numpy() for _, g in good.groupby("source")], {k: g.p.to_numpy() for k, g in good.groupby(["source", "lang"])}

    def prior(groups, means, parents, room):
        noise = sum(((g - g.mean()) ** 2).sum() for g in groups) / max(1, len(good) - len(groups))
        between = max(0, (sum(len(g) * (g.mean() - m) ** 2 for g, m in zip(groups, means, strict=True)) - (len(groups) - parents) * noise) / room) if room > 1e-9 else 0
        return min(max(noise / between, 1.0), 1e6) if between > 1e-12 else 1e6

    n = len(good)
    kh = prior(hosts, [good.p.mean()] * len(hosts), 1, n - sum(len(g) ** 2 for g in hosts) / n)
    of = {k: g.p.to_numpy() for k, g in good.groupby("source")}
    kp = prior(list(paths.values()), [of[h].mean() for h, _ in paths], len(hosts), n - sum(len(g) ** 2 / len(of[h]) for (h, _), g in paths.items()))
    got = q.op1_quality_bayes(spark, SF).toPandas().set_index("doc_id")
    inside = lambda v: min(max(v, 0.001), 0.999)
    odds = lambda v: np.log(inside(v) / (1 - inside(v)))
    for r in docs.itertuples():
        g = got.loc[r.doc_id]
        if np.isnan(r.p):
            assert g.posterior == 0 and not g.keep
            continue
        mean = inside((good.p.sum() - r.p + 0.5) / n)
        host = (of[r.source].sum() - r.p + kh * mean) / (len(of[r.source]) - 1 + kh)
        path = (paths[r.source, r.lang].sum() - r.p + kp * host) / (len(paths[r.source, r.lang]) - 1 + kp)
        want = 1 / (1 + np.exp(-(r.evidence + odds(path) - odds(mean))))
        assert np.allclose([g.evidence, g.host_posterior, g.path_posterior, g.posterior], [r.evidence, host, path, want], rtol=1e-5, atol=1e-7), r.doc_id
        assert g.keep == (g.posterior >= 0.5)


def fold(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text or "")


def brute_fingerprint(text):
    w = re.findall(r"[^\x20\x09-\x0D]+", fold(text))
    sh = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] or ([" ".join(w)] if w else [])
    h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in sh]
    return sum(1 << b for b in range(64) if sum(x >> b & 1 for x in h) * 2 > len(h))


def test_simhash_brute(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").toPandas()
    got = q.op5_simhash_classes(spark, SF).toPandas().set_index("doc_id")
    fp = {d: brute_fingerprint(t) for d, t in zip(docs.doc_id, docs.text, strict=True)}
    assert all(got.fingerprint[d] == f"{f:016x}" for d, f in fp.items())
    ids, x = list(fp), np.array(list(fp.values()), np.uint64)
    near = np.bitwise_count(x[:, None] ^ x[None, :]) <= 2
    parent = {d: d for d in ids}

    def root(d):
        while parent[d] != d:
            d = parent[d]
        return d

    for i, j in zip(*np.nonzero(near), strict=True):
        a, b = sorted((root(ids[i]), root(ids[j])))
        parent[b] = a
    assert all(got.component_id[d] == root(d) for d in ids)
    assert got.component_id.nunique() < len(ids)


def test_packing_whole(spark):
    import public_tokenizers
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    docs = spark.read.parquet(f"{SF}/documents.parquet").toPandas().set_index("doc_id")
    got = q.op6_packed_pieces(spark, SF).toPandas()
    for d, g in got.sort_values("start").groupby("doc_id"):
        ids = [*t.encode(docs.text[d], add_special_tokens=False).ids, 2]
        at = 0
        for r in g.itertuples():
            assert (r.start, r.doc_tokens) == (at, len(ids))
            assert r.ids_crc32 == zlib.crc32(np.array(ids[at : at + r.length], "<u4").tobytes())
            at += r.length
        assert at == len(ids)
    for s, g in got.sort_values("offset").groupby("sequence_id"):
        assert g.offset.tolist() == [0, *g.length.cumsum().tolist()[:-1]]
        assert g.length.sum() == 4096 or s == got.sequence_id.max()
    assert set(got.doc_id) == set(docs.index)


def test_mix_targets(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").toPandas().set_index("doc_id")
    got = q.op7_source_mix(spark, SF).toPandas().set_index("doc_id")
    assert (got.loc[docs.index, "size"] == docs.text.map(lambda t: len(re.findall(r"[^\x20\x09-\x0D]+", t)))).all()
    got["source"] = docs.source
    by = got.groupby("source").agg(size=("size", "sum"), source_size=("source_size", "first"), target=("target", "first"), taken=("taken", "sum"))
    assert (by["size"] == by.source_size).all() and abs(by.target.sum() - 1.5 * by["size"].sum()) < 1e-3
    assert (by.taken - by.target).abs().max() <= 1
    assert (got.taken <= 2 * got["size"]).all() and (by.target <= 2 * by.source_size + 1e-6).all()
    again = q.op7_source_mix(spark, SF).toPandas().set_index("doc_id")
    assert (again.taken == got.taken.loc[again.index]).all()


def plain_media(payload):
    """Media and features by loops over samples, of the format that the payload's checksum chooses."""
    form = (7, 6, 17)[zlib.crc32(payload) % 3]
    block = 96 if form == 17 else 1
    said = struct.pack("<HHIIHHH", form, 1, 8000, 8000 * 96 // 185 if form == 17 else 8000, block, 4 if form == 17 else 8, 2 if form == 17 else 0) + (struct.pack("<H", 185) if form == 17 else b"")
    n = len(payload) // 96 * 185 if form == 17 else len(payload)
    chunks = b"".join(k + struct.pack("<I", len(v)) + v for k, v in ((b"fmt ", said), (b"fact", struct.pack("<I", n)), (b"data", payload)))
    media, x = b"RIFF" + struct.pack("<I", 4 + len(chunks)) + b"WAVE" + chunks, []
    if form == 17:
        for at in range(0, len(payload), 96):
            b = payload[at : at + 96]
            value, index = int.from_bytes(b[:2], "little", signed=True), min(b[2], 88)
            x.append(value)
            for code in (c for byte in b[4:] for c in (byte & 15, byte >> 4)):
                step = int(telephony.IMA_STEP[index])
                move = (step >> 3) + (step if code & 4 else 0) + (step >> 1 if code & 2 else 0) + (step >> 2 if code & 1 else 0)
                value = max(-32768, min(32767, value - move if code & 8 else value + move))
                index = max(0, min(88, index + int(telephony.IMA_MOVE[code])))
                x.append(value)
    else:
        x = [int((telephony.MU_TABLE if form == 7 else telephony.A_TABLE)[b]) for b in payload]
    y = [v for a, b in zip(x, x[1:] + x[-1:], strict=True) for v in (a, (a + b) >> 1)]
    crossings = sum((a < 0) != (b < 0) for a, b in zip(y, y[1:], strict=False))
    return media, form, f"n={len(y)};peak={max(map(abs, y))};power={sum(v * v for v in y) // len(y)};crossings={crossings};crc={zlib.crc32(struct.pack(f'<{len(y)}h', *y)):08x}"


def test_media_read_back(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").toPandas().set_index("doc_id")
    got = q.op8_telephony_media(spark, SF).toPandas()
    assert set(got.format) == {6, 7, 17} and len(got) == len(docs)
    for k, r in enumerate(got.itertuples()):
        raw = docs.text[r.doc_id].encode()
        want = raw.ljust(max(1, -(-len(raw) // 192)) * 192, b" ")
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(raw), len(want), hashlib.sha256(want).hexdigest(), zlib.crc32(want[-16:]))
        if k % 20 == 0:  # loops over samples are slow
            media, form, feature = plain_media(want)
            assert (r.media_bytes, r.media_sha256, r.format, r.feature) == (len(media), hashlib.sha256(media).hexdigest(), form, feature)


def test_neighbours_recall(spark):
    e = spark.read.parquet(f"{SF}/embeddings.parquet").toPandas()
    x, ids = np.stack(e.embedding.values).astype(float), e.vec_id.values
    got = q.op10_ivf_pq(spark, SF).toPandas()
    hit = n = 0
    for d, g in got.sort_values("rank").groupby("query_id"):
        score = x @ x[ids == d][0]
        score[ids == d] = -np.inf
        best = ids[np.lexsort((ids, -score))[:20]]
        hit, n = hit + len(set(best) & set(g.vec_id)), n + 20
        assert g["rank"].tolist() == list(range(1, 21))
        assert np.allclose(g.score, [x[ids == v][0] @ x[ids == d][0] for v in g.vec_id], atol=1e-12)
    assert n == 20 * (ids % 20 == 0).sum() and hit / n >= 0.9


def test_edit_counts_whole(spark):
    from tidegate.llm.token_edits import PERSONAL, counter, default_vocabulary

    docs = spark.read.parquet(f"{SF}/documents.parquet").toPandas().set_index("doc_id")
    got = q.op2_edit_token_counts(spark, SF).toPandas()
    c = counter(default_vocabulary())
    assert len(got) == len(docs) and got.n_edits.sum() > 0
    size = lambda t: len(c.encoding.encode_ordinary(t))
    for r in got.itertuples():
        text, (redacted, n) = docs.text[r.doc_id], re.subn(PERSONAL, "[redacted]", docs.text[r.doc_id])
        assert (r.n_tokens, r.n_edits, r.edited_tokens, r.edited_chars) == (size(text), n, size(redacted), len(redacted))
        assert n or not r.reencoded_chars


def test_pipeline_brute(spark):
    """Each stage on what the one before it kept, against plain versions."""
    from collections import Counter, defaultdict

    import public_tokenizers
    from tokenizers import Tokenizer

    import corpus_pipeline

    stages = dict(corpus_pipeline.STAGES)
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    start = docs.toPandas()

    judged = q.op1_quality_bayes(spark, SF).toPandas()  # held against loops above
    good = stages["quality"](spark, docs, SF).toPandas()
    assert Counter(good.doc_id) == Counter(judged.doc_id[judged.keep]) and len(good) < len(start)

    unlike = stages["near_copies"](spark, spark.createDataFrame(good), SF).toPandas()
    sets, holds = {}, defaultdict(list)
    for d, t in zip(good.doc_id, good.text, strict=True):
        w = re.findall(r"[^\x20\x09-\x0D]+", fold(t))
        sets[d] = {tuple(w[i : i + 5]) for i in range(len(w) - 4)} or {tuple(w)}
        for sh in sets[d]:
            holds[sh].append(d)
    parent = {d: d for d in sets}

    def root(d):
        while parent[d] != d:
            d = parent[d]
        return d

    common = Counter((a, b) for ds in holds.values() for i, a in enumerate(ds) for b in ds[i + 1 :])
    for (a, b), n in common.items():
        if n / (len(sets[a]) + len(sets[b]) - n) >= 0.8:
            x, y = sorted((root(a), root(b)))
            parent[y] = x
    assert set(unlike.doc_id) == {d for d in sets if root(d) == d} and len(unlike) < len(good)

    mixed = stages["mixing"](spark, spark.createDataFrame(unlike), SF).toPandas()
    words = {r.doc_id: r.text.split() for r in unlike.itertuples()}
    size = {d: len(w) for d, w in words.items()}
    by = unlike.assign(size=unlike.doc_id.map(size)).groupby("source")["size"].sum()
    took = mixed.assign(size=mixed.text.str.split().map(len)).groupby("source")["size"].sum()
    target = fill_plainly(dict(by))
    assert all(abs(took[s] - target[s]) <= 1 for s in target)
    for r in mixed.itertuples():
        assert not Counter(r.text.split()) - Counter(words[r.doc_id])
    assert max(mixed.groupby("doc_id").text.apply(lambda t: sum(len(x.split()) for x in t)) / pd.Series(size)) <= 2

    t = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    pieces = stages["packing"](spark, spark.createDataFrame(mixed), SF).toPandas().sort_values(["sequence_id", "offset"])
    want = Counter()
    for r in mixed.itertuples():
        want[r.doc_id, len(t.encode(r.text, add_special_tokens=False).ids) + 1] += 1
    assert Counter((r.doc_id, r.doc_tokens) for r in pieces[pieces.start == 0].itertuples()) == want
    assert pieces.length.sum() == pieces[pieces.start == 0].doc_tokens.sum()


def fill_plainly(sizes):
    """Targets: 150 % of all words by weight, none above twice its source's, the excess reshared."""
    order = sorted(sizes)
    weight, fixed = {s: (5, 2, 1)[i % 3] for i, s in enumerate(order)}, {}
    while True:
        left, free = 1.5 * sum(sizes.values()) - sum(fixed.values()), [s for s in order if s not in fixed]
        share = {s: left * weight[s] / sum(weight[x] for x in free) for s in free}
        over = [s for s in free if share[s] > 2 * sizes[s]]
        if not over:
            return fixed | share
        fixed |= {s: 2 * sizes[s] for s in over}
