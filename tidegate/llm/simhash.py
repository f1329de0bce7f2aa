"""SimHash near-duplicates by bit-sliced comparison.

fingerprints   a document's words (A-Z lower-cased, parted at ASCII white space) give n-word shingles, each hashed by XXH64;
               a bit of the fingerprint is 1 if more than half of the hashes have it. More than 64 bits come from further
               mixes of the same hash. Fewer words than n: the whole sequence is the shingle; none: all bits 0.
blocks         rows that may be near each other share a key. `piece_keys`: the fingerprint is cut into pieces and every
               choice of pieces that must agree within the radius is a key, so no pair is missed. `band_keys`: least hashes
               of the shingle set under several mixes, taken in bands (for wide fingerprints and similarity limits).
bit slices     a block's fingerprints are stored as bit planes, 64 rows to a word. Distances of one row to 64 others are
               counted at once by carry-save adders over the planes; a block is left as soon as all its distances are
               over the radius.
confirmation   `near_copies` takes the near rows of a block only as a candidate group: its members' shingle sets are
               brought together and pairs are linked by their exact share of common shingles.
components     each block gives its spanning links only (rows minus one at most, however many pairs are near), and
               alternating large and small stars join them over all blocks.

Copies of one fingerprint (near_copies: of one shingle set) are one node. Keys with over HOT nodes are dealt out again, by
further keys, and then by pairs of blocks.

Defined results: a null text is empty; empty texts have the fingerprint 0 (near_copies: the same empty set) and are copies of each other; of
equal ids the row with the least text hash comes first; repeated rows are one node, of which simhash_classes returns each and near_copies
one; an empty table gives no rows; extra columns are kept by near_copies, whatever their names, and left out by simhash_classes.
"""

from __future__ import annotations

from itertools import combinations
from math import comb

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tidegate.llm.common import LOWER_BYTES, arrow_function, arrow_rows, as_bytes, discard, give_back, splitmix, stored

HOT = 4096  # distinct fingerprints of a key; above, the key is split
LANES = 512  # rows compared at once
SEED = 42


# ---- fingerprints ------------------------------------------------------------------------------------------------


def shingle_hashes(text: bytes, n_words: int) -> np.ndarray:
    """XXH64 of each shingle of a text, repeats included."""
    words = text.translate(LOWER_BYTES).split()
    if not words:
        return np.empty(0, np.uint64)
    joined = b" ".join(words)
    if len(words) <= n_words:
        return np.array([xxhash.xxh64_intdigest(joined, SEED)], np.uint64)
    lengths = np.fromiter(map(len, words), np.int64, len(words))
    starts = np.concatenate(([0], np.cumsum(lengths + 1)[:-1]))
    first, end = starts[: len(words) - n_words + 1].tolist(), (starts + lengths)[n_words - 1 :].tolist()
    digest = xxhash.xxh64_intdigest
    return np.fromiter((digest(joined[a:b], SEED) for a, b in zip(first, end, strict=True)), np.uint64, len(first))


def majority(hashes: np.ndarray, words: int = 1) -> np.ndarray:
    """`words` x 64 fingerprint bits of shingle hashes, as unsigned numbers."""
    out = np.zeros(words, np.uint64)
    for w in range(words):
        count = np.zeros(64, np.int64)
        for at in range(0, len(hashes), 1 << 15):
            part = hashes[at : at + (1 << 15)]
            part = splitmix(part, w) if w else part
            count += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
        out[w] = np.packbits(count * 2 > len(hashes), bitorder="little").view(np.uint64)[0]
    return out


def least_hashes(hashes: np.ndarray, n: int) -> np.ndarray:
    """Least value of the set under each of n mixes; all ones for no hash."""
    if not len(hashes):
        return np.full(n, 2**64 - 1, np.uint64)
    odd = splitmix(np.arange(1, n + 1, dtype=np.uint64), 7) | np.uint64(1)
    with np.errstate(over="ignore"):
        return np.array([(hashes * a).min() for a in odd], np.uint64)


def sketch(text: Column, n_words: int, words: int, bands: int = 0, rows: int = 0, distinct: bool = False) -> Column:
    """struct<fp array<long>, bands array<long>, node long> of a text column; node: a hash of the shingle set."""

    @F.arrow_udf("struct<fp:array<long>,bands:array<long>,node:long>")
    def made(column: pa.Array) -> pa.Array:
        fps, keys, sets = [], [], []
        for text in as_bytes(column):
            h = shingle_hashes(text, n_words)
            if distinct:
                h = np.unique(h)
            fps.append(majority(h, words))
            sets.append(xxhash.xxh64_intdigest(h.tobytes(), SEED))
            if bands:
                least = least_hashes(h, bands * rows).reshape(bands, rows)
                mixed = least[:, 0]
                for r in range(1, rows):
                    mixed = splitmix(mixed ^ least[:, r], r)
                keys.append(mixed)
        give_back()
        n = len(fps)
        lists = lambda x, k: pa.ListArray.from_arrays(
            pa.array(np.arange(0, n * k + 1, k, dtype=np.int32) if k else np.zeros(n + 1, np.int32)), pa.array(np.concatenate(x).view(np.int64) if x else np.empty(0, np.int64))
        )
        node = pa.array(np.array(sets, np.uint64).view(np.int64))
        return pa.StructArray.from_arrays([lists(fps, words), lists(keys, bands), node], names=["fp", "bands", "node"])

    return made(text)


def shingle_sets(text: Column, n_words: int) -> Column:
    """array<long>: the distinct shingle hashes of a text, in order."""

    @arrow_function("array<long>")
    def made(column: pa.Array) -> pa.Array:
        sets = [np.unique(shingle_hashes(text, n_words)).view(np.int64) for text in as_bytes(column)]
        ends = np.concatenate(([0], np.cumsum([len(x) for x in sets], dtype=np.int64)))
        out = pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(np.concatenate(sets) if sets else np.empty(0, np.int64)))
        give_back()
        return out

    return made(text)


# ---- bit-sliced comparison ---------------------------------------------------------------------------------------


def planes_of(fps: np.ndarray) -> np.ndarray:
    """Bit planes (bits, words of 64 rows) of fingerprints (rows, words); missing rows are zero."""
    n, w = fps.shape
    padded = np.zeros((-(-n // 64) * 64, w), np.uint64)
    padded[:n] = fps
    bits = np.unpackbits(padded.view(np.uint8), axis=1, bitorder="little")
    return np.packbits(np.ascontiguousarray(bits.T), axis=1, bitorder="little").view(np.uint64)


def near(queries: np.ndarray, rows: np.ndarray, radius: int) -> np.ndarray:
    """Boolean (queries, rows): distance at most radius. Counts vertically over the planes of `rows`."""
    planes, n = planes_of(rows), len(rows)
    q = np.unpackbits(np.ascontiguousarray(queries).view(np.uint8), axis=1, bitorder="little").T  # (bits, queries)
    flips = np.where(q.astype(bool), np.uint64(2**64 - 1), np.uint64(0))
    bits, shape = len(planes), (len(queries), planes.shape[1])
    counter = [np.zeros(shape, np.uint64) for _ in range(bits.bit_length())]
    over = np.zeros(shape, np.uint64)
    spare = (-n) % 64
    unused = np.zeros(shape[1], np.uint64)
    if spare:
        unused[-1] = np.uint64(2**64 - 1) << np.uint64(64 - spare)

    def add(x, level):
        while level < len(counter):
            carry = counter[level] & x
            counter[level] ^= x
            x, level = carry, level + 1
            if not x.any():
                return

    for p in range(0, bits, 4):
        a, b, c, d = (planes[p + k][None, :] ^ flips[p + k][:, None] for k in range(4))
        # two carry-save adders: a + b + c + d = ones + 2 * (t1 + t2), and so on up the counter
        s1, t1 = a ^ b ^ c, (a & b) | (c & (a ^ b))
        ones, t2 = s1 ^ d, s1 & d
        add(ones, 0)
        add(t1 ^ t2, 1)
        add(t1 & t2, 2)
        if p + 4 >= bits or p % 16 == 12:
            over = _above(counter, radius) | unused[None, :]
            if (over == np.uint64(2**64 - 1)).all():
                return np.zeros((len(queries), n), bool)
    return ~np.unpackbits(np.ascontiguousarray(over).view(np.uint8), axis=1, bitorder="little")[:, :n].astype(bool)


def _above(counter: list[np.ndarray], radius: int) -> np.ndarray:
    """Lanes whose count, one bit a plane, is over the radius."""
    above, equal = np.zeros_like(counter[0]), np.full_like(counter[0], 2**64 - 1)
    for level in range(len(counter) - 1, -1, -1):
        if radius >> level & 1:
            equal &= counter[level]
        else:
            above |= equal & counter[level]
            equal &= ~counter[level]
    return above


def _roots(parent: np.ndarray) -> np.ndarray:
    while True:
        up = parent[parent]
        if (up == parent).all():
            return parent
        parent = up


def labels(fps: np.ndarray, radius: int) -> np.ndarray:
    """Component of each row: the least row that near rows lead to."""
    parent = np.arange(len(fps))
    for a in range(0, len(fps), LANES):
        for b in range(a, len(fps), LANES * 8):
            rows = slice(b, min(b + LANES * 8, len(fps)))
            if a and len(np.unique(parent[[*range(a, min(a + LANES, len(fps)))]])) == 1 and (parent[rows] == parent[a]).all():
                continue  # all of them are joined already
            i, j = np.nonzero(near(fps[a : a + LANES], fps[rows], radius))
            i, j = i + a, j + b
            i, j = i[i < j], j[i < j]
            while len(i):
                x, y = parent[i], parent[j]
                apart = x != y
                i, j, x, y = i[apart], j[apart], x[apart], y[apart]
                np.minimum.at(parent, np.maximum(x, y), np.minimum(x, y))
                parent = _roots(parent)
    return parent


def _groups(nodes: np.ndarray, root: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(group, node) of the components of two rows or more; equal components have equal groups, whatever key found them."""
    order = np.lexsort((nodes, root))
    again = (np.diff(root[order], prepend=-1) == 0) & (nodes[order] == np.roll(nodes[order], 1))  # a node under two keys
    order = order[~again]
    starts = np.flatnonzero(np.diff(root[order], prepend=-1))
    size = np.diff(starts, append=len(order))
    with np.errstate(over="ignore"):
        ids = np.add.reduceat(splitmix(nodes[order].view(np.uint64), 3), starts).view(np.int64)
    several = np.repeat(size > 1, size)
    return np.repeat(ids, size)[several], nodes[order][several]


def _link_blocks(radius: int, words: int, groups: bool = False):
    """mapInArrow over (key, node, fp) in order of key: the spanning links of the rows that share keys, or (group, node) of
    the components within each block."""

    def links(nodes, fps, keys):
        order = np.arange(len(nodes))
        if not len(keys):
            return
        cuts = [0, *(np.flatnonzero(keys[1:] != keys[:-1]) + 1).tolist(), len(keys)]
        at = 0
        for k in range(1, len(cuts)):
            # small groups are compared together; a link between two of them is as good as any
            if k + 1 < len(cuts) and cuts[k + 1] - at <= LANES:
                continue
            part = order[at : cuts[k]]
            at = cuts[k]
            if len(part) < 2:
                continue
            root = labels(fps[part], radius)
            off = nodes[part] != nodes[part[root]]  # the same node may be there under two keys
            if off.any() and groups:
                yield _groups(nodes[part], root)
            elif off.any():
                yield nodes[part[off]], nodes[part[root[off]]]

    def run(batches):
        kept = None
        for batch in batches:
            if not batch.num_rows:
                continue
            keys, nodes = (batch.column(k).to_numpy(zero_copy_only=False) for k in (0, 1))
            fps = batch.column(2).flatten().to_numpy(zero_copy_only=False).view(np.uint64).reshape(-1, words)
            if kept is not None:
                keys, nodes, fps = (np.concatenate(x) for x in zip(kept, (keys, nodes, fps), strict=True))
            whole = int(np.searchsorted(keys, keys[-1]))  # the last key may go on in the next batch
            for a, b in links(nodes[:whole], fps[:whole], keys[:whole]):
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], names=["a", "b"])
            kept = keys[whole:], nodes[whole:], fps[whole:]
        if kept is not None:
            for a, b in links(kept[1], kept[2], kept[0]):
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], names=["a", "b"])

    return run


# ---- exact similarity --------------------------------------------------------------------------------------------


def alike(sets: list[np.ndarray], similarity: float) -> np.ndarray:
    """Component of each set: the least row that pairs with at least this share of common members lead to. Pairs that are
    joined already are not counted again."""
    n, size = len(sets), np.array([len(x) for x in sets], np.int64)
    cuts = np.concatenate(([0], np.cumsum(size)))
    ids = np.unique(np.concatenate(sets), return_inverse=True)[1]
    parent, has = np.arange(n), np.zeros(cuts[-1] + 1, np.int32)
    for i in range(n - 1):
        j = np.flatnonzero(parent[i + 1 :] != parent[i]) + i + 1
        j = j[np.minimum(size[j], size[i]) >= similarity * np.maximum(size[j], size[i]) - 1e-6]
        if not len(j):
            continue
        mine = ids[cuts[i] : cuts[i + 1]]
        has[mine] = 1
        total = np.concatenate(([0], np.cumsum(has[np.concatenate([ids[cuts[k] : cuts[k + 1]] for k in j])])))
        has[mine] = 0
        ends = np.cumsum(size[j])
        common = total[ends] - total[ends - size[j]]
        hit = common / np.maximum(size[i] + size[j] - common, 1) >= similarity
        if hit.any():
            joined = np.unique(np.append(parent[j[hit]], parent[i]))
            parent[np.isin(parent, joined)] = joined[0]
    return parent


def _confirm_blocks(similarity: float):
    """mapInArrow over (group, node, set) in order of group: spanning links of the pairs that are similar."""

    def links(nodes, sets, groups):
        cuts = [0, *(np.flatnonzero(groups[1:] != groups[:-1]) + 1).tolist(), len(groups)]
        a, b = [], []
        for x, y in zip(cuts, cuts[1:], strict=False):
            if y - x > 1:
                root, mine = alike(sets[x:y], similarity), nodes[x:y]
                off = root != np.arange(y - x)
                a.append(mine[off])
                b.append(mine[root[off]])
        if a:
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in (a, b)], names=["a", "b"])

    def run(batches):
        groups, nodes, sets = np.empty(0, np.int64), np.empty(0, np.int64), []
        for batch in batches:
            if not batch.num_rows:
                continue
            more, new = (batch.column(k).to_numpy(zero_copy_only=False) for k in (0, 1))
            # copies, so that no batch is held for the sake of a few rows
            flat, ends = batch.column(2).flatten().to_numpy().copy(), np.cumsum(batch.column(2).value_lengths().to_numpy())
            groups, nodes, sets = np.concatenate((groups, more)), np.concatenate((nodes, new)), [*sets, *np.split(flat, ends[:-1])]
            whole = int(np.searchsorted(groups, groups[-1]))  # the last group may go on in the next batch
            yield from links(nodes[:whole], sets[:whole], groups[:whole])
            groups, nodes, sets = groups[whole:], nodes[whole:], sets[whole:]
        if len(groups):
            yield from links(nodes, sets, groups)
        give_back()

    return run


def widest_share(similarity: float) -> float:
    """Largest mean share of bits in which SimHashes of sets of this similarity or more differ. Large sets: the angle's
    share, arccos(2s / (1 + s)) / pi. Small ones differ more, as even counts can tie: every way for up to 40 members."""
    most = float(np.arccos(2 * similarity / (1 + similarity)) / np.pi)
    half = lambda n: [comb(n, k) / 2**n for k in range(n + 1)]
    for union in range(2, 41):
        for common in range(1, union):
            if common / union < similarity:
                continue
            for x in range((union - common) // 2 + 1):
                y = union - common - x
                one = lambda k, extra: sum(p for e, p in enumerate(half(extra)) if 2 * (k + e) > common + extra)
                differ = sum(p * (a + b - 2 * a * b) for k, p in enumerate(half(common)) for a, b in [(one(k, x), one(k, y))])
                most = max(most, differ)
    return most


# ---- keys --------------------------------------------------------------------------------------------------------


def _pieces(radius: int) -> list[tuple[int, int]]:
    """(start, width) of radius + 2 pieces of 64 bits."""
    cuts = [64 * k // (radius + 2) for k in range(radius + 3)]
    return [(a, b - a) for a, b in zip(cuts, cuts[1:], strict=False)]


def _bits(fp: Column, start: int, width: int) -> Column:
    return F.shiftrightunsigned(fp, start).bitwiseAND(F.lit((1 << width) - 1))


def piece_keys(fp: Column, radius: int) -> Column:
    """Every choice of two of radius + 2 pieces of a 64-bit fingerprint: rows within the radius agree on one at least."""
    pieces = [_bits(fp, *p) for p in _pieces(radius)]
    return F.array(*[F.xxhash64(F.lit(100 * i + j), pieces[i], pieces[j]) for i, j in combinations(range(radius + 2), 2)])


def finer_keys(fp: Column, radius: int, choice: Column) -> Column:
    """For rows that agree on the pieces of a choice: radius + 1 cuts through the other pieces, of which near rows share one."""
    pieces, sets = _pieces(radius), []
    for i, j in combinations(range(radius + 2), 2):
        places = [b for k, (s, w) in enumerate(pieces) if k not in (i, j) for b in range(s, s + w)]
        masks = [sum(1 << b for b in places[c :: radius + 1]) for c in range(radius + 1)]
        sets.append(F.array(*[F.xxhash64(F.lit(c), fp.bitwiseAND(F.lit(m - 2**64 if m >= 2**63 else m))) for c, m in enumerate(masks)]))
    return F.element_at(F.array(*sets), choice + 1)


def pairs_of_blocks(hot: DataFrame) -> DataFrame:
    """(key, node) from (key, node, n: the key's nodes): a key's nodes lie in blocks by a hash, and every two blocks are a key of
    their own, each with itself too, so any two nodes meet in a group of about two blocks of HOT / 2."""
    cut = hot.select("key", "node", F.ceil(2 * F.col("n") / HOT).cast("long").alias("blocks")).withColumn("mine", F.pmod(F.xxhash64("node"), F.col("blocks")))
    dealt = cut.withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)))
    return dealt.select(F.xxhash64("key", F.least("mine", "other"), F.greatest("mine", "other")).alias("key"), "node")


def near_links(nodes: DataFrame, radius: int, words: int = 1, groups: bool = False) -> DataFrame:
    """(a, b) links that span the near rows, or with groups (group, node) of candidate groups, which hold every near pair
    that shares a key. nodes: node long and keys array<long>, and fp array<long> if words > 1
    (else node is the fingerprint).

    Keys of one row go at once. A key of over HOT nodes is dealt out again: for pieces by the other bits, of which near
    rows share a part; a band's, and what then is still over HOT, by every two of its blocks of nodes.
    """
    spread = nodes.select(F.posexplode("keys").alias("choice", "key"), "node")
    counted = spread.withColumn("n", F.count(F.lit(1)).over(Window.partitionBy("key"))).where("n > 1")
    cold, hot = counted.where(F.col("n") <= HOT), counted.where(F.col("n") > HOT)
    link, schema = _link_blocks(radius, words, groups), "a long, b long"
    again = lambda df: df.repartition("key").sortWithinPartitions("key").mapInArrow(link, schema)
    if words == 1:
        fine = hot.select(F.explode(finer_keys(F.col("node"), radius, F.col("choice"))).alias("m"), "key", "node").select(F.xxhash64("key", "m").alias("key"), "node")
        fine = fine.withColumn("n", F.count(F.lit(1)).over(Window.partitionBy("key"))).where("n > 1")
        first = cold.select("key", "node", F.array("node").alias("fp")).mapInArrow(link, schema)
        met = fine.where(F.col("n") <= HOT).select("key", "node").unionByName(pairs_of_blocks(fine.where(F.col("n") > HOT)))
        second = again(met.select("key", "node", F.array("node").alias("fp")))
    else:
        prints = nodes.select("node", "fp")
        first = again(cold.select("key", "node").join(prints, "node").select("key", "node", "fp"))
        second = again(pairs_of_blocks(hot).join(prints, "node").select("key", "node", "fp"))
    out = first.unionByName(second).distinct()
    return out.toDF("group", "node") if groups else out


# ---- components --------------------------------------------------------------------------------------------------


def components(links: DataFrame) -> DataFrame:
    """(node, root) of each node that has a link; root: the least node of its component. Alternating stars, each pass
    written to the shared folder, until a pass changes nothing."""
    state = lambda e: tuple(e.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())
    edges = stored(links.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a <> b").distinct(), "links")
    before = state(edges)
    if not before[0]:
        return edges.select(F.col("a").alias("node"), F.col("b").alias("root"))
    while True:
        both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        # written, so that the join's two sides are plain exchanges, whose large partitions (a hub's links) Spark can split
        least = stored(both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m")), "links")
        large = both.where("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        large = stored(large, "links")
        low = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(low, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(low.select("a", F.col("m").alias("b")))
        old, edges = edges, stored(small.where("a <> b").distinct(), "links")
        after = state(edges)
        discard(old, least, large)
        if after == before:
            return edges.select(F.col("a").alias("node"), F.col("b").alias("root"))
        before = after


# ---- operators ---------------------------------------------------------------------------------------------------


def simhash_classes(docs: DataFrame, n_words: int = 3, radius: int = 2) -> DataFrame:
    """doc_id, fingerprint (16 hex digits) and component_id (least doc_id that links of `radius` bits or less lead to).

    Exact: no near pair of fingerprints is missed. Null doc_ids take no part in component ids, unless a component has no
    other: then its id is null.
    """
    made = docs.select("doc_id", sketch(F.col("text"), n_words, 1)["fp"][0].alias("fp"))
    prints = stored(made, "fingerprints")
    classes = prints.groupBy("fp").agg(F.min("doc_id").alias("least"))
    nodes = classes.select(F.col("fp").alias("node"), piece_keys(F.col("fp"), radius).alias("keys"))
    roots = components(near_links(nodes, radius))
    named = classes.join(roots, F.col("fp") == F.col("node"), "left").select("fp", F.coalesce("root", "fp").alias("root"), "least")
    ids = named.join(named.groupBy("root").agg(F.min("least").alias("component_id")), "root").select("fp", "component_id")
    out = prints.join(ids, "fp")
    return out.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def near_copies(docs: DataFrame, n_words: int = 5, similarity: float = 0.8, words: int = 8, bands: int = 16, rows: int = 4) -> DataFrame:
    """docs without near copies: of each group the row with the least doc_id stays (null last), ties by text.

    Similarity is that of the shingle sets (shared over all) and is exact. Rows that share a band are filtered by the distance of
    `words` x 64-bit SimHashes of the distinct shingles, with a limit 3.5 standard errors over the mean at `similarity`;
    pairs of what is left are counted shingle by shingle.
    """
    bits, p = 64 * words, widest_share(similarity)
    radius = int(np.ceil(bits * p + 3.5 * (bits * p * (1 - p)) ** 0.5))
    key = F.xxhash64("doc_id", "text")
    made = docs.select("doc_id", key.alias("k"), sketch(F.col("text"), n_words, words, bands, rows, distinct=True).alias("s"))
    keyed = F.transform("s.bands", lambda k, i: F.xxhash64(i, k))
    prints = stored(made.select("doc_id", "k", "s.fp", keyed.alias("keys"), "s.node"), "sketches")
    nodes = stored(prints.groupBy("node").agg(F.first("fp").alias("fp"), F.first("keys").alias("keys"), F.min("k").alias("k")), "sketch-nodes")
    groups = stored(near_links(nodes, radius, words, groups=True), "candidates")
    texts = docs.select(key.alias("k"), "text").join(nodes.select("node", "k").join(groups.select("node").distinct(), "node"), "k").dropDuplicates(["k"])
    with arrow_rows(docs.sparkSession, 1_000):
        sets = stored(texts.select("node", shingle_sets(F.col("text"), n_words).alias("set")), "shingles")
        pairs = groups.join(sets, "node").select("group", "node", "set").repartition("group").sortWithinPartitions("group")
        links = stored(pairs.mapInArrow(_confirm_blocks(similarity), "a long, b long").distinct(), "similar")
    roots = components(links)
    grouped = prints.select("doc_id", "k", "node").join(roots, "node", "left").withColumn("group", F.coalesce("root", "node"))
    first = grouped.groupBy("group").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "k")).alias("stay"))
    mine = docs.select(F.struct(*docs.columns).alias("row"), key.alias("k")).join(first.select(F.col("stay.k").alias("k")), "k", "left_semi")
    once = Window.partitionBy("k").orderBy("k")  # repeated rows have one key; the join has dealt them by it
    return mine.withColumn("nth", F.row_number().over(once)).where("nth = 1").select("row.*")
