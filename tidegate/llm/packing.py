"""Packing by concatenating and cutting, with two passes of prefix sums.

Pass 1 tokenizes and writes, for each document, its token ids, its scan partition and the tokens before it in that
partition. Pass 2 sums the partitions (as many rows as there were tasks), turns the sums into the partitions' offsets, and
so knows each document's place in one endless row of tokens (ids are kept in two bytes, or in four where the tokenizer or the
end id has larger ones). Fixed windows cut that row; a document that crosses a window's edge gives one record for each window
it touches. No document moves between machines for this, and a long document is cut like any other. Only the last window is
not full: it is padded to the window, or left as it is at a power of two.

Ids are what the tokenizers library gives for the whole text. Text is encoded in runs between ASCII white space, which this
vocabulary's pre-tokenizer never joins, and ids of runs are remembered, since most runs return (WordEncoder).

Defined results: null text is empty; an empty document is its end id alone; repeated rows are packed again.
"""

from __future__ import annotations

import os
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tidegate.llm.common import arrow_rows, give_back, local_tokenizers, stored

WINDOW = 4096
END_ID = 2
REMEMBER = 280_000  # runs in each of a worker's two generations of memory
#: ASCII marks but the apostrophe, with which a contraction could begin
MARKS = "".join(chr(c) for c in range(33, 127) if not chr(c).isalnum() and c != 39)


class WordEncoder:
    """Token ids of texts, as little-endian unsigned 32-bit bytes.

    Texts are parted at ASCII white space, where this vocabulary's pre-tokenizer always parts. Letters and the marks after
    them are separate pre-tokens, so runs are held as letters (ASCII ones folded) and marks; any other run is held whole, as
    is one with a letter that normalising turns into a letter and a mark (sound()), for that mark joins those that follow.
    Those seen lately are remembered in two generations: when the young one is full it becomes the old one, and what is met
    again moves back. New letters are encoded many at a time, joined by blanks, and parted after ids that end a pre-token.
    """

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        words = self.tokenizer.get_vocab(with_added_tokens=False)
        self.closes = np.zeros(max(words.values()) + 1, bool)  # ids that end a pre-token
        self.closes[[i for w, i in words.items() if w.endswith("</w>")]] = True
        self.young: dict[bytes, bytes] = {}
        self.old: dict[bytes, bytes] = {}
        self.marks: dict[str, bytes] = {}
        self.letters: dict[str, bool] = {}
        self.largest = max(self.tokenizer.get_vocab(with_added_tokens=True).values())

    def _one(self, run: str) -> bytes:
        return np.asarray(self.tokenizer.encode(run, add_special_tokens=False).ids, "<u4").tobytes()

    def sound(self, letter: str) -> bool:
        """Whether a mark after this letter is a pre-token of its own."""
        got = self.letters.get(letter)
        if got is None:
            t = self.tokenizer
            alone, marked = ([x for x, _ in t.pre_tokenizer.pre_tokenize_str(t.normalizer.normalize_str(w))] for w in (letter, letter + ","))
            got = self.letters[letter] = len(alone) == 1 and marked == [*alone, ","]
        return got

    def _letters(self, words: list[bytes]) -> dict[bytes, bytes]:
        out = {}
        for at in range(0, len(words), 4000):
            part = words[at : at + 4000]
            ids = np.asarray(self.tokenizer.encode_batch_fast([b" ".join(part).decode()], add_special_tokens=False)[0].ids, "<u4")
            ends = np.flatnonzero(self.closes[ids]) + 1
            if len(ends) == len(part):
                ends = [0, *(4 * ends).tolist()]
                raw = ids.tobytes()
                out.update((w, raw[a:b]) for w, a, b in zip(part, ends, ends[1:], strict=False))
            else:  # lower-casing has parted a word
                out.update((w, self._one(w.decode())) for w in part)
        return out

    def learn(self, runs: list[bytes], letters: list[bool]) -> None:
        if len(self.young) >= REMEMBER:
            self.old, self.young = self.young, {}
        young, old, new = self.young, self.old.get, []
        for run, plain in zip(runs, letters, strict=True):
            got = old(run)
            if got is not None:
                young[run] = got
            elif plain:
                new.append(run)
            else:
                young[run] = self._one(run.decode()) if run else b""
        young.update(self._letters(new))

    def words(self, words: pa.Array) -> list[bytes]:
        """Ids of each of some different runs."""
        low = pc.if_else(pc.string_is_ascii(words), pc.ascii_lower(words), words)
        core = pc.utf8_rtrim(low, MARKS)
        plain = pc.utf8_is_alpha(core)
        other = np.flatnonzero(pc.and_(plain, pc.invert(pc.string_is_ascii(core))).to_numpy(zero_copy_only=False))
        if len(other):
            said = core.take(pa.array(other)).to_pylist()
            odd = {c for c in set("".join(said)) if c > "\x7f" and not self.sound(c)}
            if odd:
                mask = plain.to_numpy(zero_copy_only=False).copy()
                mask[[k for k, w in zip(other.tolist(), said, strict=True) if not odd.isdisjoint(w)]] = False
                plain = pa.array(mask)
        coded = pc.if_else(plain, core, words).dictionary_encode()
        bases = coded.dictionary.cast(pa.binary()).to_pylist()
        got = list(map(self.young.get, bases))
        missing = [k for k, g in enumerate(got) if g is None]
        if missing:
            alone = np.zeros(len(bases), bool)
            alone[coded.indices.to_numpy()[plain.to_numpy(zero_copy_only=False)]] = True
            self.learn([bases[k] for k in missing], alone[missing].tolist())
            for k in missing:
                got[k] = self.young[bases[k]]
        out = [got[k] for k in coded.indices.to_pylist()]
        marks = np.where(plain.to_numpy(zero_copy_only=False), (pc.binary_length(words).to_numpy(zero_copy_only=False) - pc.binary_length(core).to_numpy(zero_copy_only=False)), 0)
        marked = np.flatnonzero(marks)
        whole = words.take(pa.array(marked)).to_pylist()
        for k, n, w in zip(marked.tolist(), marks[marked].tolist(), whole, strict=True):
            out[k] += self.mark(w[-n:])
        return out

    def mark(self, marks: str) -> bytes:
        got = self.marks.get(marks)
        if got is None:
            got = self._one(marks)
            if len(marks) <= 8 and len(self.marks) < REMEMBER:
                self.marks[marks] = got
        return got

    def flat(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """All ids of some texts (no nulls) end to end, and each text's number of them.

        Arrow parts the texts and numbers the different runs, so Python sees each of those once; numpy lays the ids out.
        """
        runs = pc.ascii_split_whitespace(texts)
        coded = runs.flatten().dictionary_encode()
        kinds = self.words(coded.dictionary)
        raw = np.frombuffer(b"".join(kinds), "<u4")
        size = np.fromiter(map(len, kinds), np.int64, len(kinds)) // 4
        start = np.cumsum(size) - size
        of = coded.indices.to_numpy(zero_copy_only=False)
        n = size[of]
        upto = np.cumsum(n)
        total = int(upto[-1]) if len(upto) else 0
        kind = np.int32 if total < 2**31 else np.int64
        ids = raw[np.repeat((start[of] - (upto - n)).astype(kind), n) + np.arange(total, dtype=kind)]
        ends = np.concatenate(([0], upto))[runs.offsets.to_numpy() - runs.offsets[0].as_py()]
        return ids, np.diff(ends)

    def texts(self, texts: pa.Array, end_id: int) -> list[np.ndarray]:
        """Ids of each text, null as empty, with the end id after them."""
        return [x for part in self.some(texts, end_id) for x in part]

    def some(self, texts: pa.Array, end_id: int) -> Iterator[list[np.ndarray]]:
        """The same for a few megabytes of texts at a time; a longer text is cut at white space."""
        lengths = pc.fill_null(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False).astype(np.int64)
        upto, a = np.cumsum(lengths), 0
        while a < len(lengths):
            b = max(a + 1, int(np.searchsorted(upto, (upto[a - 1] if a else 0) + STRETCH, side="right")))
            part = pc.fill_null(texts.slice(a, b - a), "")
            if b == a + 1 and lengths[a] > STRETCH:
                parts = [self.flat(pa.array([p], pa.string()))[0] for p in stretches(part[0].as_py())]
                yield [np.append(np.concatenate(parts), np.uint32(end_id))]
            else:
                ids, n = self.flat(part)
                ids = np.insert(ids, np.cumsum(n), end_id)
                yield np.split(ids, np.cumsum(n + 1)[:-1])
            a = b


STRETCH = 3_000_000  # bytes worked on at a time


def stretches(text: str) -> list[str]:
    """A long text in parts that begin at ASCII white space."""
    out, a = [], 0
    while a < len(text):
        b = a + STRETCH // 2
        m = BLANK.search(text, b) if b < len(text) else None
        b = m.start() if m else len(text)
        out.append(text[a:b])
        a = b
    return out


BLANK = re.compile("[ \\t-\\r]")
_ENCODERS: dict[str, WordEncoder] = {}


def encoder(path: str) -> WordEncoder:
    if path not in _ENCODERS:
        _ENCODERS[path] = WordEncoder(path)
    return _ENCODERS[path]


def _tokenized(path: str, end_id: int):
    def run(batches):
        e, part, before = encoder(path), TaskContext.get().partitionId(), 0
        kind = "<u2" if max(e.largest, end_id) < 1 << 16 else "<u4"
        for k, batch in enumerate(batches):
            at = 0
            for ids in e.some(batch.column(1).cast(pa.string()), end_id):
                counts = np.fromiter(map(len, ids), np.int64, len(ids))
                places = before + np.cumsum(counts) - counts
                before += int(counts.sum())
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(at, len(ids)), pa.array(np.full(len(ids), part, np.int32)), pa.array(places), pa.array(counts), pa.array([x.astype(kind).tobytes() for x in ids], pa.binary())],
                    names=["doc_id", "part", "local", "tokens", "ids"],
                )
                at += len(ids)
            if k % 4 == 3:
                give_back()
        give_back()

    return run


def _cut(window: int, checksum: bool):
    """mapInArrow over (doc_id, tokens, at, all, ids): a row a piece, each document's ids parted at the windows' edges."""

    def run(batches):
        for batch in batches:
            doc, tokens, at, everything, ids = batch.columns
            tokens, at = tokens.to_numpy(), at.to_numpy()
            first, last = at // window, (at + tokens - 1) // window
            n = (last - first + 1).astype(np.int64)
            row = np.repeat(np.arange(len(n)), n)
            sequence = first[row] + np.arange(len(row)) - np.repeat(np.cumsum(n) - n, n)
            start = np.maximum(0, sequence * window - at[row])
            end = np.minimum(tokens[row], (sequence + 1) * window - at[row])
            tail = np.minimum(window, everything.to_numpy()[row] - sequence * window)
            padding = np.where(np.bitwise_count(tail) == 1, 0, window - tail)
            views = [np.frombuffer(x, "<u2" if len(x) == 2 * n else "<u4") for x, n in zip(ids.to_pylist(), tokens.tolist(), strict=True)]
            pieces = (views[r][a:b] for r, a, b in zip(row.tolist(), start.tolist(), end.tolist(), strict=True))
            if checksum:
                said = pa.array([zlib.crc32(x.astype("<u4").tobytes()) for x in pieces], pa.int64())
            else:
                said = pa.array([x.tobytes() for x in pieces], pa.binary())
            columns = [doc.take(pa.array(row)), *(pa.array(x.astype(np.int64)) for x in (start, end - start)), said, *(pa.array(x.astype(np.int64)) for x in (tokens[row], sequence, at[row] + start - sequence * window, padding))]
            yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "start", "length", "ids_crc32" if checksum else "ids", "doc_tokens", "sequence_id", "offset", "padding"])
            del views, pieces, ids
            give_back()

    return run


def _packed(docs: DataFrame, tokenizer: str | None, window: int, end_id: int, checksum: bool) -> DataFrame:
    if not 0 <= end_id < 1 << 32:
        raise ValueError(f"end_id {end_id} is no unsigned 32-bit number")
    path = tokenizer or os.path.join(local_tokenizers(), "word_bpe_49k.json")
    kind = docs.schema["doc_id"].dataType.simpleString()
    tokenized = docs.select("doc_id", "text").mapInArrow(_tokenized(path, end_id), f"doc_id {kind}, part int, local long, tokens long, ids binary")
    with arrow_rows(docs.sparkSession, 2000):
        rows = stored(tokenized, "packed-tokens")
    sums = rows.groupBy("part").agg(F.sum("tokens").alias("n"))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    bases = sums.select("part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"), F.sum("n").over(Window.partitionBy()).alias("all"))
    at = rows.join(F.broadcast(bases), "part").select("doc_id", "tokens", (F.col("base") + F.col("local")).alias("at"), "all", "ids")  # a row a scan task
    said = "ids_crc32 long" if checksum else "ids binary"
    return at.mapInArrow(_cut(window, checksum), f"doc_id {kind}, start long, length long, {said}, doc_tokens long, sequence_id long, offset long, padding long")


def pack(docs: DataFrame, tokenizer: str | None = None, window: int = WINDOW, end_id: int = END_ID) -> DataFrame:
    """A row a piece: doc_id, start, length, ids (two or four bytes each), doc_tokens, sequence_id, offset, and the tokens that pad
    the piece's sequence in `padding`."""
    return _packed(docs, tokenizer, window, end_id, False)


def packed_pieces(docs: DataFrame, tokenizer: str | None = None, window: int = WINDOW, end_id: int = END_ID) -> DataFrame:
    """pack() with the CRC-32 of each piece's ids, written as little-endian unsigned 32-bit numbers, in place of them."""
    return _packed(docs, tokenizer, window, end_id, True).drop("padding")
