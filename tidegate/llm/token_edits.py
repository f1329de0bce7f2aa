"""Token counts that follow edits.

A document's text is parted into pre-tokens. Up to LEAF of them, with their token counts, are a node of a balanced search
tree, whose subtrees keep sums of characters, pre-tokens and tokens; the text itself lies in the nodes, in pieces. An edit
cuts the tree before the pre-token a few characters ahead of it (boundary context) and behind the first boundary after it that
the old parting has too, parts and encodes only what lies between, and puts the three parts together again. So it copies no
text, moves no other leaf, however many it adds or takes away, and adds sums only on the paths that were cut.

Defined results: null text is empty and has no tokens; edits are (start, length, text) in code points of the text that they
are given for, in order of start; edits that overlap an earlier one or lie outside the text are cut to what is left; null
edits are left out, and null fields of one are 0 or empty; repeated rows are counted each; an empty table gives no rows; extra
columns are left out, whatever their names.
"""

from __future__ import annotations

import base64
import os
from random import Random

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tidegate.llm.common import arrow_function, local_tokenizers

CONTEXT = 4  # characters before an edit that a pre-token's end may have looked at
REMEMBER = 400_000
LEAF = 64  # pre-tokens of a tree node
LOOK = 256  # characters after an edit that are parted anew before more are looked at


class PieceCounter:
    """Pre-tokens of a byte-level BPE vocabulary and their numbers of tokens."""

    def __init__(self, path: str):
        import public_tokenizers
        import regex
        import tiktoken

        with open(path, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}
        self.pattern = regex.compile(public_tokenizers.PATTERN)
        self.encoding = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
        self.known: dict[str, int] = {}

    def __call__(self, piece: str) -> int:
        n = self.known.get(piece)
        if n is None:
            n = len(self.encoding.encode_ordinary(piece))
            if len(self.known) >= REMEMBER:
                self.known.clear()
            if len(piece) <= 64:
                self.known[piece] = n
        return n

    def pieces(self, text: str) -> list[str]:
        return self.pattern.findall(text)


class Node:
    """A node's own pre-tokens and counts, and the sums of its subtree."""

    __slots__ = ("left", "right", "pieces", "counts", "own", "size", "chars", "segments", "tokens")

    def __init__(self, left: Node | None, pieces: list[str], counts: list[int], right: Node | None):
        self.pieces, self.counts, self.own = pieces, counts, sum(map(len, pieces))
        self.left, self.right = left, right
        self.added()

    def added(self) -> Node:
        self.size, self.chars, self.segments, self.tokens = 1, self.own, len(self.pieces), sum(self.counts)
        for kid in (self.left, self.right):
            if kid is not None:
                self.size += kid.size
                self.chars += kid.chars
                self.segments += kid.segments
                self.tokens += kid.tokens
        return self


class CountTree:
    """Tree of the token counts of one text's pre-tokens."""

    def __init__(self, text: str, count: PieceCounter):
        self.count, self.encoded, self.touched, self.dice = count, 0, 0, Random(1)
        pieces = count.pieces(text)
        self.root = self._grown(pieces, list(map(count, pieces)))

    def _grown(self, pieces: list[str], counts: list[int]) -> Node | None:
        def grow(a: int, b: int) -> Node | None:  # nodes a to b, the middle one on top
            if a >= b:
                return None
            self.touched += 1
            m = (a + b) // 2
            part = slice(m * LEAF, (m + 1) * LEAF)
            return Node(grow(a, m), pieces[part], counts[part], grow(m + 1, b))

        return grow(0, -(-len(pieces) // LEAF))

    total = property(lambda self: self.root.tokens if self.root else 0)
    chars = property(lambda self: self.root.chars if self.root else 0)
    segments = property(lambda self: self.root.segments if self.root else 0)

    def _joined(self, a: Node | None, b: Node | None) -> Node | None:
        """All of a before all of b: a root drawn in proportion to the sizes keeps trees as balanced as random ones."""
        if a is None or b is None:
            return a or b
        self.touched += 1
        if self.dice.random() * (a.size + b.size) < a.size:
            a.right = self._joined(a.right, b)
            return a.added()
        b.left = self._joined(a, b.left)
        return b.added()

    def _cut(self, t: Node | None, at: int) -> tuple[Node | None, Node | None]:
        """The pre-tokens that end at `at` characters or before, and the others."""
        if t is None:
            return None, None
        self.touched += 1
        before = t.left.chars if t.left else 0
        if at < before:
            low, t.left = self._cut(t.left, at)
            return low, t.added()
        if at >= before + t.own:
            t.right, high = self._cut(t.right, at - before - t.own)
            return t.added(), high
        k, left, right = 0, t.left, t.right
        while before + len(t.pieces[k]) <= at:
            before += len(t.pieces[k])
            k += 1
        low, high = (Node(None, p, c, None) if p else None for p, c in ((t.pieces[:k], t.counts[:k]), (t.pieces[k:], t.counts[k:])))
        return self._joined(left, low), self._joined(high, right)

    def _walk(self, t: Node | None):
        """Nodes in order of the text, found as they are asked for."""
        stack = []
        while t is not None or stack:
            while t is not None:
                stack.append(t)
                t = t.left
            t = stack.pop()
            yield t
            t = t.right

    @property
    def text(self) -> str:
        return "".join(p for n in self._walk(self.root) for p in n.pieces)

    @property
    def pieces(self) -> list[str]:
        return [p for n in self._walk(self.root) for p in n.pieces]

    def edit(self, start: int, length: int, new: str) -> None:
        """Replaces `length` characters from `start` on."""
        start = max(0, min(start, self.chars))
        length = max(0, min(length, self.chars - start))
        low, rest = self._cut(self.root, max(0, start - CONTEXT))
        start -= low.chars if low else 0
        # the old text from the cut on, as far as it has been looked at, and where its pre-tokens end
        old, ends, size, nodes = [], [], 0, self._walk(rest)
        whole = rest.chars if rest else 0
        want = start + length + LOOK
        while True:
            while size < min(want, whole):
                for p in next(nodes).pieces:
                    old.append(p)
                    size += len(p)
                    ends.append(size)
            seen = "".join(old)
            pieces, here, stop = [], 0, None
            after, known = seen[:start] + new + seen[start + length :], set(ends)
            shift = len(new) - length
            for m in self.count.pattern.finditer(after):
                if size < whole and m.end() > len(after) - 2:
                    break  # what follows could change it
                pieces.append(m.group())
                here = m.end()
                if here >= start + len(new) and here - shift >= start + length and here - shift in known:
                    stop = here - shift
                    break
            if stop is not None or size >= whole:
                break
            want = 2 * size + LOOK
        stop = whole if stop is None else stop
        self.encoded += sum(map(len, pieces))
        middle = self._grown(pieces, list(map(self.count, pieces)))
        self.root = self._joined(self._joined(low, middle), self._cut(rest, stop)[1])


def apply_edits(tree: CountTree, edits: list[tuple[int, int, str]]) -> None:
    """Edits given for the first text, carried out from the last to the first."""
    done = []
    free = 0
    for start, length, new in sorted(edits, key=lambda e: (e[0], e[1])):
        begin, stop = max(start, free), max(start + length, free)
        done.append((begin, stop - begin, new))
        free = stop
    for e in reversed(done):
        tree.edit(*e)


_COUNTERS: dict[str, PieceCounter] = {}


def counter(path: str) -> PieceCounter:
    if path not in _COUNTERS:
        _COUNTERS[path] = PieceCounter(path)
    return _COUNTERS[path]


def default_vocabulary() -> str:
    return os.path.join(local_tokenizers(), "byte_bpe_50k.tiktoken")


RESULT = "struct<n_tokens:long,n_segments:long,n_edits:long,edited_tokens:long,edited_chars:long,reencoded_chars:long>"


def edited_counts(text: Column, edits: Column, vocabulary: str | None = None) -> Column:
    """Counts before and after the edits array<struct<start:int,length:int,text:string>> of each row."""
    path = vocabulary or default_vocabulary()

    @F.arrow_udf(RESULT)
    def run(texts: pa.Array, edit_lists: pa.Array) -> pa.Array:
        c, out = counter(path), []
        for t, e in zip(texts.to_pylist(), edit_lists.to_pylist(), strict=True):
            tree = CountTree(t or "", c)
            before, segments = tree.total, tree.segments
            e = [(x["start"] or 0, x["length"] or 0, x["text"] or "") for x in e or [] if x]
            apply_edits(tree, e)
            out.append((before, segments, len(e), tree.total, tree.chars, tree.encoded))
        columns = list(zip(*out, strict=True)) if out else [[]] * 6
        return pa.StructArray.from_arrays([pa.array(x, pa.int64()) for x in columns], names=["n_tokens", "n_segments", "n_edits", "edited_tokens", "edited_chars", "reencoded_chars"])

    return run(text, edits)


#: e-mail addresses and long runs of digits
PERSONAL = r"[A-Za-z0-9._%+-]{1,64}@[A-Za-z0-9-]{1,63}(?:\.[A-Za-z0-9-]{1,63})+|\d(?:[ -]?\d){6,20}"


@arrow_function("array<struct<start:int,length:int,text:string>>")
def redactions(texts: pa.Array) -> pa.Array:
    """Edits that put a mark in place of e-mail addresses and long numbers."""
    import re

    find = re.compile(PERSONAL).finditer
    rows = [[{"start": m.start(), "length": m.end() - m.start(), "text": "[redacted]"} for m in find(t or "")] for t in texts.to_pylist()]
    return pa.array(rows, pa.list_(pa.struct([("start", pa.int32()), ("length", pa.int32()), ("text", pa.string())])))


def redacted_token_counts(docs: DataFrame, vocabulary: str | None = None) -> DataFrame:
    """doc_id and the token counts of each whole text, before and after personal data is redacted."""
    return docs.select("doc_id", edited_counts(F.col("text"), redactions("text"), vocabulary).alias("c")).select("doc_id", "c.*")
