"""Token counts that follow edits: a segment tree of pre-tokens per document.

``build`` cuts a text into pre-tokens (the words that the merges never cross), groups
them into leaves of ``LEAF`` pre-tokens and keeps each leaf's characters and tokens.
``SegmentTree`` holds the sums over the leaves in a binary tree: a position is found by
descent, a count is the root's sum. ``SegmentTree.edit`` replaces a span: it re-encodes
from the leaf that holds the character ``CONTEXT`` before the edit (the splitting pattern
looks at most that far ahead of a word) to the first old leaf boundary after the edit at
which a new word also begins; from there on all words are as before. Only those leaves
are re-encoded, and only the sums above them are updated.

Edits apply one after the other, positions are code points of the text as it then is,
and spans beyond the end are cut at the end. Defined cases: a null or empty text has no
leaves and zero tokens; null edits are none; an edit with a null text inserts nothing;
repeated doc_ids stay rows of their own; an empty table gives an empty table; extra
columns are not read. A text that holds (or gets) a special token's string keeps that
string as one word, as the encoder does; since such a string can arise across words, its
texts are counted anew as a whole after each edit.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from windowjoin.llm import bpe, common

LEAF = 32
CONTEXT = 4


class SegmentTree:
    """Leaves (characters, tokens) under a binary tree of sums."""

    def __init__(self, chars: list[int], tokens: list[int]):
        self._build(chars, tokens)

    def _build(self, chars: list[int], tokens: list[int]) -> None:
        self.n = len(chars)
        self.base = 1 << max(0, (self.n - 1).bit_length())
        pad = [0] * (self.base - self.n)
        self.chars = [0] * self.base + list(chars) + pad
        self.tokens = [0] * self.base + list(tokens) + pad
        for i in range(self.base - 1, 0, -1):
            self.chars[i] = self.chars[2 * i] + self.chars[2 * i + 1]
            self.tokens[i] = self.tokens[2 * i] + self.tokens[2 * i + 1]

    @property
    def total(self) -> int:
        return self.tokens[1]

    @property
    def length(self) -> int:
        return self.chars[1]

    def leaves(self) -> tuple[list[int], list[int]]:
        return self.chars[self.base : self.base + self.n], self.tokens[self.base : self.base + self.n]

    def find(self, position: int) -> tuple[int, int]:
        """The leaf that holds a character, and the characters before that leaf."""
        i, before = 1, 0
        while i < self.base:
            i *= 2
            if position >= before + self.chars[i] and before + self.chars[i] < self.chars[1]:
                before += self.chars[i]
                i += 1
        return min(i - self.base, max(self.n - 1, 0)), before

    def _set(self, leaf: int, chars: int, tokens: int) -> None:
        i = leaf + self.base
        self.chars[i], self.tokens[i] = chars, tokens
        while i > 1:
            i //= 2
            self.chars[i] = self.chars[2 * i] + self.chars[2 * i + 1]
            self.tokens[i] = self.tokens[2 * i] + self.tokens[2 * i + 1]

    def replace(self, first: int, stop: int, chars: list[int], tokens: list[int]) -> None:
        """New leaves for the leaves first..stop-1; the tree is laid out anew only if it must grow."""
        if len(chars) <= stop - first:  # leaves that are over stay behind, empty
            for k in range(stop - first):
                self._set(first + k, *((chars[k], tokens[k]) if k < len(chars) else (0, 0)))
            return
        old_chars, old_tokens = self.leaves()
        self._build(old_chars[:first] + chars + old_chars[stop:], old_tokens[:first] + tokens + old_tokens[stop:])


def leaves_of(words: list[str], counts: np.ndarray) -> tuple[list[int], list[int]]:
    """Characters and tokens of each leaf of ``LEAF`` words with these token counts."""
    if not words:
        return [], []
    at = np.arange(0, len(words), LEAF)
    chars = np.add.reduceat(np.fromiter(map(len, words), np.int64, len(words)), at)
    return chars.tolist(), np.add.reduceat(counts, at).tolist()


def counted(model: bpe.NumpyBPE, lists: list[list[str]]) -> list[np.ndarray]:
    """Token counts of many lists of words, looked up and merged together."""
    counts = model.count_words([w for x in lists for w in x])
    return np.split(counts, np.cumsum([len(x) for x in lists])[:-1]) if lists else []


class EditedText:
    """A text, its tree, and the number of characters encoded since it was built.

    ``cut_out`` changes the text and gives the words to encode, ``put_back`` takes their
    counts; so the words of many documents' edits are encoded together.
    """

    def __init__(self, model: bpe.NumpyBPE, text: str, chars: list[int], tokens: list[int]):
        self.model, self.text, self.encoded = model, text, 0
        self.tree = SegmentTree(chars, tokens)
        self.special = self._special()

    def _special(self) -> bool:
        return any(s in self.text for s in self.model.special)

    def cut_out(self, start: int, stop: int, new: str) -> list[str]:
        tree = self.tree
        start = min(max(start, 0), len(self.text))
        stop = min(max(stop, start), len(self.text))
        had, old = self.special, self.text
        self.text = old[:start] + new + old[stop:]
        self.special = self._special()
        if had or self.special or not old:
            self.encoded += len(self.text)
            self.place, self.words = None, self.model.split(self.text)
            return self.words
        shift = len(new) - (stop - start)
        first, begin = tree.find(max(0, start - CONTEXT))
        last, before = tree.find(stop)
        chars, _ = tree.leaves()
        end = before + chars[last]
        words: list[str] = []
        match, text = self.model.pattern.match, self.text
        at = begin  # new words are known up to here, in the edited text
        while True:
            # the pattern looks a few characters ahead: match inside the whole text, stop at the boundary
            to = end + shift
            while at < to:
                found = match(text, at)
                words.append(found.group())
                at = found.end()
            if at == to or last + 1 >= tree.n:
                break
            while last + 1 < tree.n and end + shift < at:  # a word crosses the old boundary: take more leaves
                last += 1
                end += chars[last]
        self.encoded += at - begin
        self.place, self.words = (first, last + 1), words
        return words

    def put_back(self, counts: np.ndarray) -> None:
        leaves = leaves_of(self.words, counts)
        if self.place is None:
            self.tree = SegmentTree(*leaves)
        else:
            self.tree.replace(*self.place, *leaves)

    def edit(self, start: int, stop: int, new: str) -> None:
        self.put_back(self.model.count_words(self.cut_out(start, stop, new)))


def build(docs: DataFrame, definition: str) -> DataFrame:
    """(doc_id, text, seg_chars, seg_tokens): each text's leaves."""
    common.ship(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(definition)

    def rows(batches):
        model = bpe.opened(shared.value)
        for batch in batches:
            for part in common.cut(batch, most=4 << 20):
                words = list(map(model.split, part.column("text").to_pylist()))
                leaves = list(map(leaves_of, words, counted(model, words)))
                yield pa.RecordBatch.from_arrays(
                    [part.column("doc_id"), part.column("text"), *(pa.array([x[k] for x in leaves], pa.list_(pa.int32())) for k in (0, 1))],
                    names=["doc_id", "text", "seg_chars", "seg_tokens"],
                )

    return common.texts(docs, "doc_id").mapInArrow(rows, "doc_id long, text string, seg_chars array<int>, seg_tokens array<int>")


EDITS = "array<struct<start:bigint,stop:bigint,new:string>>"


def apply_edits(trees: DataFrame, definition: str, edits: str = "edits", texts_out: bool = False) -> DataFrame:
    """Counts before and after each row's ``edits``, from the trees of ``build``.

    Returns doc_id, n_tokens, n_tokens_edited, n_chars_edited, chars_encoded (what the
    edits made necessary to encode) and, on demand, the edited text and its leaves.
    """
    common.ship(trees.sparkSession)
    shared = trees.sparkSession.sparkContext.broadcast(definition)
    schema = "doc_id long, n_tokens long, n_tokens_edited long, n_chars_edited long, chars_encoded long"
    names = [c.split()[0] for c in schema.split(", ")]
    if texts_out:
        schema, names = schema + ", text string, seg_chars array<int>, seg_tokens array<int>", [*names, "text", "seg_chars", "seg_tokens"]

    def rows(batches):
        model = bpe.opened(shared.value)
        for batch in batches:
            for part in common.cut(batch, most=4 << 20):
                now = [EditedText(model, *x) for x in zip(*(part.column(c).to_pylist() for c in ("text", "seg_chars", "seg_tokens")), strict=True)]
                before = [x.tree.total for x in now]
                todo = [[e for e in x or [] if e is not None] for x in part.column("edits").to_pylist()]
                for k in range(max(map(len, todo), default=0)):  # the k-th edit of every document at once
                    at = [(x, t[k]) for x, t in zip(now, todo, strict=True) if len(t) > k]
                    words = [x.cut_out(e["start"] or 0, e["stop"] or 0, e["new"] or "") for x, e in at]
                    for (x, _), c in zip(at, counted(model, words), strict=True):
                        x.put_back(c)
                got = [(b, x.tree.total, len(x.text), x.encoded, x.text, *x.tree.leaves()) for b, x in zip(before, now, strict=True)]
                cols = list(zip(*got, strict=True))
                kinds = [pa.int64()] * 4 + [pa.string(), pa.list_(pa.int32()), pa.list_(pa.int32())]
                arrays = [pa.array(c, k) for c, k in zip(cols, kinds, strict=True)]
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), *arrays][: len(names)], names=names)

    return trees.select("doc_id", "text", "seg_chars", "seg_tokens", F.col(edits).cast(EDITS).alias("edits")).mapInArrow(rows, schema)
