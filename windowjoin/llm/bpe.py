"""Byte-level BPE in batched numpy merge rounds: encode and decode whole texts.

The symbols of many distinct words lie in one flat array. A round looks up the rank of
every neighbouring pair by binary search over the sorted pair keys (only of pairs that
the last round changed), takes each word's lowest rank, and merges every pair of that
rank in the word, left to right without overlap; words without a ranked pair leave the
array. Merging all pairs of the lowest rank at once equals merging them one by one when
each merge makes a token of its own, because then a pair with a new token ranks after
the merge that made it; for other vocabularies the leftmost pair alone is merged.

``encode`` cuts a text at the special tokens' strings, splits the rest by the public
pattern into words and joins the words' ids; each distinct word is merged once and kept
in a bounded cache. ``decode`` gathers the ids' bytes and reads them as UTF-8.

Defined cases: a null or empty text has no tokens and decodes to the empty text;
repeated rows are encoded again; an empty table gives an empty table; extra columns are
not read. No text or word has a longest length.
"""

from __future__ import annotations

import hashlib
import json

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from windowjoin.llm import common

# The public pattern of this kind of vocabulary; white space is Unicode's.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\p{White_Space}\p{L}\p{N}]+|\p{White_Space}+(?!\P{White_Space})|\p{White_Space}+"
NONE = np.int64(1 << 40)


def byte_alphabet() -> list[str]:
    """The printable character that stands for each byte in such vocabulary files."""
    plain = {*range(ord("!"), ord("~") + 1), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    spare = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(spare)) for b in range(256)]


class NumpyBPE:
    def __init__(self, definition: str, most_words: int = 400_000):
        import regex

        parts = json.loads(definition)
        vocab: dict[str, int] = parts["model"]["vocab"]
        merges = [m if isinstance(m, list) else m.split(" ") for m in parts["model"]["merges"]]
        self.special = {t["content"]: t["id"] for t in parts["added_tokens"]}
        self.pattern = regex.compile(PATTERN)
        self.cut = regex.compile("(" + "|".join(map(regex.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        alphabet = byte_alphabet()
        self.of_byte = np.array([vocab[c] for c in alphabet], np.int64)
        self.width = np.int64(max([*vocab.values(), *self.special.values()]) + 1)
        left = np.array([vocab[a] for a, _ in merges], np.int64)
        right = np.array([vocab[b] for _, b in merges], np.int64)
        made = np.array([vocab[a + b] for a, b in merges], np.int64)
        keys = left * self.width + right
        order = np.argsort(keys, kind="stable")
        self.keys, self.rank, self.made = keys[order], np.arange(len(keys), dtype=np.int64)[order], made
        self.together = len(np.unique(made)) == len(made)
        back = {c: b for b, c in enumerate(alphabet)}
        tokens = [b""] * int(self.width)
        for token, i in vocab.items():
            tokens[i] = bytes(back[c] for c in token)
        for token, i in self.special.items():
            tokens[i] = token.encode()
        self.token_size = np.array([len(t) for t in tokens], np.int64)
        self.token_start = np.cumsum(self.token_size) - self.token_size
        self.token_bytes = np.frombuffer(b"".join(tokens), np.uint8)
        self.most = most_words
        self._clear()

    def _clear(self) -> None:
        self.known: dict[str, int] = {}
        self.decimal: list[str] = []
        self.flat = np.zeros(1 << 16, np.int32)
        self.start = np.zeros(1 << 14, np.int64)
        self.size = np.zeros(1 << 14, np.int64)
        self.used = 0

    # -- merge rounds ----------------------------------------------------------------

    def _ranks(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        want = a * self.width + b
        at = np.minimum(np.searchsorted(self.keys, want), len(self.keys) - 1)
        return np.where(self.keys[at] == want, self.rank[at], NONE)

    def merge(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Flat ids of the words, and each word's number of ids."""
        sizes = np.fromiter(map(len, words), np.int64, len(words))
        sym = self.of_byte[np.frombuffer(b"".join(words), np.uint8)]
        word = np.repeat(np.arange(len(words)), sizes)
        rank = np.full(len(sym), NONE)  # of the pair that begins here
        if len(sym) > 1:
            same = word[1:] == word[:-1]
            rank[:-1][same] = self._ranks(sym[:-1][same], sym[1:][same])
        done_sym, done_word = [], []
        while len(sym):
            first = np.flatnonzero(np.concatenate(([True], word[1:] != word[:-1])))
            lowest = np.minimum.reduceat(rank, first)
            length = np.diff(np.append(first, len(sym)))
            if (over := lowest == NONE).any():
                gone = np.repeat(over, length)
                done_sym.append(sym[gone])
                done_word.append(word[gone])
                keep = ~gone
                sym, word, rank = sym[keep], word[keep], rank[keep]
                if not len(sym):
                    break
                lowest, length = lowest[~over], length[~over]
                first = np.cumsum(length) - length
            hit = np.flatnonzero(rank == np.repeat(lowest, length))
            if not self.together:
                hit = hit[np.concatenate(([True], word[hit][1:] != word[hit][:-1]))]
            elif len(hit) > 1 and (np.diff(hit) == 1).any():  # x x x: every other pair of a run
                run = np.concatenate(([True], np.diff(hit) != 1))
                since = np.arange(len(hit)) - np.maximum.accumulate(np.where(run, np.arange(len(hit)), 0))
                hit = hit[since % 2 == 0]
            sym[hit] = self.made[rank[hit]]
            keep = np.ones(len(sym), bool)
            keep[hit + 1] = False
            at = hit - np.arange(len(hit))  # where the merged symbols are afterwards
            sym, word, rank = sym[keep], word[keep], rank[keep]
            again = np.unique(np.concatenate((at, at[at > 0] - 1)))
            last = again == len(sym) - 1
            rank[again[last]] = NONE
            again = again[~last]
            same = word[again] == word[again + 1]
            rank[again] = np.where(same, self._ranks(sym[again], sym[again + 1]), NONE)
        flat, owner = np.concatenate(done_sym or [sym]), np.concatenate(done_word or [word])
        order = np.argsort(owner, kind="stable")
        return flat[order], np.bincount(owner, minlength=len(words))

    def _add(self, words: list[str]) -> None:
        ids, sizes = self.merge([w.encode("utf-8", "surrogatepass") for w in words])
        n, total = len(self.known), len(self.known) + len(words)
        while total > len(self.start):
            self.start, self.size = np.resize(self.start, 2 * len(self.start)), np.resize(self.size, 2 * len(self.size))
        while self.used + len(ids) > len(self.flat):
            self.flat = np.resize(self.flat, 2 * len(self.flat))
        self.flat[self.used : self.used + len(ids)] = ids
        ends = np.cumsum(sizes)
        self.start[n:total], self.size[n:total] = self.used + ends - sizes, sizes
        self.used += len(ids)
        text = list(map(str, ids.tolist()))
        self.decimal += [",".join(text[e - s : e]) for s, e in zip(sizes.tolist(), ends.tolist(), strict=True)]
        self.known.update(zip(words, range(n, total), strict=True))

    # -- texts -----------------------------------------------------------------------

    def split(self, text: str) -> list[str]:
        """Words of a text; special tokens' strings are words of their own."""
        if self.cut is None or not any(s in text for s in self.special):
            return self.pattern.findall(text)
        return [w for part in self.cut.split(text) for w in ([part] if part in self.special else self.pattern.findall(part))]

    def slots(self, words: list[str]) -> list[int]:
        """Cache slots of the words, in order; valid until the next call."""
        known = self.known
        found = list(map(known.get, words))
        if None in found:
            if len(known) > self.most:
                self._clear()
                known = self.known
            missing = list(dict.fromkeys(w for w in words if w not in known))
            special = [w for w in missing if w in self.special]
            self._add([w for w in missing if w not in self.special])
            for w in special:  # known under its own id
                self._add_special(w)
            found = list(map(known.__getitem__, words))
        return found

    def _add_special(self, token: str) -> None:
        n = len(self.known)
        if n >= len(self.start):
            self.start, self.size = np.resize(self.start, 2 * len(self.start)), np.resize(self.size, 2 * len(self.size))
        if self.used + 1 > len(self.flat):
            self.flat = np.resize(self.flat, 2 * len(self.flat))
        self.flat[self.used], self.start[n], self.size[n] = self.special[token], self.used, 1
        self.used += 1
        self.decimal.append(str(self.special[token]))
        self.known[token] = n

    def encode_batch(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray, list[str]]:
        """Flat ids, each text's number of ids, each text's ids in decimal with commas."""
        words = list(map(self.split, texts))
        per = np.fromiter(map(len, words), np.int64, len(words))
        slots = self.slots([w for x in words for w in x])
        ends = np.cumsum(per).tolist()
        decimal, of = [], self.decimal
        for n, e in zip(per.tolist(), ends, strict=True):
            decimal.append(",".join([of[s] for s in slots[e - n : e]]))
        at = np.array(slots, np.int64)
        sizes = self.size[at]
        ids = self.flat[common.ranges(self.start[at], sizes)]
        total = np.concatenate(([0], np.cumsum(sizes)))
        return ids, np.diff(total[np.concatenate(([0], np.cumsum(per)))]), decimal

    def count_words(self, words: list[str]) -> np.ndarray:
        """Number of tokens of each word."""
        at = np.array(self.slots(words), np.int64)  # may replace the arrays
        return self.size[at]

    def decode_batch(self, ids: np.ndarray, counts: np.ndarray) -> list[str]:
        """The texts of consecutive id lists; bytes that are no UTF-8 become U+FFFD."""
        sizes = self.token_size[ids]
        data = self.token_bytes[common.ranges(self.token_start[ids], sizes)].tobytes()
        at = np.concatenate(([0], np.cumsum(sizes)))[np.concatenate(([0], np.cumsum(counts)))].tolist()
        return [data[a:b].decode("utf-8", "replace") for a, b in zip(at[:-1], at[1:], strict=True)]


_OPEN: dict[int, NumpyBPE] = {}


def opened(definition: str) -> NumpyBPE:
    key = hash(definition)
    if key not in _OPEN:
        _OPEN.clear()
        _OPEN[key] = NumpyBPE(definition)
    return _OPEN[key]


def encode(docs: DataFrame, definition: str) -> DataFrame:
    """(doc_id, ids array<int>) of ``docs`` (doc_id, text)."""
    common.ship(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(definition)

    def rows(batches):
        bpe = opened(shared.value)
        for batch in batches:
            for part in common.cut(batch, most=4 << 20):
                ids, counts, _ = bpe.encode_batch(part.column("text").to_pylist())
                ends = np.concatenate(([0], np.cumsum(counts))).astype(np.int32)
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.ListArray.from_arrays(pa.array(ends), pa.array(ids))], names=["doc_id", "ids"])

    return common.texts(docs, "doc_id").mapInArrow(rows, "doc_id long, ids array<int>")


def decode(tokens: DataFrame, definition: str) -> DataFrame:
    """(doc_id, text) of ``tokens`` (doc_id, ids)."""
    common.ship(tokens.sparkSession)
    shared = tokens.sparkSession.sparkContext.broadcast(definition)

    def rows(batches):
        bpe = opened(shared.value)
        for batch in batches:
            lists = batch.column("ids")
            counts = np.diff(common.offsets(lists))
            text = bpe.decode_batch(lists.flatten().to_numpy(zero_copy_only=False), counts)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(text, pa.string())], names=["doc_id", "text"])

    return tokens.select("doc_id", "ids").mapInArrow(rows, "doc_id long, text string")


def round_trip_digests(docs: DataFrame, definition: str) -> DataFrame:
    """Encode and decode every text: token count and digests of the ids and of the decoded text."""
    common.ship(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(definition)
    sha = hashlib.sha256

    def rows(batches):
        bpe = opened(shared.value)
        for batch in batches:
            for part in common.cut(batch, most=4 << 20):
                ids, counts, decimal = bpe.encode_batch(part.column("text").to_pylist())
                back = bpe.decode_batch(ids, counts)
                yield pa.RecordBatch.from_arrays(
                    [part.column("doc_id"), pa.array(counts, pa.int64()), pa.array([sha(x.encode()).hexdigest() for x in decimal]), pa.array([sha(x.encode()).hexdigest() for x in back])],
                    names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"],
                )

    return common.texts(docs, "doc_id").mapInArrow(rows, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
