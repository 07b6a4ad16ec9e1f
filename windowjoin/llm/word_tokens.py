"""Token ids of whole texts through the tokenizers library, once per distinct chunk.

The tokenizer's pieces never contain a space or a line feed, so a text's ids are those
of its chunks between spaces and line feeds, one after the other. Each distinct chunk
of a batch is found with Arrow's dictionary encoding and goes to the library once; a
bounded cache keeps the ids of earlier batches' chunks by two hashes of together 96 bits, in
flat arrays of about 25 bytes a chunk. ASCII chunks are lower-cased before
the look-up when the vocabulary's normaliser does so anyway. A text that holds one of
the special tokens' strings goes to the library as a whole.
"""

from __future__ import annotations

import json
import os
import re
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from windowjoin.llm.common import cut, offsets, ranges, utf8
from windowjoin.llm.multiset_hash import mixed

os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")

# Fixed value: the public pattern of this kind of vocabulary, for lower-case printable ASCII.
ASCII_PIECES = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[a-z]+|[0-9]|[^a-z0-9]+")

_OPEN: dict[int, "ChunkTokenizer"] = {}


LONG = 255  # bytes; longer chunks are encoded each time
_RANDOM = np.random.default_rng(4099)
BYTE_VALUES = _RANDOM.integers(1, 2**63, (2, 256), np.uint64) * np.uint64(2) + np.uint64(1)
PLACE_VALUES = _RANDOM.integers(1, 2**63, (2, LONG + 1), np.uint64) * np.uint64(2) + np.uint64(1)


def chunk_hashes(chunks: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Two independent hashes (64 and 32 bits) of each chunk, and its bytes."""
    data, ends = utf8(chunks)
    size = np.diff(ends)
    some = np.flatnonzero(size)
    place = np.arange(len(data)) - np.repeat(ends[:-1][some], size[some])
    np.minimum(place, LONG, out=place)
    out = []
    for values, places in zip(BYTE_VALUES, PLACE_VALUES, strict=True):
        h = np.zeros(len(size), np.uint64)
        if len(some):
            h[some] = np.add.reduceat(values[data] * places[place], ends[:-1][some])
        out.append(mixed(h + size.astype(np.uint64)))
    return out[0], (out[1] >> np.uint64(32)).astype(np.uint32), size


class IdCache:
    """Ids of chunks by hash, in flat arrays: a large sorted part and a small one, merged now and then."""

    def __init__(self):
        self.hash = [np.zeros(0, np.uint64), np.zeros(0, np.uint64)]
        self.slot = [np.zeros(0, np.int32), np.zeros(0, np.int32)]
        self.check = np.zeros(1 << 14, np.uint32)
        self.start = np.zeros(1 << 14, np.int32)
        self.size = np.zeros(1 << 14, np.int32)
        self.flat = np.zeros(1 << 16, np.uint32)
        self.n = self.used = 0

    def find(self, hashes: np.ndarray, checks: np.ndarray) -> np.ndarray:
        """Slot of each chunk, -1 where it is not known."""
        out = np.full(len(hashes), -1, np.int64)
        for h, s in zip(self.hash, self.slot, strict=True):
            if len(h):
                at = np.minimum(np.searchsorted(h, hashes), len(h) - 1)
                hit = (h[at] == hashes) & (self.check[s[at]] == checks)
                out[hit] = s[at[hit]]
        return out

    def add(self, hashes: np.ndarray, checks: np.ndarray, ids: np.ndarray, sizes: np.ndarray) -> np.ndarray:
        """Slots of chunks that were not known."""
        total = self.n + len(hashes)
        while total > len(self.start):
            self.check, self.start, self.size = (np.resize(x, 2 * len(x)) for x in (self.check, self.start, self.size))
        while self.used + len(ids) > len(self.flat):
            self.flat = np.resize(self.flat, 2 * len(self.flat))
        self.flat[self.used : self.used + len(ids)] = ids
        self.start[self.n : total] = self.used + np.cumsum(sizes) - sizes
        self.size[self.n : total], self.check[self.n : total] = sizes, checks
        slots = np.arange(self.n, total, dtype=np.int32)
        self.used, self.n = self.used + len(ids), total
        h, s = np.concatenate((self.hash[1], hashes)), np.concatenate((self.slot[1], slots))
        if len(h) > 200_000:
            h, s = np.concatenate((self.hash[0], h)), np.concatenate((self.slot[0], s))
        order = np.argsort(h)
        if len(h) > 200_000:
            self.hash, self.slot = [h[order], h[:0]], [s[order], s[:0]]
        else:
            self.hash[1], self.slot[1] = h[order], s[order]
        return slots


class ChunkTokenizer:
    """``encode(texts)`` gives the flat ids and each text's number of ids."""

    def __init__(self, definition: str, most_chunks: int = 2_000_000):
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_str(definition)
        self.library.no_truncation()
        self.library.no_padding()
        parts = json.loads(definition)
        self.special = [t["content"] for t in parts["added_tokens"]]
        self.marks = {s[0] for s in self.special}
        model = parts["model"]
        suffix = model.get("end_of_word_suffix") or ""
        self.ends = np.zeros(1 + max([*model["vocab"].values(), *(t["id"] for t in parts["added_tokens"])]), bool)
        if suffix:
            self.ends[[i for t, i in model["vocab"].items() if t.endswith(suffix)]] = True
        self.lower = '"Lowercase"' in json.dumps(parts["normalizer"])
        self.most = most_chunks
        self.cache = IdCache()

    def _encoded(self, texts: list[str], at_once: int) -> tuple[np.ndarray, np.ndarray]:
        """Flat ids and numbers of ids; few texts at once, for the library's results are large."""
        flat, sizes = [np.zeros(0, np.uint32)], [np.zeros(0, np.int64)]
        for i in range(0, len(texts), at_once):
            ids = [e.ids for e in self.library.encode_batch_fast(texts[i : i + at_once], add_special_tokens=False)]
            flat.append(np.fromiter(chain.from_iterable(ids), np.uint32))
            sizes.append(np.fromiter(map(len, ids), np.int64, len(ids)))
        return np.concatenate(flat), np.concatenate(sizes)

    def _ids(self, chunks: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Flat ids of the chunks, and each chunk's number of ids.

        Every piece ends with an end-of-word token, so printable ASCII chunks, whose
        pieces can be counted here, go to the library many to a text and are told
        apart by these tokens; any other chunk is a text of its own.
        """
        joined = [c for c in chunks if c.isascii() and c.isprintable() and c] if self.ends.any() else []
        others = [c for c in chunks if not (c.isascii() and c.isprintable() and c)] if joined else chunks
        if joined:
            pieces = np.fromiter((len(ASCII_PIECES.findall(c.lower())) for c in joined), np.int64, len(joined))
            lines = [" ".join(joined[i : i + 200]) for i in range(0, len(joined), 200)]
            flat, _ = self._encoded(lines, 50)
            at = np.concatenate(([0], np.flatnonzero(self.ends[flat]) + 1))
            if len(at) - 1 == pieces.sum():
                bounds = at[np.concatenate(([0], np.cumsum(pieces)))]
            else:  # not a vocabulary of that kind
                joined, others = [], chunks
        rest, rest_sizes = self._encoded(others, 2000)
        if not joined:
            return rest, rest_sizes
        self.order = joined + others
        return np.concatenate((flat, rest)), np.concatenate((np.diff(bounds), rest_sizes))

    def _slots(self, chunks: pa.Array) -> np.ndarray:
        """Cache slots of distinct chunks."""
        if self.cache.n + len(chunks) > self.most:
            self.cache = IdCache()
        hashes, checks, size = chunk_hashes(chunks)
        slots = self.cache.find(hashes, checks)
        if (long := size > LONG).any():  # their hashes do not tell them apart: never found again
            slots[long] = -1
            hashes[long] = mixed(np.uint64(1 << 63) + np.uint64(self.cache.n) + np.arange(long.sum(), dtype=np.uint64))
        new = np.flatnonzero(slots < 0)
        if len(new):
            missing = chunks.take(pa.array(new)).to_numpy(zero_copy_only=False).tolist()
            # a chunk that could turn into a special token's string stays as it is
            plain = [c.lower() if c.isascii() and self.marks.isdisjoint(c) else c for c in missing] if self.lower else missing
            self.order = list(dict.fromkeys(plain))
            ids, sizes = self._ids(self.order)
            place = {c: i for i, c in enumerate(self.order)}
            at = np.fromiter(map(place.__getitem__, plain), np.int64, len(plain))
            sizes = sizes.astype(np.int64)
            starts = np.cumsum(sizes) - sizes
            slots[new] = self.cache.add(hashes[new], checks[new], ids[ranges(starts[at], sizes[at])], sizes[at])
        return slots

    def encode(self, text: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        if not len(text):
            return np.zeros(0, np.uint32), np.zeros(0, np.int64)
        whole = np.zeros(len(text), bool)
        for s in self.special:
            whole |= pc.match_substring(text, s).to_numpy(zero_copy_only=False)
        plain = pc.if_else(pa.array(whole), pa.scalar("", text.type), text) if whole.any() else text
        lists = pc.split_pattern(pc.replace_substring(plain, "\n", " "), " ")
        words = lists.flatten()
        per = np.diff(offsets(lists))
        coded = words.dictionary_encode()
        slots = self._slots(coded.dictionary)[coded.indices.to_numpy()]
        sizes = self.cache.size[slots]
        total = np.cumsum(sizes, dtype=np.int64)
        # a slice holds less than 2**31 ids, so places fit 32 bits
        where = np.repeat(self.cache.start[slots] - (total - sizes).astype(np.int32), sizes)
        where += np.arange(len(where), dtype=np.int32)
        ids = self.cache.flat[where]
        ends = np.concatenate(([0], total))[np.concatenate(([0], np.cumsum(per)))]
        counts = np.diff(ends)
        if whole.any():
            rows = np.flatnonzero(whole)
            own = [np.array(e.ids, np.uint32) for e in self.library.encode_batch([text[int(i)].as_py() for i in rows], add_special_tokens=False)]
            parts = np.split(ids, ends[1:-1])
            for i, x in zip(rows, own, strict=True):
                parts[i] = x
                counts[i] = len(x)
            ids = np.concatenate(parts)
        return ids, counts


def opened(definition: str) -> ChunkTokenizer:
    """One tokenizer per worker process and definition."""
    key = hash(definition)
    if key not in _OPEN:
        _OPEN.clear()
        _OPEN[key] = ChunkTokenizer(definition)
    return _OPEN[key]


def with_end(ids: np.ndarray, counts: np.ndarray, end_id: int) -> tuple[np.ndarray, np.ndarray]:
    """Appends ``end_id`` to every document."""
    out = np.insert(ids, np.cumsum(counts), np.uint32(end_id))
    return out.astype(np.uint32, copy=False), counts + 1


def encoded(batches, definition: str, end_id: int, key: str = "doc_id"):
    """(keys, flat ids, counts with the end id) of each bounded slice of the batches."""
    tok = opened(definition)
    for batch in batches:
        for part in cut(batch, most=2 << 20):
            ids, counts = tok.encode(part.column("text"))
            yield part.column(key), *with_end(ids, counts, end_id)
        pa.default_memory_pool().release_unused()
