"""Document fingerprints: a homomorphic hash of the multiset of a text's paragraphs.

A paragraph is what stands between line feeds. Its wide vector has ``EQUAL`` lanes of 16
bits drawn from its 128-bit hash, and ``LIKE`` lanes of 32 bits that add a sign for each
of its pieces (sentences, cut every ``PIECE`` bytes). A fingerprint is the sum of the
vectors, lane by lane modulo 2**16 and 2**32: it does not depend on the paragraphs'
order, adding a paragraph adds its vector and deleting one subtracts it (``updated``),
and fingerprints of parts add up (``total``). The EQUAL lanes decide equality; over the
LIKE lanes the mean square of a difference estimates how many pieces differ, so
``likeness`` is one minus that over both texts' own mean squares, between 0 and 1.

``edited_pairs`` gives each document's own fingerprint, that of the text edited with its
next document's beginning, and both likenesses. Texts move once, to one of many ranges
of ids; the first document of each range is sent to the range before as well.

Defined cases: a null or empty text has the zero fingerprint, and two of them likeness 1;
documents that share an id have the same next document, namely the first in text order of
the next smaller id; a lone document is its own next; a null id has no next document
(its edited text just loses its second half); an empty table gives an empty table; extra
columns are not read.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from windowjoin.llm import common

EQUAL, LIKE, PIECE = 32, 128, 64
SIZE = 2 * EQUAL + 4 * LIKE
_RANDOM = np.random.default_rng(20240101)
BYTE_VALUE = _RANDOM.integers(1, 2**63, 256, np.uint64) * np.uint64(2) + np.uint64(1)
BYTE_VALUE[10] = 0  # a line feed ends a paragraph and is no part of it
PLACE_VALUE = _RANDOM.integers(1, 2**63, PIECE, np.uint64) * np.uint64(2) + np.uint64(1)
SENTENCE_END = np.zeros(256, bool)
SENTENCE_END[list(b".!?")] = True


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit mixer."""
    with np.errstate(over="ignore"):
        x = (x ^ x >> np.uint64(30)) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ x >> np.uint64(27)) * np.uint64(0x94D049BB133111EB)
        return x ^ x >> np.uint64(31)


def piece_hashes(data: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hash and document of every piece."""
    if not len(data):
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    start = np.zeros(len(data), bool)
    start[ends[:-1][np.diff(ends) > 0]] = True
    start[1:] |= data[:-1] == 10
    start[2:] |= (data[1:-1] == 32) & SENTENCE_END[data[:-2]]
    index = np.arange(len(data))
    place = (index - np.maximum.accumulate(np.where(start, index, 0))) % PIECE
    first = np.flatnonzero(place == 0)
    with np.errstate(over="ignore"):
        sums = np.add.reduceat(BYTE_VALUE[data] * PLACE_VALUE[place], first)
    doc = np.searchsorted(ends, first, side="right") - 1
    some = sums != 0
    return mixed(sums[some]), doc[some]


def sign_lanes(hashes: np.ndarray, doc: np.ndarray, n_docs: int) -> np.ndarray:
    """Sums of signs per document, LIKE lanes of 32 bits."""
    out = np.zeros((n_docs, LIKE), np.int64)
    for at in range(0, len(hashes), 65_536):
        h, d = hashes[at : at + 65_536], doc[at : at + 65_536]
        wide = np.stack([mixed(h + np.uint64(k)) for k in range(1, LIKE // 64 + 1)], axis=1)
        bits = np.unpackbits(wide.view(np.uint8), axis=1)
        first = np.flatnonzero(np.concatenate(([True], d[1:] != d[:-1])))
        ones = np.add.reduceat(bits, first, axis=0, dtype=np.int32).astype(np.int64)
        n = np.diff(np.append(first, len(d)))
        np.add.at(out, d[first], 2 * ones - n[:, None])
    return out.astype(np.int32)  # wraps modulo 2**32


def equal_lanes(texts: list[bytes]) -> np.ndarray:
    """Sums of the paragraphs' random lanes per document, EQUAL lanes of 16 bits."""
    import xxhash

    parts = [t.split(b"\n") if t else [] for t in texts]
    n = np.fromiter(map(len, parts), np.int64, len(parts))
    digests = b"".join([xxhash.xxh3_128_digest(p) for x in parts for p in x])
    out = np.zeros((len(texts), EQUAL), np.uint16)
    h = np.frombuffer(digests, np.uint64).reshape(-1, 2)
    owner = np.repeat(np.arange(len(texts)), n)
    for at in range(0, len(h), 65_536):
        a, d = h[at : at + 65_536], owner[at : at + 65_536]
        with np.errstate(over="ignore"):
            wide = np.stack([mixed(a[:, 0] + mixed(a[:, 1] + np.uint64(k))) for k in range(EQUAL // 4)], axis=1)
        first = np.flatnonzero(np.concatenate(([True], d[1:] != d[:-1])))
        np.add.at(out, d[first], np.add.reduceat(wide.view(np.uint16), first, axis=0))
    return out


def fingerprints_of(texts: list[bytes]) -> np.ndarray:
    """One row of SIZE bytes per text: EQUAL lanes, then the LIKE lanes byte plane by byte plane."""
    ends = np.concatenate(([0], np.cumsum(np.fromiter(map(len, texts), np.int64, len(texts)))))
    like = sign_lanes(*piece_hashes(np.frombuffer(b"".join(texts), np.uint8), ends), len(texts))
    return packed(equal_lanes(texts), like)


def packed(equal: np.ndarray, like: np.ndarray) -> np.ndarray:
    planes = like.astype("<i4").view(np.uint8).reshape(len(like), LIKE, 4).transpose(0, 2, 1).reshape(len(like), -1)
    return np.concatenate((equal.astype("<u2").view(np.uint8), planes), axis=1)


def unpacked(prints: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    planes = prints[:, 2 * EQUAL :].reshape(-1, 4, LIKE).transpose(0, 2, 1)
    return np.ascontiguousarray(prints[:, : 2 * EQUAL]).view("<u2"), np.ascontiguousarray(planes).reshape(len(prints), -1).view("<i4")


def total(*prints: np.ndarray, signs: tuple[int, ...] | None = None) -> np.ndarray:
    """Fingerprint sums; a sign of -1 deletes."""
    equal, like = np.zeros((len(prints[0]), EQUAL), np.uint16), np.zeros((len(prints[0]), LIKE), np.int32)
    for p, sign in zip(prints, signs or (1,) * len(prints), strict=True):
        e, k = unpacked(p)
        with np.errstate(over="ignore"):
            equal, like = (equal + e, like + k) if sign > 0 else (equal - e, like - k)
    return packed(equal, like)


def updated(print_: np.ndarray, added: list[bytes] = (), removed: list[bytes] = ()) -> np.ndarray:
    """The fingerprint (one row) after adding and deleting paragraphs, without the text."""
    one = lambda p: fingerprints_of([p]) if p else _empty_paragraph()
    for p in added:
        print_ = total(print_, one(p))
    for p in removed:
        print_ = total(print_, one(p), signs=(1, -1))
    return print_


def _empty_paragraph() -> np.ndarray:
    return total(fingerprints_of([b"\n\n"]), fingerprints_of([b"\n"]), signs=(1, -1))


def likeness(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Estimated share of common pieces of two rows of fingerprints; 1 if they are equal."""
    x, y = unpacked(a)[1], unpacked(b)[1]
    with np.errstate(over="ignore"):
        d = (x - y).astype(np.float64)
    own = (x.astype(np.float64) ** 2).sum(1) + (y.astype(np.float64) ** 2).sum(1)
    value = 1 - np.divide((d**2).sum(1), own, out=np.ones(len(d)), where=own > 0)
    return np.where((a == b).all(1), 1.0, np.clip(value, 0, 1))


def fingerprints(docs: DataFrame) -> DataFrame:
    """(doc_id, fingerprint binary) of every whole text."""
    common.ship(docs.sparkSession)

    def rows(batches):
        for batch in batches:
            for part in common.cut(batch, most=2 << 20):
                prints = fingerprints_of(_bytes(part.column("text")))
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array([p.tobytes() for p in prints], pa.binary())], names=["doc_id", "fingerprint"])

    return common.texts(docs, "doc_id").mapInArrow(rows, "doc_id long, fingerprint binary")


def _bytes(col: pa.Array) -> list[bytes]:
    data, ends = common.utf8(col)
    raw, at = data.tobytes(), ends.tolist()
    return [raw[a:b] for a, b in zip(at[:-1], at[1:], strict=True)]


ROUTED = "range int, ahead boolean, doc_id long, text string, fingerprint binary"
PAIRS = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def edited_pairs(docs: DataFrame) -> DataFrame:
    """Each document against its edited text and its next document (see the module)."""
    spark = docs.sparkSession
    common.ship(spark)
    plain = common.texts(docs, "doc_id")
    width = common.shuffle_width(spark)
    n_ranges = 4 * width
    ids = docs.select("doc_id").filter("doc_id is not null")
    # what the driver gets is one id per range, twice; ranges follow the shuffle's width
    found = ids.agg(F.percentile_approx("doc_id", [k / n_ranges for k in range(1, n_ranges)], 20 * n_ranges).alias("s")).first().s
    splits = np.unique(np.array(found or [], np.int64))

    def range_of(x: np.ndarray) -> np.ndarray:
        return len(splits) - np.searchsorted(splits, x, side="left")  # descending, like the documents

    def head_rows(batches):
        for b in batches:
            x = b.column("doc_id").to_numpy()
            if len(x):
                r = range_of(x)
                order = np.lexsort((-x, r))
                first = order[np.concatenate(([True], np.diff(r[order]) != 0))]
                yield pa.RecordBatch.from_arrays([pa.array(r[first], pa.int32()), pa.array(x[first])], names=["range", "head"])

    heads = sorted((r["range"], r["head"]) for r in ids.mapInArrow(head_rows, "range int, head long").groupBy("range").agg(F.max("head").alias("head")).collect())
    before = {head: heads[k - 1][0] for k, (_, head) in enumerate(heads)}  # the first of all follows the last

    def route(batches):
        for batch in batches:
            for part in common.cut(batch, most=2 << 20):
                texts = _bytes(part.column("text"))
                prints = [p.tobytes() for p in fingerprints_of(texts)]
                keys = part.column("doc_id").to_pylist()
                own = [-1 if k is None else int(range_of(np.int64(k))) for k in keys]
                extra = [i for i, k in enumerate(keys) if k in before]
                take = pa.array([*range(len(keys)), *extra], pa.int64())
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array([*own, *(before[keys[i]] for i in extra)], pa.int32()),
                        pa.array([False] * len(keys) + [True] * len(extra)),
                        part.column("doc_id").take(take),
                        part.column("text").take(take),
                        pa.array([*prints, *(prints[i] for i in extra)], pa.binary()),
                    ],
                    names=["range", "ahead", "doc_id", "text", "fingerprint"],
                )

    def pairs(batches):
        waiting: list[tuple] = []  # rows of one id that wait for their next document
        ready: list[tuple] = []
        at, size = None, 0
        for batch in batches:
            for range_, ahead, doc, text, print_ in zip(*(batch.column(c).to_pylist() for c in ("range", "ahead", "doc_id", "text", "fingerprint")), strict=True):
                if waiting and (range_ != at or ahead or doc != waiting[0][0]):
                    follows = range_ == at and doc is not None
                    n_next = [(w, (text, print_) if follows else None) for w in waiting]
                    for w, nxt in n_next:
                        ready.append((*w, *_edit(w[1], nxt)))
                        size += len(ready[-1][3])
                    waiting = []
                at = range_
                if not ahead:
                    waiting.append((doc, text, print_))
                    if doc is None:
                        ready.append((*waiting.pop(), *_edit(text, None)))
                if size > 1 << 20 or len(ready) > 5000:
                    yield _pair_batch(ready)
                    ready, size = [], 0
        ready += [(*w, *_edit(w[1], None)) for w in waiting]
        if ready:
            yield _pair_batch(ready)

    routed = plain.mapInArrow(route, ROUTED).repartition(width, "range").sortWithinPartitions("range", "ahead", F.desc("doc_id"), "text")
    return routed.mapInArrow(pairs, PAIRS)


def _edit(text: str, following: tuple[str, bytes] | None) -> tuple[str, bytes]:
    """The edited text, and the next document's fingerprint."""
    n = len(text)
    return text[: n - n // 2] + (following[0][: n // 2] if following else ""), following[1] if following else bytes(SIZE)


def _pair_batch(ready: list[tuple]) -> pa.RecordBatch:
    docs, texts, own, edited, following = map(list, zip(*ready, strict=True))
    rows = lambda prints: np.frombuffer(b"".join(prints), np.uint8).reshape(-1, SIZE)
    coded = [e.encode() for e in edited]
    new = fingerprints_of(coded)
    mine = rows(own)
    return pa.RecordBatch.from_arrays(
        [
            pa.array(docs, pa.int64()),
            pa.array(list(map(len, texts)), pa.int64()),
            pa.array([hashlib.sha256(e).hexdigest() for e in coded]),
            pa.array([p.hex() for p in own]),
            pa.array([p.tobytes().hex() for p in new]),
            pa.array(likeness(mine, new)),
            pa.array(likeness(mine, rows(following))),
        ],
        names=[c.split()[0] for c in PAIRS.split(", ")],
    )
