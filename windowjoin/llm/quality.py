"""Quality classifier: regularised quadratic discriminant over document statistics.

``statistics`` turns a whole text into ``FEATURES``: smoothed shares of byte classes,
words and repetitions on a log scale (a short text is drawn towards usual shares), in
numpy over the bytes of many texts at once. ``fit`` sums counts, features and products
per class over all labelled rows (partial sums in the tasks; the driver gets one number
per class and pair of features), shrinks each class covariance towards the pooled one and
towards its diagonal and keeps its Cholesky factor. A score is the logistic of the
difference of the two classes' log densities, Mahalanobis distances by solving with the
cached factors, plus the log prior ratio.

Defined cases: a null text is empty and has the statistics of an empty text; null labels
and labels without a document do not count; several labels of a document count each;
without rows of both classes every score is 0.5; an empty table gives an empty table;
extra columns are dropped, except by ``keep_good``, which passes them through.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from windowjoin.llm import common

FEATURES = ("length", "upper", "digits", "white", "lines", "stops", "marks", "bars", "symbols", "beyond_ascii", "word_length", "repeated_words", "repeated_pairs", "shouting_words", "symbol_words", "same_bytes")
#: usual shares that short texts are drawn to, per byte or per word, and the weight of that
USUAL = {"upper": 0.03, "digits": 0.005, "white": 0.17, "lines": 0.004, "stops": 0.03, "marks": 0.002, "bars": 0.001, "symbols": 0.003, "beyond_ascii": 0.05, "same_bytes": 0.02}
WEIGHT_BYTES, WEIGHT_WORDS, FLOOR = 60.0, 12.0, 1e-3


def _class_table(*members: bytes) -> np.ndarray:
    out = np.zeros(256, bool)
    for m in members:
        out[list(m)] = True
    return out


CLASSES = {
    "upper": _class_table(bytes(range(65, 91))),
    "digits": _class_table(bytes(range(48, 58))),
    "white": _class_table(b" \t\r\n\x0b\x0c"),
    "lines": _class_table(b"\n"),
    "stops": _class_table(b".,;:"),
    "marks": _class_table(b"!?"),
    "bars": _class_table(b"|"),
    "symbols": _class_table(b"#$%&*@^~=+<>{}[]_\\/"),
    "beyond_ascii": _class_table(bytes(range(128, 256))),
}
MULTIPLIER = np.uint64(0x9E3779B97F4A7C15)


def statistics(data: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """One row of FEATURES per text; ``ends`` are the offsets of the texts in ``data``."""
    n_docs = len(ends) - 1
    size = np.diff(ends).astype(np.float64)
    doc = np.repeat(np.arange(n_docs), np.diff(ends))
    count = {}
    for name, table in CLASSES.items():
        # a running count per class, read at the texts' ends
        total = np.concatenate(([0], np.cumsum(table[data], dtype=np.int64)))
        count[name] = (total[ends[1:]] - total[ends[:-1]]).astype(np.float64)
    inner = np.ones(len(data), bool)
    inner[ends[:-1][np.diff(ends) > 0]] = False  # first bytes have no byte before them
    same = np.concatenate(([0], np.cumsum(inner & np.concatenate(([False], data[1:] == data[:-1])), dtype=np.int64)))
    count["same_bytes"] = (same[ends[1:]] - same[ends[:-1]]).astype(np.float64)

    white = CLASSES["white"][data]
    begins = ~white & (~inner | np.concatenate(([True], white[:-1])))
    first = np.flatnonzero(begins)
    words = np.bincount(doc[first], minlength=n_docs).astype(np.float64)
    out = {"length": np.log1p(size)}
    for name, usual in USUAL.items():
        out[name] = np.log(FLOOR + (count[name] + WEIGHT_BYTES * usual) / (size + WEIGHT_BYTES))
    out["word_length"] = np.log(((size - count["white"]) + 5.5 * WEIGHT_WORDS) / (words + WEIGHT_WORDS))
    if len(first):
        with np.errstate(over="ignore"):
            value = (data.astype(np.uint64) + np.uint64(1)) * ~white
            value *= value * MULTIPLIER
            # a word's hash: its bytes' values weighted by their place in the word
            place = (np.arange(len(data)) - np.maximum.accumulate(np.where(begins, np.arange(len(data)), 0))).astype(np.uint64)
            hashes = np.add.reduceat(value * (MULTIPLIER * (place * np.uint64(2) + np.uint64(1))), first)
        owner = doc[first]
        again = np.zeros(len(first), bool)
        again[1:] = (hashes[1:] == hashes[:-1]) & (owner[1:] == owner[:-1])
        pairs = np.zeros(len(first), bool)
        pairs[2:] = (hashes[2:] == hashes[:-2]) & (owner[2:] == owner[:-2])
        upper = np.add.reduceat(CLASSES["upper"][data].astype(np.int32), first)
        symbol = np.add.reduceat((CLASSES["symbols"] | CLASSES["marks"] | CLASSES["bars"])[data].astype(np.int32), first)
        per_word = {"repeated_words": again, "repeated_pairs": pairs, "shouting_words": upper >= 2, "symbol_words": symbol >= 1}
    else:
        owner, per_word = np.zeros(0, np.int64), {k: np.zeros(0, bool) for k in ("repeated_words", "repeated_pairs", "shouting_words", "symbol_words")}
    for name, hit in per_word.items():
        share = (np.bincount(owner[hit], minlength=n_docs) + 0.02 * WEIGHT_WORDS) / (words + WEIGHT_WORDS)
        out[name] = np.log(FLOOR * 10 + share)
    return np.stack([out[f] for f in FEATURES], axis=1)


def features(docs: DataFrame) -> DataFrame:
    """(doc_id, features array<double>) of every text."""
    common.ship(docs.sparkSession)

    def rows(batches):
        for batch in batches:
            for part in common.cut(batch, most=1 << 20):
                x = statistics(*common.utf8(part.column("text")))
                at = pa.array(np.arange(len(x) + 1, dtype=np.int32) * x.shape[1])
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.ListArray.from_arrays(at, pa.array(x.ravel()))], names=["doc_id", "features"])

    return common.texts(docs, "doc_id").mapInArrow(rows, "doc_id long, features array<double>")


@dataclass(frozen=True)
class Discriminant:
    """Means, cached Cholesky factors and log terms of the two classes."""

    means: np.ndarray
    factors: np.ndarray
    logs: np.ndarray  # log prior - half the log determinant
    temperature: float = 4.0

    def log_odds(self, x: np.ndarray) -> np.ndarray:
        value = []
        for mean, factor, log in zip(self.means, self.factors, self.logs, strict=True):
            # forward substitution in the triangular factor, all rows at once, without a threaded library
            r, z = (x - mean).T, np.empty(x.T.shape)
            for i in range(len(mean)):
                z[i] = (r[i] - (factor[i, :i, None] * z[:i]).sum(0)) / factor[i, i]
            value.append(log - 0.5 * (z * z).sum(0))
        return value[1] - value[0]

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1.0 / (1.0 + np.exp(np.clip(-self.log_odds(x) / self.temperature, -35, 35)))


def discriminant(count: np.ndarray, total: np.ndarray, products: np.ndarray, pooled_share: float = 0.1, diagonal_share: float = 0.05, least: float = 1e-4) -> Discriminant | None:
    """From both classes' counts, sums and sums of products; None without both classes."""
    if (count < 2).any():
        return None
    means = total / count[:, None]
    own = products / count[:, None, None] - means[:, :, None] * means[:, None, :]
    pooled = np.einsum("c,cij->ij", count / count.sum(), own)
    d = means.shape[1]
    factors, logs = [], []
    for c in range(2):
        s = (1 - pooled_share) * own[c] + pooled_share * pooled
        s = (1 - diagonal_share) * s + diagonal_share * np.diag(np.diag(s)) + least * np.eye(d)
        factors.append(np.linalg.cholesky(s))
        logs.append(np.log(count[c] / count.sum()) - np.log(np.diag(factors[-1])).sum())
    return Discriminant(means, np.array(factors), np.array(logs))


def fit(labelled: DataFrame) -> Discriminant | None:
    """From all rows of ``labelled`` (label 0 or 1, features)."""
    common.ship(labelled.sparkSession)
    d = len(FEATURES)

    def sums(batches):
        count, products = np.zeros(2), np.zeros((2, d + 1, d + 1))
        for b in batches:
            label = b.column("label").to_numpy()
            x = np.concatenate((np.ones((len(label), 1)), b.column("features").flatten().to_numpy().reshape(-1, d)), axis=1)
            for c in (0, 1):
                products[c] += np.einsum("ni,nj->ij", x[label == c], x[label == c])
        count = products[:, 0, 0]
        if count.any():
            c, i, j = (a.ravel() for a in np.meshgrid(range(2), range(d + 1), range(d + 1), indexing="ij"))
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int32()), pa.array(i, pa.int32()), pa.array(j, pa.int32()), pa.array(products.ravel())], names=["c", "i", "j", "v"])

    rows = labelled.filter("label in (0, 1) and features is not null").select(F.col("label").cast("int"), "features")
    table = np.zeros((2, d + 1, d + 1))
    # 2 * (d + 1)**2 rows, whatever the input
    for r in rows.mapInArrow(sums, "c int, i int, j int, v double").groupBy("c", "i", "j").agg(F.sum("v").alias("v")).collect():
        table[r.c, r.i, r.j] = r.v
    return discriminant(table[:, 0, 0], table[:, 0, 1:], table[:, 1:, 1:])


def held_out(doc_id: str = "doc_id"):
    """True for the third of the ids whose labels are never learned from."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % 3 == 1, F.lit(False))


def scores(table: DataFrame, model: Discriminant | None) -> DataFrame:
    """(doc_id, score) from (doc_id, features)."""
    common.ship(table.sparkSession)
    d = len(FEATURES)

    def rows(batches):
        for b in batches:
            x = b.column("features").flatten().to_numpy().reshape(-1, d)
            s = np.full(len(x), 0.5) if model is None else model.score(x)
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(s)], names=["doc_id", "score"])

    return table.select("doc_id", "features").mapInArrow(rows, "doc_id long, score double")


def train(table: DataFrame, labels: DataFrame) -> Discriminant | None:
    """Fit on the labelled documents that are not held out; ``table`` has doc_id and features."""
    known = labels.select("doc_id", F.col("quality").alias("label")).filter("label is not null and doc_id is not null")
    return fit(table.filter(~held_out()).join(known.filter(~held_out()), "doc_id"))


def classify(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score and predicted of every document."""
    table = common.written(features(docs), "features")
    scored = scores(table, train(table, labels))
    return scored.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def keep_good(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows of ``docs``, all columns, that the classifier does not reject."""
    model = train(common.written(features(docs), "features"), labels)
    if model is None:
        return docs
    common.ship(docs.sparkSession)

    def rows(batches):
        for batch in batches:
            for part in common.cut(batch, most=1 << 20):
                good = model.score(statistics(*common.utf8(part.column("text").fill_null("")))) >= 0.5
                yield part.filter(pa.array(good))

    return docs.mapInArrow(rows, docs.schema)
