"""What the training-data operators share: shipping code, shared folders, Arrow helpers.

Conventions of every operator in this subpackage
------------------------------------------------
* A null text counts as the empty text; a null id is kept as null.
* Input columns that an operator does not need are dropped before any exchange, so an
  input with extra or clashing column names works; only the named columns are read.
* Python code runs in Arrow batches cut to a bounded number of bytes, whatever the
  length of a single text.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from windowjoin.runtime import drop_path, forget, new_path, ship, shared_root, shuffle_width, written

__all__ = ["cut", "drop_path", "forget", "keep_rows", "new_path", "offsets", "ranges", "read_documents", "shared_root", "ship", "shuffle_width", "task_partition", "text_id", "texts", "utf8", "written"]

def texts(docs: DataFrame, *keep: str, text: str = "text") -> DataFrame:
    """The needed columns only; a null text becomes empty."""
    return docs.select(*keep, F.coalesce(F.col(text), F.lit("")).alias("text"))


def text_id(text: str = "text"):
    """A hash that tells rows of one doc_id with different texts apart."""
    return F.xxhash64(F.coalesce(F.col(text), F.lit("")))


def keep_rows(docs: DataFrame, kept: DataFrame, rows: DataFrame) -> DataFrame:
    """One row of ``docs`` for each (kept__id, kept__text) of ``kept``; rows with null ids stay.

    ``rows`` has (doc_id, text_id) of every row. Only rows whose id and text are there more
    than once go through an exchange of whole rows; any one of those stays.
    """
    pair = ["kept__id", "kept__text"]
    kept = written(kept.select(*pair), "kept")
    often = rows.groupBy("doc_id", "text_id").count().filter("count > 1").select(F.col("doc_id").alias(pair[0]), F.col("text_id").alias(pair[1]))
    often = written(often.join(kept, pair), "often")
    match = (F.col("doc_id") == F.col("kept__id")) & (text_id() == F.col("kept__text"))
    if often.isEmpty():
        known = docs.join(kept, match, "left_semi")
    else:
        known = docs.join(kept.join(often, pair, "left_anti"), match, "left_semi")
        repeated = docs.join(often, match, "left_semi").withColumn("kept__text", text_id())
        known = known.unionByName(repeated.dropDuplicates(["doc_id", "kept__text"]).drop("kept__text"))
    return known.unionByName(docs.filter("doc_id is null"))


def read_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def cut(batch: pa.RecordBatch, column: str = "text", most: int = 8 << 20) -> Iterator[pa.RecordBatch]:
    """Slices of a batch with about ``most`` bytes of ``column`` each, one row at least."""
    if not batch.num_rows:
        return
    ends = offsets(batch.column(column))
    ends = ends[1:] - ends[0]
    at = 0
    while at < batch.num_rows:
        base = ends[at - 1] if at else 0
        to = max(at + 1, int(np.searchsorted(ends, base + most, side="right")))
        yield batch.slice(at, to - at)
        at = to


def offsets(col: pa.Array) -> np.ndarray:
    """Offsets of a string, binary or list array as int64, also for a slice."""
    kind = np.int64 if pa.types.is_large_string(col.type) or pa.types.is_large_binary(col.type) or pa.types.is_large_list(col.type) else np.int32
    if len(col) == 0:
        return np.zeros(1, np.int64)
    return np.frombuffer(col.buffers()[1], kind)[col.offset : col.offset + len(col) + 1].astype(np.int64)


def utf8(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All bytes of a string array without nulls, and the offsets into them."""
    ends = offsets(col)
    data = col.buffers()[2] if len(col) else None
    flat = np.frombuffer(data, np.uint8)[ends[0] : ends[-1]] if data is not None else np.zeros(0, np.uint8)
    return flat, ends - ends[0]


def ranges(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """start, start+1, ... of every piece, one after the other."""
    total = int(lengths.sum())
    if not total:
        return np.zeros(0, np.int64)
    out_at = np.cumsum(lengths) - lengths
    return np.repeat(starts - out_at, lengths) + np.arange(total)


def task_partition() -> int:
    from pyspark import TaskContext

    return TaskContext.get().partitionId()
