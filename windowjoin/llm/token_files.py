"""Token-id files: Parquet list columns in id order, for selective reads.

``write_token_files`` range-partitions the texts by id, encodes each partition in id
order and writes one row per document: its id, the ids before it in its file, the number
of ids and the ids as a list column. Ids are dictionary-encoded (bounded vocabulary),
the ascending metadata columns delta-encoded; row groups and pages are kept small and
Parquet's column and offset indexes are written, so that a reader of a range of ids or
of metadata only touches those pages. File names follow the id order.

``read_token_files`` gives (doc_id, start, n_tokens, ids): ``start`` counts all ids of
documents before it and comes from per-file totals, one row per file.

Defined cases: a null text is empty and has the end id only; a null doc_id sorts first;
documents that share a doc_id are kept as rows of their own, in text order; an empty
table gives an empty table. Extra columns are not read.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from windowjoin.llm import common
from windowjoin.llm.word_tokens import encoded

FILE_SCHEMA = "doc_id long, file int, before long, n_tokens long, ids array<int>"
LAYOUT = {
    "parquet.block.size": str(32 << 20),
    "parquet.page.size": str(256 << 10),
    "parquet.page.row.count.limit": "2000",
    "parquet.writer.version": "v2",
    "parquet.enable.dictionary": "true",
    "parquet.enable.dictionary#doc_id": "false",
    "parquet.enable.dictionary#before": "false",
    "compression": "zstd",
}


def write_token_files(docs: DataFrame, path: str, definition: str, end_id: int = 1, files: int | None = None) -> None:
    """Encode ``docs`` (doc_id, text) and write the files under ``path``."""
    spark = docs.sparkSession
    common.ship(spark)
    shared = spark.sparkContext.broadcast(definition)

    def rows(batches):
        file, before = common.task_partition(), 0
        for keys, ids, counts in encoded(batches, shared.value, end_id):
            ends = np.cumsum(counts)
            n = len(counts)
            lists = pa.ListArray.from_arrays(pa.array(np.concatenate(([0], ends)).astype(np.int32)), pa.array(ids.view(np.int32)))
            yield pa.RecordBatch.from_arrays(
                [keys, pa.array(np.full(n, file, np.int32)), pa.array(before + ends - counts), pa.array(counts), lists],
                names=["doc_id", "file", "before", "n_tokens", "ids"],
            )
            before += int(ends[-1])

    parts = files or max(2, common.shuffle_width(spark))
    ordered = common.texts(docs, "doc_id").repartitionByRange(parts, "doc_id").sortWithinPartitions("doc_id", "text")
    ordered.mapInArrow(rows, FILE_SCHEMA).write.options(**LAYOUT).parquet(path)


def read_token_files(spark: SparkSession, path: str) -> DataFrame:
    """(doc_id, start, n_tokens, ids) of all files; columns that are not used are not read."""
    files = spark.read.schema(FILE_SCHEMA).parquet(path)
    totals = files.groupBy("file").agg(F.sum("n_tokens").alias("total"))
    # one row per file: the window is over the files, not over the documents
    bases = totals.select("file", (F.sum("total").over(Window.orderBy("file")) - F.col("total")).alias("base"))
    return files.join(F.broadcast(bases), "file").select("doc_id", (F.col("base") + F.col("before")).alias("start"), "n_tokens", "ids")


def with_checksum(tokens: DataFrame) -> DataFrame:
    """Adds the crc32 of each list's ids as little-endian 32-bit integers, drops the list."""
    common.ship(tokens.sparkSession)

    def rows(batches):
        for b in batches:
            ids = b.column("ids")
            ends = common.offsets(ids)
            flat = memoryview(ids.values.to_numpy(zero_copy_only=False).astype("<u4", copy=False)).cast("B")
            crc = [zlib.crc32(flat[4 * i : 4 * j]) for i, j in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("start"), b.column("n_tokens"), pa.array(crc, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    return tokens.mapInArrow(rows, "doc_id long, start long, n_tokens long, ids_crc32 long")


def token_file_table(docs: DataFrame, definition: str, end_id: int = 1) -> DataFrame:
    """Write the token files to the shared folder, read them back, check-sum each document."""
    path = common.new_path(docs.sparkSession, "tokens")
    write_token_files(docs, path, definition, end_id)
    return with_checksum(read_token_files(docs.sparkSession, path))
