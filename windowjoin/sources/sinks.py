"""Writers of results and of subwindows at rest."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql.streaming import DataStreamWriter


def subwindow_store(rows: DataFrame, path: str) -> None:
    """Subwindows as folders, so that expiry drops folders and probes prune them; the batch that
    wrote a part is a folder below, which the same batch overwrites when it runs again."""
    rows.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("side", "sub_id", "batch").parquet(path)


def sorted_run(rows: DataFrame, path: str, partitions: int) -> None:
    """A compacted subwindow: value ranges, sorted inside, small row groups for pruning."""
    rows.repartitionByRange(partitions, "side", "sub_id", "value").sortWithinPartitions("side", "sub_id", "value").write.option("parquet.block.size", str(8 << 20)).parquet(path)


def discard(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()


def files(stream: DataFrame, path: str, checkpoint: str, mode: str = "append") -> DataStreamWriter:
    return stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).outputMode(mode).trigger(availableNow=True)


def each_batch(stream: DataFrame, work: Callable[[DataFrame, int], None], checkpoint: str) -> DataStreamWriter:
    return stream.writeStream.foreachBatch(work).option("checkpointLocation", checkpoint).trigger(availableNow=True)


def console(stream: DataFrame) -> DataStreamWriter:
    return stream.writeStream.format("console").outputMode("append")


def memory(stream: DataFrame, name: str, mode: str = "append") -> DataStreamWriter:
    return stream.writeStream.format("memory").queryName(name).outputMode(mode)
