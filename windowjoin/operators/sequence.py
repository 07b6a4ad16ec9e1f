"""Arrival order, ranks, subwindows and batches of two streams.

A stream tuple has side ('S' or 'R'), key, value and, for time windows, ts. Ranks come
from counts per order bucket: a small table of bucket sums, then row numbers inside the
buckets. No window runs over the whole table in one task; only the bucket table, one
row per bucket, is summed in order.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from windowjoin.config import BatchPolicy

#: above every arrival number
END = 1 << 60


def cents(x: str | Column) -> Column:
    """Money as whole cents."""
    return F.round((F.col(x) if isinstance(x, str) else x) * 100).cast("bigint")


def prefilter(raw: DataFrame, where: Column | str, side: Column, key: Column, value: Column, *keep: str) -> DataFrame:
    """What a node ahead of the manager does: only wanted rows and join fields go on; filter and
    columns reach the scan."""
    return raw.filter(where).select(side.alias("side"), key.alias("key"), value.alias("value"), *keep)


def union_sides(s: DataFrame, r: DataFrame) -> DataFrame:
    """One table of both streams; columns key, value (and ts, payload of both alike)."""
    return s.withColumn("side", F.lit("S")).unionByName(r.withColumn("side", F.lit("R")))


def sequence(tuples: DataFrame, order_by: Sequence[str], bucket: Column) -> DataFrame:
    """Adds seq (arrival number from 1), rank within the side, seen_s and seen_r.

    ``bucket`` must not fall along the order, e.g. the hour of a time stamp. Tuples with
    a null value take part in the order, they count for windows as they arrived.
    """
    rows = tuples.withColumn("bucket", bucket)
    is_side = lambda side: F.when(F.col("side") == side, 1).otherwise(0).cast("bigint")
    sums = rows.groupBy("bucket").agg(F.sum(is_side("S")).alias("s_n"), F.sum(is_side("R")).alias("r_n"))
    before = Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    bases = sums.select("bucket", *(F.coalesce(F.sum(f"{x}_n").over(before), F.lit(0)).alias(f"{x}_base") for x in "sr"))
    inside = Window.partitionBy("bucket").orderBy(*order_by).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    out = rows.join(bases, "bucket").withColumns({"seen_s": F.col("s_base") + F.sum(is_side("S")).over(inside), "seen_r": F.col("r_base") + F.sum(is_side("R")).over(inside)})
    out = out.withColumns({"seq": F.col("seen_s") + F.col("seen_r"), "rank": F.when(F.col("side") == "S", F.col("seen_s")).otherwise(F.col("seen_r"))})
    return out.drop("bucket", "s_base", "r_base")


def assign_subwindows(ranked: DataFrame, n_sub: int) -> DataFrame:
    """Adds sub_id: contiguous runs of n_sub arrivals of a side."""
    return ranked.withColumn("sub_id", F.expr(f"(rank - 1) div {n_sub}"))


def time_slot(micros: str, seconds: int) -> Column:
    """Number of the time slot, equally long ones before and after 1970."""
    n = seconds * 1_000_000
    return F.expr(f"({micros} - pmod({micros}, {n}L)) div {n}L")


def assign_time_subwindows(ranked: DataFrame, seconds: int) -> DataFrame:
    """Adds sub_id by time stamp."""
    return ranked.withColumn("sub_id", time_slot("unix_micros(cast(ts as timestamp))", seconds))


def place(sub_id: Column | str, slots: int) -> Column:
    """Round-robin worker slot of a subwindow."""
    return F.pmod(F.col(sub_id) if isinstance(sub_id, str) else sub_id, F.lit(slots)).cast("int")


def collect_batches(ranked: DataFrame, n_bat: int) -> DataFrame:
    """Adds batch_id; one buffer per stream, closed at n_bat tuples."""
    return ranked.withColumn("batch_id", F.expr(f"(rank - 1) div {n_bat}"))


def prepare(ranked: DataFrame, n_sub: int, n_bat: int | BatchPolicy = 1, max_wait: float | None = None) -> DataFrame:
    """Adds sub_id, batch_id, done (when the tuple's batch is worked on) and opp (how many
    tuples of the other stream are in its window structure by then).

    A batch closes at ``n_bat`` tuples or, with ``max_wait``, at the next tick of a clock of so
    many seconds, whichever comes first; at a tick both streams' buffers close, S before R.
    """
    if isinstance(n_bat, BatchPolicy):
        n_bat, max_wait = n_bat.max_count, n_bat.max_wait
    rows = assign_subwindows(ranked, n_sub)
    if n_bat == 1:
        return collect_batches(rows, 1).withColumns({"done": F.col("seq"), "opp": F.when(F.col("side") == "S", F.col("seen_r")).otherwise(F.col("seen_s"))})
    tick = F.lit(0).cast("bigint") if max_wait is None else F.expr(f"(unix_micros(cast(ts as timestamp)) - pmod(unix_micros(cast(ts as timestamp)), {int(max_wait * 1_000_000)}L)) div {int(max_wait * 1_000_000)}L")
    rows = rows.withColumn("tick", tick)
    # what both sides had by the end of each tick, and so by its beginning: a row a tick
    ticks = rows.groupBy("tick").agg(F.max("seen_s").alias("tot_s"), F.max("seen_r").alias("tot_r"), F.max("seq").alias("end_seq"), F.min("seq").alias("first_seq"), F.sum(F.when(F.col("side") == "S", 1).otherwise(0)).alias("n_s"), F.sum(F.when(F.col("side") == "R", 1).otherwise(0)).alias("n_r"))
    ticks = ticks.select("tick", "tot_s", "tot_r", "end_seq", (F.col("tot_s") - F.col("n_s")).alias("base_s"), (F.col("tot_r") - F.col("n_r")).alias("base_r"))
    s_side = F.col("side") == "S"
    base = F.when(s_side, F.col("base_s")).otherwise(F.col("base_r"))
    rows = rows.join(ticks, "tick").withColumn("batch_in", F.floor((F.col("rank") - 1 - base) / n_bat))
    batches = rows.groupBy("tick", "side", "batch_in").agg(F.count("*").alias("n"), F.max("seq").alias("last"), F.max("seen_s").alias("s"), F.max("seen_r").alias("r"), F.first("base_s").alias("bs"), F.first("base_r").alias("br"), F.first("tot_s").alias("ts_"), F.first("tot_r").alias("tr"), F.first("end_seq").alias("end"))
    whole = lambda c, b: F.expr(f"{b} + (({c} - {b}) div {n_bat}) * {n_bat}")
    full = F.col("n") == n_bat
    closed = batches.select(
        "tick", "side", "batch_in",
        F.when(full, 4 * F.col("last")).when(s_side, 4 * F.col("end") + 1).otherwise(4 * F.col("end") + 2).alias("done"),
        F.when(full & s_side, whole("r", "br")).when(full, whole("s", "bs")).when(s_side, whole("tr", "br")).otherwise(F.col("ts_")).alias("opp"),
    )
    first = F.floor((F.col("rank") - 1) / n_bat) if max_wait is None else F.floor(base / 1) + F.col("batch_in")
    return rows.withColumn("batch_id", first.cast("bigint")).join(closed, ["tick", "side", "batch_in"]).drop("tick", "batch_in", "tot_s", "tot_r", "base_s", "base_r", "end_seq")


def sort_batch(prepared: DataFrame) -> DataFrame:
    """Each batch in value order, where it lies."""
    return prepared.sortWithinPartitions("side", "batch_id", "value")
