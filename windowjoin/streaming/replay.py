"""Structured Streaming forms of the window join; each replays what is there and ends.

``native``: a stream-stream join on value buckets with watermarks, for time windows.
``stateful``: a subwindow's tuples in keyed state that expires by count or watermark.
``microbatch``: folders of subwindows, of which the live ones are read and dead ones dropped.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from windowjoin.config import CountWindow, Layout, TimeWindow
from windowjoin.operators.sequence import prepare
from windowjoin.plans import bucket, worker
from windowjoin.predicates import Predicate
from windowjoin.runtime import drop_path, forget, make_path, new_path, ship, written
from windowjoin.sources import sinks
from windowjoin.sources.sinks import each_batch, files

PAIR = "s_key bigint, r_key bigint, s_value bigint, r_value bigint"


def as_stream(rows: DataFrame, files_: int = 3, order: str = "seq") -> DataFrame:
    """The rows as a stream of files, one a micro-batch, to replay them: written one after the other,
    because the source takes files by their time stamps. A harness: a file is one task's."""
    spark = rows.sparkSession
    path = new_path(spark, "stream")
    rows = written(rows, "arrivals")  # ranked once, not once a file
    at = F.unix_micros(F.col(order).cast("timestamp")) if dict(rows.dtypes)[order].startswith("timestamp") else F.col(order)
    cuts = rows.agg(F.percentile_approx(at, [k / files_ for k in range(1, files_)])).first()[0] or []
    for lo, hi in zip([None, *cuts], [*cuts, None], strict=True):
        part = rows if lo is None else rows.filter(at > lo)
        (part if hi is None else part.filter(at <= hi)).coalesce(1).sortWithinPartitions(order).write.mode("append").parquet(path)
    forget(rows)
    return spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(path)


def _ended(stream: DataFrame, spark: SparkSession) -> DataFrame:
    """Run to the end of what is available and read the result."""
    out, checkpoint = new_path(spark, "result"), new_path(spark, "progress")
    files(stream, out, checkpoint).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def native_band(tuples: DataFrame, eps: int, seconds: int, width: int = 256, delay: str = "0 seconds") -> DataFrame:
    """Band join within a closed time distance; (side, key, value, ts).

    The streams are joined by blocks: a task packs its tuples by time slot of half the distance and
    value cell, blocks of S go to all slots and cells that their tuples reach. The join's key is
    (slot, cell), so that a probe reads state of about its own distance and values, whatever a
    micro-batch or the stream holds; block pairs are compared as arrays. A block's time is its last
    tuple's: it is late if all of it is.
    """
    spark = tuples.sparkSession
    ship(spark)
    us = seconds * 1_000_000
    slot = max(1, us // 2)
    stream = as_stream(tuples.select("side", "key", "value", F.col("ts").cast("timestamp").alias("ts")), order="ts")

    def blocks(side: str, reach: int, near: int) -> DataFrame:
        mine = stream.filter(F.col("side") == side).filter("value IS NOT NULL AND ts IS NOT NULL").select("key", "value", F.unix_micros("ts").alias("us"))
        packed = mine.mapInArrow(lambda batches: _packed(batches, slot, width, reach, near), BLOCKS)
        return packed.select(*(F.col(c).alias(f"{side}_{c}") for c in ("slot", "cell", "data")), F.timestamp_micros("last").alias(f"{side}_at")).withWatermark(f"{side}_at", delay)

    far = f"INTERVAL {us + slot} MICROSECONDS"  # a tuple is less than a slot before its block's last
    met = F.expr(f"S_slot = R_slot AND S_cell = R_cell AND R_at >= S_at - {far} AND R_at <= S_at + {far}")
    both = blocks("S", us, eps).join(blocks("R", 0, 0), met).select("S_data", "R_data")
    return _ended(both.mapInArrow(lambda batches: _matches(batches, eps, us), PAIR), spark)


BLOCKS = "slot bigint, cell bigint, last bigint, data binary"
#: tuples that are packed together, and pairs in one batch of the result
PACKED, MATCHED = 1 << 17, 1 << 18
FIELDS = ("key", "value", "us")


def _packed(batches: Iterator[pa.RecordBatch], slot: int, width: int, reach: int, near: int) -> Iterator[pa.RecordBatch]:
    """Blocks of tuples of one time slot, in value order, for each (slot, cell) that a tuple within
    ``reach`` and ``near`` of its own would be in."""
    held: list[pa.RecordBatch] = []
    most = max(1, PACKED // (2 * near // width + 1))  # a tuple is repeated for its cells

    def block() -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(held)
        known = table["key"].is_valid().to_numpy()
        key, value, us = (table[c].fill_null(0).to_numpy().astype(np.int64) for c in FIELDS)
        first_slot, first_cell = (us - reach) // slot, (value - near) // width
        slots, cells = (us + reach) // slot - first_slot + 1, (value + near) // width - first_cell + 1
        row = np.repeat(np.arange(len(us)), slots * cells)
        place = np.arange(len(row)) - np.repeat(np.cumsum(slots * cells) - slots * cells, slots * cells)
        to = np.stack((first_slot[row] + place // cells[row], first_cell[row] + place % cells[row], us[row] // slot))
        order = np.lexsort((value[row], *to[::-1]))
        row, to = row[order], to[:, order]
        cuts = np.append(np.flatnonzero(np.concatenate(([True], (to[:, 1:] != to[:, :-1]).any(axis=0)))), len(row))
        last = np.maximum.reduceat(us[row], cuts[:-1])
        columns = [x[row] for x in (key, value, us, known)]
        data = [b"".join(x[i:j].tobytes() for x in columns) for i, j in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True)]
        out = pa.RecordBatch.from_arrays([pa.array(to[0, cuts[:-1]]), pa.array(to[1, cuts[:-1]]), pa.array(last), pa.array(data, pa.binary())], names=["slot", "cell", "last", "data"])
        for at in range(0, out.num_rows, 1000):
            yield out.slice(at, 1000)

    for batch in batches:
        held += [batch] if batch.num_rows else []
        if sum(b.num_rows for b in held) >= most:
            yield from block()
            held = []
    if held:
        yield from block()


def _unpacked(data: bytes) -> tuple[np.ndarray, ...]:
    n = len(data) // (8 * len(FIELDS) + 1)
    return *np.frombuffer(data, np.int64, n * len(FIELDS)).reshape(len(FIELDS), n), np.frombuffer(data, np.bool_, n, 8 * n * len(FIELDS))


def _matches(batches: Iterator[pa.RecordBatch], eps: int, us: int) -> Iterator[pa.RecordBatch]:
    """The pairs of tuples of each pair of blocks, a bounded number at once."""
    names = [c.split()[0] for c in PAIR.split(", ")]
    held: list[tuple] = []
    size = 0

    def batch_of() -> pa.RecordBatch:
        s_key, r_key, s_value, r_value, s_known, r_known = (np.concatenate(x) for x in zip(*held, strict=True))
        return pa.RecordBatch.from_arrays([pa.array(s_key, mask=~s_known), pa.array(r_key, mask=~r_known), pa.array(s_value), pa.array(r_value)], names=names)

    for batch in batches:
        for s_data, r_data in zip(batch.column("S_data"), batch.column("R_data"), strict=True):
            (s_key, s_value, s_us, s_known), (r_key, r_value, r_us, r_known) = _unpacked(s_data.as_buffer()), _unpacked(r_data.as_buffer())
            lo, hi = np.searchsorted(r_value, s_value - eps), np.searchsorted(r_value, s_value + eps, side="right")
            total = np.cumsum(hi - lo)
            timed = max(s_us.max() - r_us.min(), r_us.max() - s_us.min()) > us
            at = 0
            while at < len(lo):
                to = max(at + 1, int(np.searchsorted(total, (total[at - 1] if at else 0) + MATCHED, side="right")))
                n = (hi - lo)[at:to]
                i = np.repeat(np.arange(at, to), n)
                j = np.arange(len(i)) + np.repeat(lo[at:to] - np.cumsum(n) + n, n)
                if timed:
                    near = np.abs(s_us[i] - r_us[j]) <= us
                    i, j = i[near], j[near]
                at = to
                if len(i):
                    size += len(i)
                    held.append((s_key[i], r_key[j], s_value[i], r_value[j], s_known[i], r_known[j]))
                if size >= MATCHED:
                    yield batch_of()
                    held, size = [], 0
    if held:
        yield batch_of()


def native_equi(tuples: DataFrame, seconds: int) -> DataFrame:
    """Spark's symmetric hash join of two streams, equality within a time distance."""
    spark = tuples.sparkSession
    stream = as_stream(tuples.select("side", "key", "value", F.col("ts").cast("timestamp").alias("ts")), order="ts")
    s = stream.filter("side = 'S'").select(F.col("key").alias("s_key"), F.col("value").alias("s_value"), F.col("ts").alias("s_ts")).withWatermark("s_ts", "0 seconds")
    r = stream.filter("side = 'R'").select(F.col("key").alias("r_key"), F.col("value").alias("r_value"), F.col("ts").alias("r_ts")).withWatermark("r_ts", "0 seconds")
    near = F.expr(f"s_value = r_value AND r_ts >= s_ts - INTERVAL {seconds} SECONDS AND r_ts <= s_ts + INTERVAL {seconds} SECONDS")
    return _ended(s.join(r, near).select("s_key", "r_key", "s_value", "r_value"), spark)


def stateful_join(ranked: DataFrame, pred: Predicate, window: CountWindow | TimeWindow, layout: Layout, delay: str = "0 seconds") -> tuple[DataFrame, str]:
    """The window join with a subwindow's tuples in keyed state; also the place of its progress, so
    that the state that is left can be read.

    Each micro-batch sends a state its inserts, probes and expiry: by count, the tuple with which the
    subwindow has left the window sends it an expire row; by time, the state's timer goes off when the
    watermark has passed the last moment at which a probe can want it.
    """
    spark = ranked.sparkSession
    ship(spark)
    timed = isinstance(window, TimeWindow)
    prepared = prepare(ranked, layout.n_sub).select("side", "key", "value", "rank", "done", "opp", *(["ts"] if timed else []))
    stream = as_stream(prepared, order="done")
    sent = worker.commands(stream, window, layout, ("ts",) if timed else (), chained=False, expiry=True)
    if timed:
        sent = sent.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)
    rows, closed = worker.bounded(sent.drop("segment", "share"), pred, F.col("side") == "R", F.col("op") == worker.PROBE)
    plan = worker.Plan(window, layout, _sorted, "pairs", pred.negated, len(closed), closed, (), 1, False)
    names = [c.split()[0] for c in PAIR.split(", ")]
    fields = ["value", "key", "rank", "done", "opp", *(["us"] if timed else [])]

    def work(address: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        rows = pd.concat(list(batches))
        held = [np.frombuffer(bytes(state.get[0]), np.int64).reshape(-1, len(fields))] if state.exists else []
        held.append(rows.loc[rows["op"] == worker.INSERT, fields].to_numpy(np.int64))
        stored = np.concatenate(held)
        asked = rows[rows["op"] == worker.PROBE]
        if len(stored) and len(asked):
            table = pa.RecordBatch.from_arrays([pa.array(stored[:, i]) for i in range(len(fields))], names=fields)
            where = (address[0], 0, 0, address[1])
            sub = worker.Subwindow(where, [table], worker.Chain(plan), plan)
            probes = pa.RecordBatch.from_pandas(asked[[c for c in asked.columns if c in fields or c[:2] in ("lo", "hi")]], preserve_index=False)
            for found in sub.answer(probes, names):
                yield found.to_pandas()
        if (rows["op"] == worker.EXPIRE).any():
            if state.exists:
                state.remove()
        elif len(stored) > len(held[0]) or not state.exists:
            state.update((stored.tobytes(),))
        if timed and state.exists:
            last = (int(address[1]) + 1) * layout.n_sub + window.seconds + window.disorder
            state.setTimeoutTimestamp(max(last * 1000, state.getCurrentWatermarkMs() + 1))

    timeout = GroupStateTimeout.EventTimeTimeout if timed else GroupStateTimeout.NoTimeout
    found = rows.groupBy("side", "sub_id").applyInPandasWithState(work, PAIR, "tuples binary", "append", timeout)
    out, progress = new_path(spark, "result"), new_path(spark, "progress")
    files(found, out, progress).start().awaitTermination()
    return spark.read.schema(found.schema).parquet(out), progress


def _sorted(_: int) -> str:
    return "sorted"


def live_subwindows(spark: SparkSession, progress: str) -> DataFrame:
    """(side, sub_id) of the subwindows that a stateful join still holds."""
    return spark.read.format("statestore").load(progress).select("key.side", "key.sub_id")


def microbatch_join(ranked: DataFrame, pred: Predicate, window: CountWindow, layout: Layout, overlap: bool = False) -> tuple[DataFrame, str]:
    """The manager as a micro-batch: append the batch to the folders of its subwindows, join it as
    probes with the live ones, write the batch's result folder, drop the folders of subwindows that
    no later probe can want. Returns the result and the store.

    A batch that runs again overwrites its own folders, so results are neither lost nor doubled.
    With ``overlap`` the narrow rows are written by a query of their own while this one works on
    what is there.
    """
    spark = ranked.sparkSession
    prepared = prepare(ranked, layout.n_sub).select("side", "sub_id", "key", "value", "rank", "done", "opp")
    store, out, progress = (new_path(spark, x) for x in ("subwindows", "result", "progress"))
    dropped, stored = {"S": 0, "R": 0}, {"S": 0, "R": 0}  # first subwindow that has a folder, and past the last

    def work(batch: DataFrame, batch_id: int) -> None:
        newest = {r.side: (r.top, r.opp) for r in batch.groupBy("side").agg(F.max("rank").alias("top"), F.min("opp").alias("opp")).collect()}
        gone = {side: max(0, newest[side][0] - window.size) // layout.n_sub if side in newest else dropped[side] for side in "SR"}
        # a folder is for later batches: what this one brings and ends with is not laid down
        kept = F.col("sub_id") >= F.when(F.col("side") == "S", gone["S"]).otherwise(gone["R"])
        sinks.subwindow_store(batch.filter(kept).withColumn("batch", F.lit(batch_id)), store)
        wanted = {"R": newest.get("S", (0, 0))[1], "S": newest.get("R", (0, 0))[1]}  # the least that the batch's probes see of a side
        seen = spark.read.schema("key bigint, value bigint, rank bigint, done bigint, opp bigint, side string, sub_id bigint, batch int").option("basePath", store).parquet(store)
        live = seen.filter(F.col("batch") < batch_id).filter(F.col("sub_id") >= F.when(F.col("side") == "S", max(0, (wanted["S"] or 0) - window.size) // layout.n_sub).otherwise(max(0, (wanted["R"] or 0) - window.size) // layout.n_sub))
        both = live.drop("batch").withColumn("asks", F.lit(False)).unionByName(batch.withColumn("asks", F.lit(True)))
        found = worker.run(both, pred, window, layout, "sorted")
        bucket.theta_filter_pairs(found, pred).write.mode("overwrite").parquet(f"{out}/batch={batch_id}")
        for side in newest:
            for sub_id in range(dropped[side], min(gone[side], stored[side])):
                drop_path(spark, f"{store}/side={side}/sub_id={sub_id}")
            dropped[side], stored[side] = max(dropped[side], gone[side]), (newest[side][0] - 1) // layout.n_sub + 1

    raw = as_stream(prepared, order="done")
    if not overlap:
        each_batch(raw, work, progress).start().awaitTermination()
    else:
        narrow, ahead = new_path(spark, "narrow"), new_path(spark, "progress")
        make_path(spark, narrow)
        preparing = files(raw, narrow, ahead).start()
        going = True
        while going:
            going = preparing.isActive
            arrived = spark.readStream.schema(prepared.schema).option("maxFilesPerTrigger", 1).parquet(narrow)
            each_batch(arrived, work, progress).start().awaitTermination()
        preparing.awaitTermination()
    return spark.read.schema(PAIR).option("recursiveFileLookup", "true").parquet(out), store


def stored_subwindows(spark: SparkSession, store: str) -> DataFrame:
    """(side, sub_id) of the subwindow folders that are left."""
    return spark.read.option("basePath", store).parquet(store).select("side", F.col("sub_id").cast("bigint").alias("sub_id")).distinct()


def counted(tuples: DataFrame) -> DataFrame:
    """The no-op joiner as a stream: tuples per side and batch file, nothing joined."""
    spark = tuples.sparkSession
    stream = as_stream(tuples.select("side", "seq"))
    n: list[DataFrame] = []

    def work(batch: DataFrame, batch_id: int) -> None:
        n.append(written(batch.groupBy("side").agg(F.count("*").alias("n")), "counts"))

    each_batch(stream, work, new_path(spark, "progress")).start().awaitTermination()
    total = n[0]
    for x in n[1:]:
        total = total.unionByName(x)
    return total.groupBy("side").agg(F.sum("n").cast("bigint").alias("n"))


def admitted(tuples: DataFrame, arrival: str, delay_seconds: int) -> DataFrame:
    """Out-of-order replay: a tuple is late if its time is below the watermark, the greatest
    time that arrived before it less the delay. Adds ``late`` (admitted, but out of order),
    ``dropped`` and ``top``, that greatest time in microseconds. The running maximum goes over blocks of arrivals, then inside them."""
    from pyspark.sql import Window

    rows = tuples.withColumns({"us": F.expr("unix_micros(cast(ts as timestamp))"), "block": F.expr(f"{arrival} div 4096")})
    tops = rows.groupBy("block").agg(F.max("us").alias("top"))
    before = tops.select("block", F.max("top").over(Window.orderBy("block").rowsBetween(Window.unboundedPreceding, -1)).alias("carried"))
    inside = Window.partitionBy("block").orderBy(arrival, "key").rowsBetween(Window.unboundedPreceding, -1)
    known = rows.join(before, "block").withColumn("top", F.greatest(F.max("us").over(inside), F.col("carried")))
    mark = F.col("top") - delay_seconds * 1_000_000
    return known.withColumns({"dropped": F.coalesce(F.col("us") < mark, F.lit(False)), "late": F.coalesce((F.col("us") < F.col("top")) & (F.col("us") >= mark), F.lit(False))}).drop("block")
