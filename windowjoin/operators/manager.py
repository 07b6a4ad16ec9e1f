"""The manager's part: placement, commands, status, subwindow registry - metadata only."""

from __future__ import annotations

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from windowjoin.operators.sequence import place


def registry(prepared: DataFrame, n_sub: int) -> DataFrame:
    """One row per subwindow: count, full and empty flags, first and last arrival, oldest and newest time."""
    rows = prepared.groupBy("side", "sub_id").agg(F.count("*").alias("cnt"), F.min("seq").alias("first_seq"), F.max("seq").alias("last_seq"), *([F.min("ts").alias("min_ts"), F.max("ts").alias("max_ts")] if "ts" in prepared.columns else []))
    return rows.withColumns({"is_full": F.col("cnt") >= n_sub, "is_empty": F.col("cnt") == 0})


def status(prepared: DataFrame, n_sub: int, slots: int) -> DataFrame:
    """What workers report: per slot and side its tuples, subwindows and whether the newest is full."""
    subs = registry(prepared, n_sub).withColumn("slot", place("sub_id", slots))
    newest = F.max(F.struct("sub_id", "is_full"))
    return subs.groupBy("slot", "side").agg(F.sum("cnt").alias("cnt"), F.count("*").alias("subs"), newest["is_full"].alias("newest_full"))


def observed(rows: DataFrame, name: str) -> tuple[DataFrame, Observation]:
    """The same rows and an observation that an action on them fills in: tuples, tuples a side and
    the newest arrival. It rides on that action; nothing is computed twice or collected."""
    seen = Observation(name)
    count = lambda side: F.sum(F.when(F.col("side") == side, 1).otherwise(0)).alias(f"n_{side.lower()}")
    return rows.observe(seen, F.count("*").alias("n"), count("S"), count("R"), F.max("seq").alias("last_seq")), seen


def plan_commands(prepared: DataFrame, n_sub: int, slots: int, window: int) -> DataFrame:
    """Commands a batch sends: create, insert, expire and probe, by slot.

    A batch inserts into its side's subwindows, creates those that it begins, expires
    those that its side's window then has left as a whole, and probes each slot that
    holds a live, non-empty subwindow of the other side.
    """
    batches = prepared.groupBy("side", "batch_id").agg(F.min("rank").alias("first"), F.max("rank").alias("last"), F.max("opp").alias("opp"))
    subs = batches.withColumn("sub_id", F.explode(F.sequence(F.expr(f"(first - 1) div {n_sub}"), F.expr(f"(last - 1) div {n_sub}"))))
    insert = subs.select("side", "batch_id", "sub_id", F.lit("insert").alias("op"))
    create = subs.filter(F.col("sub_id") * n_sub + 1 >= F.col("first")).select("side", "batch_id", "sub_id", F.lit("create").alias("op"))
    gone = lambda upto: F.expr(f"({upto} - {window}) div {n_sub} - 1")  # noqa: E731  last subwindow wholly out
    expired = batches.withColumn("sub_id", F.explode(F.sequence(F.greatest(F.when(F.expr(f"first - 1 - {window} >= 0"), gone("first - 1") + 1).otherwise(0), F.lit(0)), F.greatest(F.when(F.expr(f"last - {window} >= 0"), gone("last")).otherwise(-1), F.lit(-1)))))
    expire = expired.filter((F.expr(f"last - {window} >= 0")) & (F.col("sub_id") >= 0) & ((F.col("sub_id") + 1) * n_sub <= F.col("last") - window) & ((F.col("sub_id") + 1) * n_sub > F.col("first") - 1 - window)).select("side", "batch_id", "sub_id", F.lit("expire").alias("op")).distinct()
    other = F.when(F.col("side") == "S", "R").otherwise("S")
    probe = batches.filter("opp > 0").withColumn("sub_id", F.explode(F.sequence(F.expr(f"greatest(0L, opp - {window}) div {n_sub}"), F.expr(f"(opp - 1) div {n_sub}")))).select(other.alias("side"), "batch_id", "sub_id", F.lit("probe").alias("op"))
    return insert.unionByName(create).unionByName(expire).unionByName(probe).withColumn("slot", place("sub_id", slots))


def pack_partitions(hist: DataFrame, tasks: int) -> DataFrame:
    """Partitions over tasks by count: sorted by size and dealt back and forth, so that tasks
    differ by one partition at most in number and little in tuples."""
    w = F.row_number().over(_by_size())
    round_ = F.expr(f"(place - 1) div {tasks}")
    at = F.expr(f"(place - 1) % {tasks}")
    return hist.withColumn("place", w).withColumn("task", F.when(round_ % 2 == 0, at).otherwise(tasks - 1 - at).cast("int")).drop("place")


def _by_size():
    from pyspark.sql import Window

    return Window.partitionBy("side", "sub_id").orderBy(F.desc("cnt"), "pid")
