"""The window part of a join: which subwindows a probe meets, which pairs count.

Every tuple probes the other stream's window when it is worked on, so a pair is found
once, by its later member. Stored tuples and probes carry ``side``: that of the stored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from windowjoin.config import CountWindow, Layout, TimeWindow
from windowjoin.operators.sequence import assign_time_subwindows, time_slot

Window = CountWindow | TimeWindow | None
OTHER = {"S": "R", "R": "S"}


def with_subwindows(prepared: DataFrame, window: Window, layout: Layout) -> DataFrame:
    """sub_id by arrival, or by time for time windows (``layout.n_sub`` seconds)."""
    if isinstance(window, TimeWindow):
        return assign_time_subwindows(prepared, layout.n_sub)
    return prepared.withColumn("sub_id", F.expr(f"(rank - 1) div {layout.n_sub}"))


def stored(prepared: DataFrame, extra: tuple[str, ...] = ()) -> DataFrame:
    """Narrow table of what lies in the windows; null values never match and are left out."""
    keep = [c for c in ("ts",) if c in prepared.columns]
    return prepared.filter("value is not null").select("side", "sub_id", F.col("rank").alias("st_rank"), F.col("done").alias("st_done"), F.col("key").alias("st_key"), F.col("value").alias("st_value"), *(F.col(c).alias(f"st_{c}") for c in (*keep, *extra)))


def probes(prepared: DataFrame, extra: tuple[str, ...] = ()) -> DataFrame:
    """Narrow table of questions to the other side."""
    keep = [c for c in ("ts",) if c in prepared.columns]
    target = F.when(F.col("side") == "S", "R").otherwise("S").alias("side")
    return prepared.filter("value is not null").select(target, F.col("done").alias("pr_done"), F.col("opp").alias("pr_opp"), F.col("key").alias("pr_key"), F.col("value").alias("pr_value"), *(F.col(c).alias(f"pr_{c}") for c in (*keep, *extra)))


def live_range(window: Window, layout: Layout, opp: str = "pr_opp", micros: str = "unix_micros(cast(pr_ts as timestamp))") -> tuple[Column, Column]:
    """First and last subwindow that a probe meets; none if first > last."""
    n = layout.n_sub
    if isinstance(window, TimeWindow):
        ahead = min(window.seconds, window.disorder) * 1_000_000
        return time_slot(f"({micros} - {window.seconds * 1_000_000}L)", n), time_slot(f"({micros} + {ahead}L)", n)
    if window is None:
        return F.lit(0).cast("bigint"), F.expr(f"({opp} + {n - 1}) div {n} - 1")
    return F.expr(f"greatest(0L, {opp} - {window.size}) div {n}"), F.expr(f"({opp} + {n - 1}) div {n} - 1")


def route(asked: DataFrame, window: Window, layout: Layout) -> DataFrame:
    """A row for each subwindow that a probe meets; those without tuples are skipped by the join."""
    first, last = live_range(window, layout)
    return asked.withColumns({"first_sub": first, "last_sub": last}).filter("first_sub <= last_sub").withColumn("sub_id", F.explode(F.sequence("first_sub", "last_sub")))


def in_window(window: Window) -> Column:
    """Pair test: the stored tuple was there when the probe was worked on, and is still live."""
    earlier = F.col("pr_done") > F.col("st_done")
    if window is None:
        return earlier
    if isinstance(window, TimeWindow):
        apart = F.abs(F.expr("unix_micros(cast(pr_ts as timestamp)) - unix_micros(cast(st_ts as timestamp))"))
        return earlier & (apart <= window.seconds * 1_000_000) if window.exact else earlier
    if not window.exact:  # whole subwindows: what routing let through
        return earlier
    return earlier & (F.col("pr_opp") - F.col("st_rank") < window.size)


def pairs(found: DataFrame, extra: tuple[str, ...] = ()) -> DataFrame:
    """(s_key, r_key, s_value, r_value) whatever side probed."""
    probe_is_s = F.col("side") == "R"
    pick = lambda s, c: F.when(probe_is_s == F.lit(s == "s"), F.col(f"pr_{c}")).otherwise(F.col(f"st_{c}"))
    cols = ("key", "value", *extra)
    return found.select(*(pick(s, c).alias(f"{s}_{c}") for c in cols for s in "sr"))
