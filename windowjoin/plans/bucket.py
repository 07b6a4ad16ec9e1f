"""Value-bucket plan: the theta join as an equi join on (side, subwindow, partition).

A stored tuple has one partition. A probe asks each partition between those of its lower
and upper bound, in each live subwindow. Only the two border partitions need the value
test; tuples of the partitions between are taken as they are. Catalyst sees an equi join
with a residual condition, so AQE can split skewed partitions and nothing is a nested
loop. Splitters come per subwindow from one aggregate. They are compared one by one in the
JVM, which is meant for few partitions; the worker plan searches them.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from windowjoin.config import Layout
from windowjoin.operators.splitters import splitters_below, subwindow_splitters
from windowjoin.plans import window as win
from windowjoin.plans import worker
from windowjoin.predicates import Interval, Predicate, Theta

KEYS = ["side", "sub_id"]
#: partitions for which comparing all splitters of a row is still cheap
MOST = 256


def asked_intervals(pred: Predicate, value: Column, probe_is_s: Column) -> list[tuple[Column | None, Column | None, Interval, Interval]]:
    """Per interval: lower and upper bound for either probing side (None where both are open)."""
    out = []
    for a, b in zip(pred.bounds(value), pred.mirrored().bounds(value), strict=True):
        pick = lambda x, y: None if x is None and y is None else F.when(probe_is_s, x if x is not None else F.lit(None)).otherwise(y if y is not None else F.lit(None))
        out.append((pick(a.lo, b.lo), pick(a.hi, b.hi), a, b))
    return out


def holds(pred: Predicate) -> Column:
    """Value condition between probe and stored tuple, whichever is S."""
    s_side = pred.residual(F.col("pr_value"), F.col("st_value"))
    r_side = pred.residual(F.col("st_value"), F.col("pr_value"))
    return F.when(F.col("side") == "R", s_side).otherwise(r_side)


def search(stored: DataFrame, asked: DataFrame, table: DataFrame, pred: Predicate, window: win.Window) -> DataFrame:
    """Joined rows (pr_*, st_*) of routed probes ``asked`` and ``stored`` tuples."""
    placed = stored.join(table, KEYS).withColumn("pid", splitters_below(F.col("splitters"), F.col("st_value"))).drop("splitters")
    routed = asked.join(table, KEYS)
    parts = []
    for lo, hi, _, _ in asked_intervals(pred, F.col("pr_value"), F.col("side") == "R"):
        first = F.lit(0) if lo is None else F.when(lo.isNull(), 0).otherwise(splitters_below(F.col("splitters"), lo))
        last = F.size("splitters") if hi is None else F.when(hi.isNull(), F.size("splitters")).otherwise(splitters_below(F.col("splitters"), hi))
        parts.append(routed.withColumns({"pid_lo": first.cast("int"), "pid_hi": last.cast("int")}).filter("pid_lo <= pid_hi"))
    wide = parts[0]
    for p in parts[1:]:
        wide = wide.unionByName(p)
    wide = wide.withColumn("pid", F.explode(F.sequence("pid_lo", "pid_hi"))).drop("splitters")
    if len(parts) > 1:  # intervals of one probe may ask for the same partition
        wide = wide.drop("pid_lo", "pid_hi").dropDuplicates(["side", "sub_id", "pr_key", "pid"])
        value_test = holds(pred)
    else:
        inner = (F.col("pid") > F.col("pid_lo")) & (F.col("pid") < F.col("pid_hi"))
        value_test = holds(pred) if isinstance(pred, Theta) else inner | holds(pred)
    found = wide.join(placed, [*KEYS, "pid"]).filter(value_test & win.in_window(window))
    return found


def theta_filter_pairs(out: DataFrame, pred: Predicate) -> DataFrame:
    """Pairs that also satisfy a Theta's own condition."""
    return out.filter(F.expr(pred.expr)) if isinstance(pred, Theta) else out


def theta_filter(found: DataFrame, pred: Predicate, extra: tuple[str, ...]) -> DataFrame:
    return theta_filter_pairs(win.pairs(found, extra), pred)


def join(prepared: DataFrame, pred: Predicate, window: win.Window, layout: Layout, kind: str = "splitter", extra: tuple[str, ...] = (), table: DataFrame | None = None) -> DataFrame:
    """Pairs of the window join."""
    if layout.partitions > MOST:
        raise ValueError(f"more than {MOST} partitions: use the worker plan")
    rows = win.with_subwindows(prepared, window, layout)
    if table is None:
        table = worker.chained_splitters(rows, layout) if kind == "splitter" else subwindow_splitters(rows, layout.partitions)
    asked = win.route(win.probes(rows, extra), window, layout)
    found = search(win.stored(rows, extra), asked, table, pred, window)
    return theta_filter(found, pred, extra)
