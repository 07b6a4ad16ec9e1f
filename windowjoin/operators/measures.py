"""Cost and accuracy measures, each as a table or as arithmetic."""

from __future__ import annotations

import functools
import math
import time
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from windowjoin.config import CountWindow, Layout
from windowjoin.operators.splitters import partition_histogram, splitters_below, subwindow_splitters
from windowjoin.plans import bucket
from windowjoin.plans import window as win
from windowjoin.predicates import Predicate


def throughput(run: Callable[[], DataFrame], tuples: int) -> float:
    """Input tuples a second, the result being discarded."""
    began = time.perf_counter()
    run().write.format("noop").mode("overwrite").save()
    return tuples / (time.perf_counter() - began)


def speedup(a: float, b: float) -> float:
    return a / b


def rates(run: Callable[[], DataFrame], inserts: Callable[[], DataFrame], tuples: int) -> dict[str, float]:
    """Tuples a second of the whole join, of the insertion part (no probe is sent) and of the
    rest, the probing."""
    whole, insertion = tuples / throughput(run, tuples), tuples / throughput(inserts, tuples)
    return {"system": tuples / whole, "insertion": tuples / insertion, "probing": tuples / max(1e-9, whole - insertion)}


def noop_ratio(join_rate: float, noop_rate: float) -> float:
    return join_rate / noop_rate


def energy_ratio(rate_a: float, watts_a: float, rate_b: float, watts_b: float) -> float:
    """Throughput per watt of a over b."""
    return (rate_a / watts_a) / (rate_b / watts_b)


def selectivity(found: DataFrame, probes: int, live: int) -> DataFrame:
    """Matches and matches per probe and subwindow."""
    return found.agg(F.count("*").alias("matches")).withColumn("selectivity", F.round(F.col("matches") / (probes * live), 6))


def comparisons(prepared: DataFrame, pred: Predicate, window: win.Window, layout: Layout, table: DataFrame | None = None) -> DataFrame:
    """One row: probes asked, partitions touched, tuples touched, tuples of a full scan."""
    rows = win.with_subwindows(prepared, window, layout)
    table = subwindow_splitters(rows, layout.partitions) if table is None else table
    held = win.stored(rows).join(table, bucket.KEYS).withColumn("pid", splitters_below(F.col("splitters"), F.col("st_value")).cast("int"))
    hist = held.groupBy(*bucket.KEYS, "pid").agg(F.count("*").alias("cnt"))
    sizes = hist.groupBy(*bucket.KEYS).agg(F.sum("cnt").alias("size"))
    asked = win.route(win.probes(rows), window, layout).join(table, bucket.KEYS)
    pids = []
    for lo, hi, _, _ in bucket.asked_intervals(pred, F.col("pr_value"), F.col("side") == "R"):
        first = F.lit(0) if lo is None else F.when(lo.isNull(), 0).otherwise(splitters_below(F.col("splitters"), lo))
        last = F.size("splitters") if hi is None else F.when(hi.isNull(), F.size("splitters")).otherwise(splitters_below(F.col("splitters"), hi))
        pids.append(F.sequence(first.cast("int"), last.cast("int")))
    routed = asked.select(*bucket.KEYS, "pr_key", F.array_distinct(F.flatten(F.array(*pids))).alias("pids")).join(sizes, bucket.KEYS)
    total = routed.agg(F.count("*").alias("asked"), F.sum(F.size("pids")).cast("bigint").alias("partitions"), F.sum("size").cast("bigint").alias("full_scan"))
    touched = routed.withColumn("pid", F.explode("pids")).join(hist, [*bucket.KEYS, "pid"]).agg(F.sum("cnt").cast("bigint").alias("touched"))
    return total.crossJoin(touched)  # one row each


def balance_error(placed: DataFrame, p: int) -> DataFrame:
    """Mean over the P partitions of |count - N/P| over N/P, empty partitions counted."""
    hist = partition_histogram(placed)
    n = F.sum("cnt")
    off = F.sum(F.abs(F.col("cnt") * p - F.col("total"))) + (F.lit(p) - F.count("*")) * F.max("total")
    total = placed.agg(F.count("*").alias("total"))
    return hist.crossJoin(F.broadcast(total)).agg(n.alias("n"), F.round(off / (F.max("total") * p), 6).alias("mae"))


def rounds_to_converge(errors: list[float], tolerance: float = 0.05) -> int:
    """First round within the tolerance, or from which nothing improves."""
    for k, e in enumerate(errors):
        if e <= tolerance or (k and e >= errors[k - 1]):
            return k
    return len(errors) - 1


def slot_layout(n_sub: int, p: int, sigma: float = 1.25) -> dict[str, int]:
    """Capacity of a slot and number of slots: P of the partitions, P in reserve."""
    return {"capacity": math.ceil(n_sub * sigma / p - 1e-9), "slots": 2 * p}


def storage_overhead(sigma: float = 1.25) -> dict[str, float]:
    """Extra space over the tuples, and the share of the space that is used."""
    return {"extra": 2 * sigma - 1, "utilisation": 1 / (2 * sigma)}


def metadata_overhead(p: int, n_sub: int) -> float:
    """Histograms (count, least, greatest) and splitters over the subwindow's tuples."""
    return 4 * p / n_sub


def index_bytes(p: int, value_bytes: int = 4) -> int:
    return p * value_bytes


def tree_footprint(fanout: int = 64, nodes: int = 1, value_bytes: int = 4) -> int:
    return fanout * value_bytes * nodes


def merge_cost(n: int, b: int) -> int:
    """Tuples moved while n arrive, a buffer of b being merged into the run each time it fills:
    sum over merges of run plus buffer."""
    k = n // b
    return b * k * (k + 1) // 2


def message_cost(prepared: DataFrame, window: CountWindow, layout: Layout) -> DataFrame:
    """One row: insert messages, probe messages (a slot each at most), probes over a chain of slots."""
    rows = win.with_subwindows(prepared, window, layout)
    asked = win.route(win.probes(rows), window, layout)
    per = asked.groupBy("side", "pr_key").agg(F.countDistinct(F.pmod("sub_id", F.lit(layout.slots))).alias("m"))
    n = prepared.agg(F.count("*").alias("inserts"), (F.count("*") * (layout.slots - 1)).alias("chain_hops"))
    return n.crossJoin(per.agg(F.sum("m").cast("bigint").alias("probe_messages")))


def expired_probe_share(prepared: DataFrame, pred: Predicate, window: CountWindow, layout: Layout) -> DataFrame:
    """One row: matches in the live subwindows, and those of them that the exact window drops."""
    loose = bucket.search(win.stored(r := win.with_subwindows(prepared, window, layout)), win.route(win.probes(r), window, layout), subwindow_splitters(r, layout.partitions), pred, CountWindow(window.size, exact=False))
    gone = F.when(F.col("pr_opp") - F.col("st_rank") >= window.size, 1).otherwise(0)
    return loose.agg(F.count("*").alias("coarse_matches"), F.coalesce(F.sum(gone), F.lit(0)).cast("bigint").alias("expired_matches"))


def result_size(records: DataFrame) -> DataFrame:
    """One row: non-empty range records, and the pairs that they stand for."""
    width = F.col("id_end") - F.col("id_start")
    return records.filter("id_end > id_start").agg(F.count("*").alias("range_records"), F.coalesce(F.sum(width), F.lit(0)).cast("bigint").alias("pairs"))


def same_pairs(a: DataFrame, b: DataFrame) -> bool:
    """Is the symmetric difference empty, copies counted?"""
    b = b.select(*a.columns)
    return a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()


def epsilon_for(prepared: DataFrame, wanted: int, layout: Layout, window: CountWindow, highest: int = 1 << 31) -> int:
    """Least band half-width with ``wanted`` matches or more (``highest`` if none has).

    Quantiles of both sides, from one sketch, say where to begin; exact counts, which make no
    pairs, then close in on it from there in doubling steps and by bisection.
    """
    from windowjoin.plans import worker
    from windowjoin.predicates import Band

    grid = [k / 256 for k in range(1, 256)]
    sides = {r.side: np.array(r.q or [0], np.float64) for r in prepared.groupBy("side").agg(F.percentile_approx("value", grid, 10_000).alias("q"), F.count("*").alias("n")).collect()}
    if len(sides) < 2:
        return highest
    n = prepared.filter("value is not null").agg(F.sum(F.least(F.col("opp"), F.lit(window.size)))).first()[0] or 0
    gaps = np.sort(np.abs(sides["S"][:, None] - sides["R"][None, :]).ravel())
    share = min(1.0, wanted / n) if n else 1.0
    guess = int(gaps[min(len(gaps) - 1, int(share * len(gaps)))])

    @functools.cache
    def enough(eps: int) -> bool:
        found = worker.run(prepared, Band(-eps, eps), window, layout, "sorted", "count")
        return (found.agg(F.sum("n")).first()[0] or 0) >= wanted

    step = max(1, guess // 16)
    if enough(min(guess, highest)):
        hi = min(guess, highest)
        lo = max(-1, hi - step)
        while lo >= 0 and enough(lo):
            step *= 2
            hi, lo = lo, max(-1, lo - step)
    else:
        lo = min(guess, highest)
        hi = min(highest, lo + step)
        while hi < highest and not enough(hi):
            step *= 2
            lo, hi = hi, min(highest, hi + step)
    while hi - lo > 1:  # not enough at lo, enough at hi (or it is the highest)
        mid = (lo + hi) // 2
        lo, hi = (lo, mid) if enough(mid) else (mid, hi)
    return hi


def transfer(df: DataFrame) -> dict[str, int]:
    """What the exchanges of a result move while it is computed once: bytes written, nanoseconds
    of writing, milliseconds of waiting for blocks, and rows."""
    plan = df._jdf.queryExecution()
    plan.toRdd().count()
    found = {"shuffleBytesWritten": 0, "shuffleWriteTime": 0, "fetchWaitTime": 0, "shuffleRecordsWritten": 0}
    todo = [plan.executedPlan()]
    while todo:
        node = todo.pop()
        metrics = node.metrics()
        for name in found:
            if metrics.contains(name):
                found[name] += metrics.apply(name).value()
        kind = node.getClass().getSimpleName()
        if kind == "AdaptiveSparkPlanExec":
            todo.append(node.executedPlan())
        elif kind.endswith("QueryStageExec"):
            todo.append(node.plan())
        children = node.children()
        todo += [children.apply(i) for i in range(children.size())]
    return found


def result_bytes(found: DataFrame) -> DataFrame:
    """Pairs against range records, one row: from ``ranges`` of whole or border subwindows, how many
    there are and the bytes that keys and values (four numbers a pair), or a probe's key, subwindow
    and four places (six a record) take."""
    width = F.col("id_end") - F.col("id_start")
    rows = found.filter("id_end > id_start").agg(F.count("*").alias("records"), F.coalesce(F.sum(width), F.lit(0)).cast("bigint").alias("pairs"))
    return rows.select("records", "pairs", (F.col("records") * 48).alias("record_bytes"), (F.col("pairs") * 32).alias("pair_bytes"))
