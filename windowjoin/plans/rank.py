"""Merge-rank plan: range records instead of pairs, by window functions alone.

Stored tuples of a (side, subwindow, partition) and the bounds of the probes that fall
there are put in one order; the running count of stored tuples at a bound, plus the
tuples of the partitions before, is the bound's position in the sorted run. A probe's
result in a subwindow is then a record (id_start, id_end), however many tuples it covers.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from windowjoin.config import CountWindow, Layout, TimeWindow
from windowjoin.operators.splitters import splitters_below, subwindow_splitters
from windowjoin.plans import bucket
from windowjoin.plans import window as win
from windowjoin.predicates import Interval, NotEqual, Predicate

KEYS = ["side", "sub_id"]


def fences(placed: DataFrame, table: DataFrame) -> DataFrame:
    """(side, sub_id, pid, cnt, first_v, base) of every partition, the empty ones too."""
    every = table.select(*KEYS, F.explode(F.sequence(F.lit(0), F.size("splitters"))).alias("pid"))
    counts = placed.groupBy(*KEYS, "pid").agg(F.count("*").alias("cnt"), F.min("st_value").alias("first_v"))
    before = Window.partitionBy(*KEYS).orderBy("pid").rowsBetween(Window.unboundedPreceding, -1)
    return every.join(counts, [*KEYS, "pid"], "left").select(*KEYS, "pid", F.coalesce("cnt", F.lit(0)).alias("cnt"), "first_v", F.coalesce(F.sum("cnt").over(before), F.lit(0)).alias("base"))


def place(stored: DataFrame, table: DataFrame) -> DataFrame:
    return stored.join(table, KEYS).withColumn("pid", splitters_below(F.col("splitters"), F.col("st_value")).cast("int")).drop("splitters")


def mirror(placed: DataFrame, fence: DataFrame) -> DataFrame:
    """The sorted run with positions: (side, sub_id, pos, st_key, st_value, ...)."""
    order = Window.partitionBy(*KEYS, "pid").orderBy("st_value", "st_key")
    local = placed.withColumn("local", F.row_number().over(order) - 1)
    return local.join(fence.select(*KEYS, "pid", "base"), [*KEYS, "pid"]).withColumn("pos", F.col("base") + F.col("local")).drop("local", "base", "pid")


def _intervals(pred: Predicate, value: Column) -> tuple[list[Interval], list[Interval]]:
    if isinstance(pred, NotEqual):
        return [pred.equal_range(value)], [pred.equal_range(value)]
    return pred.bounds(value), pred.mirrored().bounds(value)


def _ranked(placed: DataFrame, marks: DataFrame) -> DataFrame:
    """Distinct marks (keys, pid, at, kind) with the number of stored tuples before each in its partition."""
    line = placed.select(*KEYS, "pid", F.col("st_value").alias("at"), F.lit(1).alias("kind"))
    order = Window.partitionBy(*KEYS, "pid").orderBy("at", "kind").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return line.unionByName(marks).withColumn("local", F.sum(F.when(F.col("kind") == 1, 1).otherwise(0)).over(order)).filter("kind <> 1")


def merge_rank(placed: DataFrame, asked: DataFrame, table: DataFrame, fence: DataFrame, pred: Predicate, dedupe_probes: bool = False) -> DataFrame:
    """(side, sub_id, pr_key, band, id_start, id_end, negated) for routed probes. With
    ``dedupe_probes`` equal bounds are placed once and the place is copied to all who ask for it."""
    from_s, from_r = _intervals(pred, F.col("pr_value"))
    routed = asked.join(table, KEYS)
    marks = []
    for band, (a, b) in enumerate(zip(from_s, from_r, strict=True)):
        for end in ("lo", "hi"):
            x, y = getattr(a, end), getattr(b, end)
            at = F.when(F.col("side") == "R", x if x is not None else F.lit(None)).otherwise(y if y is not None else F.lit(None)).cast("bigint")
            closed = F.when(F.col("side") == "R", getattr(a, f"{end}_closed")).otherwise(getattr(b, f"{end}_closed"))
            before_equals = closed if end == "lo" else ~closed
            marks.append(routed.select(*KEYS, "pr_key", F.lit(band).alias("band"), F.lit(end).alias("end"), at.alias("at"), F.when(before_equals, 0).otherwise(2).alias("kind"), splitters_below(F.col("splitters"), at).cast("int").alias("pid")))
    bounds = marks[0]
    for m in marks[1:]:
        bounds = bounds.unionByName(m)
    known = bounds.filter("at is not null")
    nothing = lambda kind: F.lit(None).cast(kind)
    line = placed.select(*KEYS, "pid", F.col("st_value").alias("at"), F.lit(1).alias("kind"), nothing(dict(known.dtypes)["pr_key"]).alias("pr_key"), nothing("int").alias("band"), nothing("string").alias("end"))
    order = Window.partitionBy(*KEYS, "pid").orderBy("at", "kind").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    ranked = line.unionByName(known.select(*line.columns)).withColumn("local", F.sum(F.when(F.col("kind") == 1, 1).otherwise(0)).over(order)).filter("kind <> 1")
    if dedupe_probes:
        once = _ranked(placed, known.select(*KEYS, "pid", "at", F.col("kind")).distinct())
        ranked = known.join(once, [*KEYS, "pid", "at", "kind"])
    placed_marks = ranked.join(fence.select(*KEYS, "pid", "base"), [*KEYS, "pid"]).select(*KEYS, "pr_key", "band", "end", (F.col("base") + F.col("local")).alias("pos"))
    open_ends = bounds.filter("at is null").join(fence.groupBy(*KEYS).agg(F.sum("cnt").alias("size")), KEYS).select(*KEYS, "pr_key", "band", "end", F.when(F.col("end") == "lo", 0).otherwise(F.col("size")).cast("bigint").alias("pos"))
    both = placed_marks.unionByName(open_ends) if any(getattr(i, e) is None for i in (*from_s, *from_r) for e in ("lo", "hi")) else placed_marks
    at = lambda e: F.max(F.when(F.col("end") == e, F.col("pos"))).cast("bigint")
    return both.groupBy(*KEYS, "pr_key", "band").agg(at("lo").alias("id_start"), at("hi").alias("id_end")).withColumn("negated", F.lit(pred.negated))


def range_records(prepared: DataFrame, pred: Predicate, window: win.Window, layout: Layout, whole_only: bool = False, dedupe_probes: bool = False) -> DataFrame:
    """Range records of every probe in every live subwindow (whole subwindows, unfiltered)."""
    rows = win.with_subwindows(prepared, window, layout)
    table = subwindow_splitters(rows, layout.partitions)
    placed = place(win.stored(rows), table)
    asked = win.route(win.probes(rows), window, layout)
    if whole_only:
        asked = with_facts(asked, win.stored(rows), window).filter(whole_subwindow(window))
    records = merge_rank(placed, asked, table, fences(placed, table), pred, dedupe_probes)
    return records.select(F.when(F.col("side") == "R", "S").otherwise("R").alias("probe_side"), F.col("pr_key").alias("probe_key"), "sub_id", "band", "id_start", "id_end", "negated")


def with_facts(asked: DataFrame, held: DataFrame, window: win.Window) -> DataFrame:
    """Routed probes with their subwindow's first rank, last arrival, oldest and newest time (a row a subwindow)."""
    facts = [F.min("st_rank").alias("first_rank"), F.max("st_done").alias("last_done")]
    if isinstance(window, TimeWindow):
        us = F.unix_micros(F.col("st_ts").cast("timestamp"))
        facts += [F.min(us).alias("oldest"), F.max(us).alias("newest")]
    return asked.join(held.groupBy(*KEYS).agg(*facts), KEYS)


def whole_subwindow(window: win.Window) -> Column:
    """Is every tuple of the routed subwindow in the probe's window? From the subwindow's facts."""
    inside = F.col("pr_done") > F.col("last_done")
    if isinstance(window, CountWindow) and window.exact:
        inside = inside & (F.col("pr_opp") - F.col("first_rank") < window.size)
    if isinstance(window, TimeWindow) and window.exact:
        us, reach = F.unix_micros(F.col("pr_ts").cast("timestamp")), window.seconds * 1_000_000
        inside = inside & (us - F.col("oldest") <= reach) & (F.col("newest") - us <= reach)
    return inside


def expand(records: DataFrame, run: DataFrame) -> DataFrame:
    """Stored tuples of each record; a negated record covers what lies outside its range."""
    sizes = run.groupBy(*KEYS).agg(F.count("*").alias("size"))
    spans = F.when(F.col("negated"), F.array(F.struct(F.lit(0).cast("bigint").alias("a"), F.col("id_start").alias("b")), F.struct(F.col("id_end").alias("a"), F.col("size").alias("b")))).otherwise(F.array(F.struct(F.col("id_start").alias("a"), F.col("id_end").alias("b"))))
    cut = records.join(sizes, KEYS).withColumn("span", F.explode(spans)).filter("span.a < span.b")
    return cut.withColumn("pos", F.explode(F.sequence(F.col("span.a"), F.col("span.b") - 1))).drop("span", "size", "id_start", "id_end").join(run, [*KEYS, "pos"])


def join(prepared: DataFrame, pred: Predicate, window: win.Window, layout: Layout, extra: tuple[str, ...] = ()) -> DataFrame:
    """Pairs: range records expanded for the subwindows inside the window, the bucket plan for the border ones."""
    rows = win.with_subwindows(prepared, window, layout)
    table = subwindow_splitters(rows, layout.partitions)
    held = win.stored(rows, extra)
    asked = with_facts(win.route(win.probes(rows, extra), window, layout), held, window)
    inside = whole_subwindow(window)
    placed = place(held, table)
    fence = fences(placed, table)
    records = merge_rank(placed, asked.filter(inside), table, fence, pred)
    # a whole subwindow below the probe's count was worked on before the probe
    wide = expand(records.drop("band"), mirror(placed, fence)).join(win.probes(rows, extra).drop("pr_opp", "pr_done", "pr_ts"), ["side", "pr_key"])
    border = bucket.search(held, asked.filter(~inside), table, pred, window)
    return bucket.theta_filter(wide, pred, extra).unionByName(bucket.theta_filter(border, pred, extra))


def counts_per_probe(prepared: DataFrame, pred: Predicate, window: win.Window, layout: Layout) -> DataFrame:
    """(probe_side, probe_key, matches) without making pairs, but for border subwindows."""
    rows = win.with_subwindows(prepared, window, layout)
    table = subwindow_splitters(rows, layout.partitions)
    held = win.stored(rows)
    placed = place(held, table)
    asked = with_facts(win.route(win.probes(rows), window, layout), held, window)
    inside = whole_subwindow(window)
    fence = fences(placed, table)
    records = merge_rank(placed, asked.filter(inside), table, fence, pred).join(fence.groupBy(*KEYS).agg(F.sum("cnt").alias("size")), KEYS)
    width = F.col("id_end") - F.col("id_start")
    whole = records.select("side", "pr_key", F.when(F.col("negated"), F.col("size") - width).otherwise(width).alias("n"))
    border = bucket.search(held, asked.filter(~inside), table, pred, window).groupBy("side", "pr_key").agg(F.count("*").alias("n"))
    out = whole.unionByName(border).groupBy("side", "pr_key").agg(F.sum("n").cast("bigint").alias("matches")).filter("matches > 0")
    return out.select(F.when(F.col("side") == "R", "S").otherwise("R").alias("probe_side"), F.col("pr_key").alias("probe_key"), "matches")
