"""The methods that the partitioned window join is compared with; all give the same pairs."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from windowjoin.config import Layout, TimeWindow
from windowjoin.operators.sequence import prepare
from windowjoin.plans import bucket
from windowjoin.plans import window as win
from windowjoin.predicates import Band, Predicate
from windowjoin.runtime import shuffle_width


def _reached(prepared: DataFrame, window: win.Window, blocks: int = 1) -> tuple[DataFrame, DataFrame, list[str]]:
    """Stored tuples, probes, and the columns that bring them together: the side and, for exact windows,
    runs of ``blocks`` window lengths, so that a probe is asked of its window and not of the whole stream."""
    if window is None or not window.exact:
        return win.stored(prepared).drop("sub_id"), win.probes(prepared), ["side"]
    timed = isinstance(window, TimeWindow)
    layout = Layout(max(1, blocks * (window.seconds if timed else window.size)))
    rows = win.with_subwindows(prepared if timed else prepared.drop("ts"), window, layout)
    return win.stored(rows), win.route(win.probes(rows), window, layout).drop("first_sub", "last_sub"), ["side", "sub_id"]


def _met(asked: DataFrame, held: DataFrame, keys: list[str]) -> DataFrame:
    """Equi join dealt over all of the shuffle's partitions: few bytes in make many comparisons, so neither
    a broadcast nor joined-up small partitions do."""
    width = shuffle_width(held.sparkSession)
    return asked.repartition(width, *keys).join(held.repartition(width, *keys).hint("merge"), keys)


def nested_loop(ranked: DataFrame, pred: Predicate, window: win.Window, n_bat: int = 1) -> DataFrame:
    """Every probe is compared with every tuple of the other side's window, whatever its value: the reference answer."""
    held, asked, keys = _reached(prepare(ranked, 1, n_bat), window)
    return bucket.theta_filter(_met(asked, held, keys).filter(bucket.holds(pred) & win.in_window(window)), pred, ())


def _on_slots(ranked: DataFrame, pred: Predicate, window: win.Window, slots: int, n_bat: int = 1) -> DataFrame:
    """Each tuple is kept on one core and asked of all; nested loop over the window inside a core."""
    held, asked, keys = _reached(prepare(ranked, 1, n_bat), window, 2)
    held = held.withColumn("slot", F.pmod("st_rank", F.lit(slots)).cast("int"))
    asked = asked.withColumn("slot", F.explode(F.sequence(F.lit(0), F.lit(slots - 1))))
    return _met(asked, held, [*keys, "slot"]).filter(bucket.holds(pred) & win.in_window(window))


def split_replicate(ranked: DataFrame, pred: Predicate, window: win.Window, slots: int = 16, n_bat: int = 1) -> DataFrame:
    """Each tuple is stored on one core and asked of all cores; nested loop inside a core."""
    return bucket.theta_filter(_on_slots(ranked, pred, window, slots, n_bat), pred, ())


def chain_flow(ranked: DataFrame, pred: Predicate, window: win.Window, slots: int = 16) -> DataFrame:
    """Tuples pass along a chain of cores; each is kept by its home core. Adds the hops that
    brought a pair together: the distance of the stored tuple's core from the probe's entry
    (S enters at one end, R at the other)."""
    hops = F.when(F.col("side") == "R", F.col("slot")).otherwise(F.lit(slots - 1) - F.col("slot"))
    found = _on_slots(ranked, pred, window, slots).withColumn("hops", hops)
    return win.pairs(found.withColumns({"st_hops": F.col("hops"), "pr_hops": F.col("hops")}), ("hops",)).withColumnRenamed("s_hops", "hops").drop("r_hops")


def chained_tree(ranked: DataFrame, pred: Predicate, window: win.Window, n_sub: int = 64) -> DataFrame:
    """One ordered index per subwindow, no value partitions: the architecture's ancestor."""
    from windowjoin.plans import worker

    layout = Layout(n_sub, 1)
    return bucket.theta_filter_pairs(worker.run(prepare(ranked, n_sub), pred, window, layout, "sorted"), pred)


def symmetric_hash(ranked: DataFrame, window: win.Window) -> DataFrame:
    """Hash both windows by value: equality only."""
    prepared = prepare(ranked, 1)
    held, asked = win.stored(prepared).drop("sub_id"), win.probes(prepared)
    found = asked.withColumn("v", F.col("pr_value")).join(held.withColumn("v", F.col("st_value")), ["side", "v"]).filter(win.in_window(window))
    return win.pairs(found)


def static_partitions(ranked: DataFrame, pred: Predicate, window: win.Window, layout: Layout, lo: int, hi: int) -> DataFrame:
    """Equal-width value partitions, never adjusted."""
    from windowjoin.operators.splitters import equal_width_splitters

    prepared = prepare(ranked, layout.n_sub)
    fixed = F.array(*map(F.lit, equal_width_splitters(lo, hi, layout.partitions))).cast("array<bigint>")
    table = prepared.select("side", "sub_id").distinct().withColumn("splitters", fixed)
    return bucket.join(prepared, pred, window, layout, table=table)


def no_op(ranked: DataFrame) -> None:
    """Receives and discards."""
    ranked.write.format("noop").mode("overwrite").save()


#: rows of S and of R that are met as one, and the least number of tasks that the pairs come from
BLOCKS, TASKS = {"s": 32, "r": 128}, 64


def _blocks(rows: DataFrame, side: str) -> DataFrame:
    """Rows of a cell that are neighbours by value as one row, with their least and greatest value."""
    value, fields = f"{side}_value", [c for c in rows.columns if c != "cell"]
    placed = rows.repartition(max(TASKS, shuffle_width(rows.sparkSession)), "cell").sortWithinPartitions("cell", value)
    numbered = placed.withColumn("block", F.expr(f"monotonically_increasing_id() div {BLOCKS[side]}"))
    return numbered.groupBy("cell", "block").agg(F.min(value).alias(f"{side}_least"), F.max(value).alias(f"{side}_most"), F.collect_list(F.struct(*fields)).alias(side)).drop("block")


def spark_native(s: DataFrame, r: DataFrame, pred: Predicate, width: int = 128) -> DataFrame:
    """The theta join of two tables as Spark plans it by itself. A band also says which value cells meet:
    without an equality Spark compares every S with every R. Blocks of tuples are joined and opened behind
    the join, so that the same few R follow one S after the other: a column file then has few bytes a
    pair. If all matches of an S came in one go, its pages would have as many different keys as rows."""
    test = pred.residual(F.col("s_value"), F.col("r_value"))
    if not isinstance(pred, Band):
        return s.join(r, test)
    (near,) = pred.bounds(F.col("s_value"))
    cells = F.sequence(F.floor(near.lo / width), F.floor(near.hi / width))
    left = _blocks(s.filter("s_value is not null").withColumn("cell", F.explode(cells)), "s")
    right = _blocks(r.filter("r_value is not null").withColumn("cell", F.floor(F.col("r_value") / width)), "r")
    (first,), (last,) = pred.bounds(F.col("s_least")), pred.bounds(F.col("s_most"))
    met = left.join(right.hint("merge"), "cell").filter((F.col("r_most") >= first.lo) & (F.col("r_least") <= last.hi))
    # a step without generated code: behind it a task holds the pairs of two blocks, not those of a whole S block
    met = met.select("s", "r").coalesce(max(TASKS, shuffle_width(s.sparkSession)))
    opened = met.select(F.explode("s").alias("s"), "r").select("s", F.explode("r").alias("r"))
    return opened.select("s.*", "r.*").filter(test)


def asof_join(ranked: DataFrame) -> DataFrame:
    """The last R tuple before each S tuple, for contrast: one match a probe, no window.

    Inside rank buckets by a running ``last``, across them from a table of bucket ends.
    """
    rows = ranked.withColumn("bucket", F.expr("seq div 4096"))
    is_r = F.when(F.col("side") == "R", F.struct("seq", "key", "value"))
    ends = rows.groupBy("bucket").agg(F.max(is_r).alias("end"))
    carried = ends.select("bucket", F.last("end", ignorenulls=True).over(Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)).alias("before"))
    inside = Window.partitionBy("bucket").orderBy("seq").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    found = rows.withColumn("own", F.last(is_r, ignorenulls=True).over(inside)).join(carried, "bucket").filter("side = 'S'")
    match = F.coalesce("own", "before")
    return found.select(F.col("key").alias("s_key"), match["key"].alias("r_key"), F.col("value").alias("s_value"), match["value"].alias("r_value"))
