"""The window join: one call for every predicate, window, index structure and result form."""

from __future__ import annotations

from collections.abc import Callable, Mapping

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from windowjoin.config import BatchPolicy, CountWindow, Layout, TimeWindow
from windowjoin.operators.advisor import LARGE_BATCH
from windowjoin.operators.sequence import prepare
from windowjoin.plans import bucket, rank, worker
from windowjoin.plans import window as win
from windowjoin.predicates import Inequality, NotEqual, Predicate

KINDS = ("splitter", "wideleaf", "sorted")


def window_join(
    ranked: DataFrame,
    pred: Predicate,
    window: win.Window,
    layout: Layout | None = None,
    index: str | Mapping[int, str] | Callable[[int], str] = "auto",
    n_bat: int | BatchPolicy = 1,
    result: str = "pairs",
    extra: tuple[str, ...] = (),
    engine: str = "worker",
    adjust: bool = True,
) -> DataFrame:
    """Join the two sides of ``ranked`` (from ``sequence``) over a sliding window.

    ``index``: ``splitter`` (boundaries inherited from the subwindow before and adjusted),
    ``wideleaf`` (leaves cut as tuples come), ``sorted`` (range records), ``auto`` (chosen per
    subwindow from its predecessor's statistics), or a choice per subwindow.
    ``n_bat`` above 1 gives the two-buffer batch semantics; a ``BatchPolicy`` also closes by waiting.
    ``result``: ``pairs``, ``count`` per probe, ``ranges`` (a record per probe, subwindow and band:
    places [id_start, id_end) of the sorted run, of which tuples with ranks in [rank_from, rank_to)
    are in the window), or ``profile`` (a row of work per subwindow).
    ``extra`` names further columns that a Theta's condition or the caller needs.
    ``engine``: ``worker`` (one exchange, a subwindow in a task) or ``relational`` (equi join on
    side, subwindow and partition, or window functions; no Python).
    """
    layout = layout or Layout()
    policy = n_bat if isinstance(n_bat, BatchPolicy) else BatchPolicy(n_bat)
    n_bat = policy.max_count
    prepared = prepare(ranked, layout.n_sub, policy)
    if engine == "relational":
        return _relational(prepared, pred, window, layout, index, result, extra)
    if engine != "worker" or result not in ("pairs", "count", "ranges", "profile"):
        raise ValueError(f"{engine}, {result}")
    if isinstance(index, str) and index not in (*KINDS, "auto"):
        raise ValueError(index)
    if result in ("count", "ranges"):
        index = "sorted"
    elif index == "auto" and (isinstance(pred, Inequality | NotEqual) or n_bat >= LARGE_BATCH):
        index = "sorted"
    choose = index if isinstance(index, str) or callable(index) else _Listed(dict(index))
    found = worker.run(prepared, pred, window, layout, choose, result, extra, n_bat, adjust)
    if result == "count":
        return found.groupBy("probe_side", "probe_key").agg(F.sum("n").cast("bigint").alias("matches"))
    return bucket.theta_filter_pairs(found, pred) if result == "pairs" else found


class _Listed:
    """Structure by subwindow number, the splitter table where none is named."""

    def __init__(self, kinds: dict[int, str]):
        self.kinds = kinds

    def __call__(self, sub_id: int) -> str:
        return self.kinds.get(sub_id, "splitter")


def _relational(prepared: DataFrame, pred: Predicate, window: win.Window, layout: Layout, index: str, result: str, extra: tuple[str, ...]) -> DataFrame:
    if result == "ranges":
        return rank.range_records(prepared, pred, window, layout)
    if result == "count":
        return rank.counts_per_probe(prepared, pred, window, layout)
    if result != "pairs" or index not in KINDS:
        raise ValueError(f"{index}, {result}")
    return rank.join(prepared, pred, window, layout, extra) if index == "sorted" else bucket.join(prepared, pred, window, layout, index, extra)


def outer_join(ranked: DataFrame, pred: Predicate, window: win.Window, how: str, layout: Layout | None = None, index: str = "splitter") -> DataFrame:
    """left, right, full, semi or anti form over the S side: payload by key after the join."""
    found = window_join(ranked, pred, window, layout, index)
    s = ranked.filter("side = 'S'").select(F.col("key").alias("s_key"), F.col("value").alias("s_value"))
    r = ranked.filter("side = 'R'").select(F.col("key").alias("r_key"), F.col("value").alias("r_value"))
    if how in ("semi", "anti"):
        return s.join(found.select("s_key").distinct(), "s_key", f"left_{how}")
    keys = found.select("s_key", "r_key")
    if how == "left":
        return s.join(keys, "s_key", "left").join(r, "r_key", "left").select("s_key", "r_key", "s_value", "r_value")
    if how == "right":
        return r.join(keys, "r_key", "left").join(s, "s_key", "left").select("s_key", "r_key", "s_value", "r_value")
    if how == "full":
        left = s.join(keys, "s_key", "left").join(r, "r_key", "left").select("s_key", "r_key", "s_value", "r_value")
        alone = r.join(keys.select("r_key").distinct(), "r_key", "left_anti").select(F.lit(None).cast("bigint").alias("s_key"), "r_key", F.lit(None).cast("bigint").alias("s_value"), "r_value")
        return left.unionByName(alone)
    raise ValueError(how)


def attach(found: DataFrame, s: DataFrame, r: DataFrame, s_key: str, r_key: str) -> DataFrame:
    """Late materialisation: payload columns of both streams, only for the pairs found."""
    return found.join(s, found.s_key == s[s_key]).join(r, found.r_key == r[r_key])


def top_matches(found: DataFrame, k: int) -> DataFrame:
    """The k nearest matches of each S tuple by value, ties by key."""
    rank_ = F.row_number().over(rank.Window.partitionBy("s_key").orderBy(F.abs(F.col("r_value") - F.col("s_value")), "r_key"))
    return found.withColumn("place", rank_).filter(F.col("place") <= k)


def theta_pairs(s: DataFrame, r: DataFrame, pred: Predicate, width: int, where: str | None = None, equal: tuple[str, str] | None = None) -> DataFrame:
    """Theta join of two whole tables (no window): buckets of a fixed value width.

    ``s`` and ``r`` have key and value and any payload; ``where`` is a further condition
    over s_* and r_*. Only bands make sense here: one-sided predicates and not-equal have
    results near the product and come as ranges or counts. ``equal``: what ``where`` implies as an
    equality, an array over s_* of which one element is the expression over r_*.
    """
    if isinstance(pred, Inequality | NotEqual):
        raise ValueError("ask for ranges or counts")
    named = lambda df, p: df.select(*(F.col(c).alias(f"{p}_{c}") for c in df.columns)).filter(F.col(f"{p}_value").isNotNull())
    left, right, keys = named(s, "s"), named(r, "r").withColumn("cell", F.floor(F.col("r_value") / width)), ["cell"]
    if equal:
        left, right, keys = left.withColumn("also", F.explode(F.expr(equal[0]))), right.withColumn("also", F.expr(equal[1])), ["cell", "also"]
    out = None
    for i in pred.bounds(F.col("s_value")):
        cells = F.sequence(F.floor(i.lo / width), F.floor(i.hi / width))
        part = left.withColumn("cell", F.explode(cells)).join(right, keys).filter(i.holds(F.col("r_value"))).drop(*keys)
        out = part if out is None else out.unionByName(part)
    return out.filter(where) if where else out
