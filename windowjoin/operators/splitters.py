"""Value partitions of subwindows: splitters, histograms, adaptive adjustment.

Partition i (from 1) of P holds the values in (s[i-1], s[i]]; the last has no upper end.
So a value's partition is one more than the number of splitters below it.
"""

from __future__ import annotations

import math
from collections.abc import Sequence

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def equal_width_splitters(lo: int, hi: int, p: int) -> list[int]:
    """P-1 boundaries that cut [lo, hi] into equal widths."""
    return [lo + (hi - lo) * j // p for j in range(1, p)]


def splitters_below(splitters: Column, value: Column) -> Column:
    """Number of splitters below a value, from an array column."""
    return F.size(F.filter(splitters, lambda x: x < value))


def assign_pid(df: DataFrame, splitters: Sequence[int], value: str = "value", how: str | None = None) -> DataFrame:
    """Adds pid by one splitter array: by comparison inside the JVM for few, by binary search for many."""
    if how is None:
        how = "hof" if len(splitters) <= 64 else "arrow"
    if how == "hof":
        return df.withColumn("pid", (splitters_below(F.array(*map(F.lit, splitters)).cast("array<bigint>"), F.col(value)) + 1).cast("int"))
    if how == "arrow":
        known = np.asarray(splitters)

        @F.pandas_udf("int")
        def search(v: pd.Series) -> pd.Series:
            return pd.Series(np.searchsorted(known, v.to_numpy(), side="left") + 1)

        return df.withColumn("pid", search(value))
    if how == "merge":
        spark = df.sparkSession
        marks = spark.createDataFrame([(int(s),) for s in splitters], "mark bigint").groupBy("mark").agg(F.count("*").alias("n"))
        below = Window.orderBy("mark").rowsBetween(Window.unboundedPreceding, Window.currentRow)
        bands = marks.select("mark", F.sum("n").over(below).alias("below"), F.lead("mark").over(Window.orderBy("mark")).alias("upto"))
        joined = df.join(F.broadcast(bands), (F.col(value) > F.col("mark")) & (F.col("upto").isNull() | (F.col(value) <= F.col("upto"))), "left")
        return joined.withColumn("pid", (F.coalesce("below", F.lit(0)) + 1).cast("int")).drop("mark", "below", "upto")
    raise ValueError(how)


def partition_histogram(df: DataFrame, *keys: str, value: str = "value") -> DataFrame:
    """Count, least and greatest value per partition."""
    return df.groupBy(*keys, "pid").agg(F.count("*").alias("cnt"), F.min(value).alias("min_v"), F.max(value).alias("max_v"))


def adjust_splitters(hist: DataFrame, p: int, *keys: str) -> DataFrame:
    """New splitters (keys, j, splitter) from a histogram.

    The j-th lies where the counts reach j/P of all: inside the partition whose running
    counts enclose that, interpolated linearly between its least and greatest value.
    Whole-number form in decimals, so that nothing overflows; partitions without tuples
    enclose nothing.
    """
    d = lambda c: c.cast("decimal(38,0)")
    w = Window.partitionBy(*keys) if keys else Window.partitionBy(F.lit(0))
    run = w.orderBy("pid").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    rows = hist.filter("cnt > 0").withColumns({"cum": F.sum("cnt").over(run), "total": F.sum("cnt").over(w)})
    rows = rows.withColumn("prev", F.col("cum") - F.col("cnt"))
    first = F.expr(f"(cast(prev as decimal(38,0)) * {p}) div total") + 1
    last = F.least(F.expr(f"(cast(cum as decimal(38,0)) * {p}) div total"), F.lit(p - 1))
    picked = rows.withColumns({"first": first, "last": last}).filter("first <= last").withColumn("j", F.explode(F.sequence("first", "last")))
    moved = F.expr(f"((cast(total as decimal(20,0)) * j - cast(prev as decimal(20,0)) * {p}) * (cast(max_v as decimal(20,0)) - min_v)) div (cast(cnt as decimal(20,0)) * {p})")
    return picked.select(*keys, F.col("j").cast("int").alias("j"), (F.col("min_v") + moved).cast("bigint").alias("splitter"))


def as_list(splitters: DataFrame) -> list[int]:
    """At most P-1 numbers, to the driver."""
    return [r.splitter for r in splitters.orderBy("j").collect()]


def adapt_splitters(df: DataFrame, p: int, rounds: int, start: Sequence[int] | None = None, value: str = "value") -> list[list[int]]:
    """Splitters of each round on the same data, round 0 being ``start`` (equal width over 32 bits)."""
    out = [list(start) if start is not None else equal_width_splitters(0, 1 << 32, p)]
    for _ in range(rounds):
        out.append(as_list(adjust_splitters(partition_histogram(assign_pid(df, out[-1], value), value=value), p)))
    return out


def nearest_ranks(df: DataFrame, p: int, cells: int = 1024) -> DataFrame:
    """(j, splitter): the least value with j/P of all at or below it. Values are counted, the counts
    added up per cell of the value range, and ranks found inside the cells: no window spans the
    table, no row is copied but once for each splitter that it is."""
    per = df.filter("value is not null").groupBy("value").agg(F.count("*").alias("c"))
    cuts = df.agg(F.percentile_approx("value", [k / cells for k in range(1, cells)], 10 * cells)).first()[0] or []
    marks = F.array(*map(F.lit, sorted(set(cuts)))) if cuts else F.array().cast("array<bigint>")
    per = per.withColumn("cell", splitters_below(marks, F.col("value")))
    sums = per.groupBy("cell").agg(F.sum("c").alias("cc"))
    before = Window.orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)  # over the cells, a bounded number
    bases = sums.select("cell", F.coalesce(F.sum("cc").over(before), F.lit(0)).alias("base"), F.sum("cc").over(Window.partitionBy(F.lit(0))).alias("n"))
    inside = Window.partitionBy("cell").orderBy("value").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    rows = per.join(F.broadcast(bases), "cell").withColumn("upto", F.col("base") + F.sum("c").over(inside))
    first = F.expr(f"(upto - c) * {p} div n + 1")
    last = F.least(F.expr(f"upto * {p} div n"), F.lit(p - 1))
    picked = rows.withColumns({"first": first, "last": last}).filter("first <= last")
    return picked.select(F.explode(F.sequence(F.col("first").cast("int"), F.col("last").cast("int"))).alias("j"), F.col("value").alias("splitter"))


def quantile_splitters(df: DataFrame, p: int, how: str = "approx", value: str = "value") -> list[int]:
    """Parallel alternatives to the chain: exact nearest-rank, approximate, KLL sketch, or a hash sample."""
    if how == "exact":
        return [r.splitter for r in nearest_ranks(df.select(F.col(value).alias("value")), p).orderBy("j").collect()]
    if how == "approx":
        return df.agg(F.percentile_approx(value, [j / p for j in range(1, p)], 100 * p)).first()[0] or []
    if how == "kll":
        asked = F.array(*[F.lit(j / p) for j in range(1, p)])
        return list(df.agg(F.kll_sketch_agg_bigint(F.col(value)).alias("k")).select(F.kll_sketch_get_quantile_bigint("k", asked).alias("q")).first().q)
    if how == "sample":
        kept = df.filter(F.pmod(F.xxhash64(value, *[c for c in ("key",) if c in df.columns]), F.lit(100)) < 10)
        return kept.agg(F.percentile_approx(value, [j / p for j in range(1, p)], 100 * p)).first()[0] or []
    raise ValueError(how)


def subwindow_splitters(prepared: DataFrame, p: int, accuracy: int = 10_000) -> DataFrame:
    """(side, sub_id, splitters) of every subwindow from its own quantiles, in one aggregate; equal
    ones once, so that no value lies in two partitions. Inherited ones: ``plans.worker``."""
    asked = [j / p for j in range(1, p)]
    if p == 1:
        return prepared.filter("value is not null").select("side", "sub_id").distinct().withColumn("splitters", F.array().cast("array<bigint>"))
    own = prepared.filter("value is not null").groupBy("side", "sub_id").agg(F.percentile_approx("value", asked, accuracy).alias("q"))
    return own.select("side", "sub_id", F.array_distinct("q").cast("array<bigint>").alias("splitters"))


def drift_score(hist: DataFrame, p: int) -> DataFrame:
    """Share of tuples in the outermost partitions under inherited splitters: near 1 for monotone values."""
    edge = F.sum(F.when(F.col("pid").isin(1, p), F.col("cnt")).otherwise(0))
    return hist.groupBy("sub_id").agg(edge.cast("bigint").alias("edge_cnt"), F.sum("cnt").cast("bigint").alias("cnt"))


def adjustment_bound(p: int, bits: int = 32) -> int:
    """Most rounds of adjustment: ceil(log_P 2**bits)."""
    return math.ceil(bits / math.log2(p))


def worst_case_values(p: int, span: int = 1 << 32) -> list[int]:
    """Geometric values span / p**i: one leaves the first partition a round."""
    out, v = [], span
    while v >= 1:
        out.append(v)
        v //= p
    return out


def split_overfull(df: DataFrame, most: int, value: str = "value", keys: Sequence[str] = ("side", "sub_id")) -> DataFrame:
    """Relational twin of the wide-leaf tree: leaf numbers such that leaves hold about ``most``
    tuples at most, except where one value alone has more; no value lies in two leaves."""
    per_value = df.groupBy(*keys, value).agg(F.count("*").alias("c"))
    run = Window.partitionBy(*keys).orderBy(value).rowsBetween(Window.unboundedPreceding, -1)
    leaves = per_value.withColumn("leaf", F.expr("0") + F.floor(F.coalesce(F.sum("c").over(run), F.lit(0)) / most)).drop("c")
    return df.join(leaves, [*keys, value])
