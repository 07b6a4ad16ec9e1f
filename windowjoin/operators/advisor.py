"""Which index structure fits: batch size, selectivity, stability of the values."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

# Batch and selectivity from which the sorted structure is reported best.
LARGE_BATCH, LARGE_SELECTIVITY = 1 << 16, 1 << 10
DRIFT_LIMIT = 0.5


def choose_index(n_bat: int, selectivity: float, drift: float, monotone: bool) -> str:
    """Sorted for large batches or many matches; splitter if values are stable; else wide-leaf."""
    if n_bat >= LARGE_BATCH or selectivity >= LARGE_SELECTIVITY:
        return "sorted"
    return "wideleaf" if monotone or drift > DRIFT_LIMIT else "splitter"


def column_facts(df: DataFrame, value: str, order: str, n_sub: int) -> DataFrame:
    """One row: tuples, rising neighbours, and tuples outside the range of the subwindow before.

    ``order`` numbers the tuples from 1; neighbours are compared inside subwindows and
    ranges between them, so no window spans the table.
    """
    rows = df.select(F.col(value).alias("v"), F.col(order).alias("o")).withColumn("sub", F.expr(f"(o - 1) div {n_sub}"))
    inside = Window.partitionBy("sub").orderBy("o")
    rising = rows.withColumn("up", F.when(F.col("v") >= F.lag("v").over(inside), 1).otherwise(0))
    spans = rows.groupBy("sub").agg(F.min("v").alias("lo"), F.max("v").alias("hi"))
    before = spans.select((F.col("sub") + 1).alias("sub"), "lo", "hi")
    outside = F.when((F.col("v") < F.col("lo")) | (F.col("v") > F.col("hi")), 1).otherwise(0)
    return rising.join(before, "sub", "left").agg(
        F.count("*").alias("n"), F.sum("up").cast("bigint").alias("rising"), F.sum(outside).cast("bigint").alias("outside"), F.count("lo").alias("with_before")
    )


def advise(facts: DataFrame, n_bat: int, selectivity: int) -> DataFrame:
    """(choice) per row of ``column_facts``: a value is monotone if 9 in 10 neighbours rise."""
    monotone = F.col("rising") * 10 >= F.col("n") * 9
    drifting = F.col("outside") * 2 > F.col("with_before")
    big = F.lit(n_bat >= LARGE_BATCH or selectivity >= LARGE_SELECTIVITY)
    return facts.withColumn("choice", F.when(big, "sorted").when(monotone | drifting, "wideleaf").otherwise("splitter"))
