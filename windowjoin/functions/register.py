"""SQL surface: functions, table functions and views for window joins."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf


@F.pandas_udf("int")
def partition_of(value: pd.Series, splitters: pd.Series) -> pd.Series:
    """1 + number of splitters below the value; rows with the same array are searched together."""
    out = np.zeros(len(value), np.int64)
    _, group = np.unique([np.asarray(s).tobytes() for s in splitters], return_inverse=True)
    for g in range(group.max() + 1 if len(group) else 0):
        rows = np.flatnonzero(group == g)
        out[rows] = np.searchsorted(splitters.iloc[rows[0]], value.to_numpy()[rows], side="left") + 1
    return pd.Series(out)


@udtf(returnType="pos bigint")
class ExpandRange:
    """Positions of a range record: id_start up to id_end - 1, or what lies outside of it."""

    def eval(self, id_start: int, id_end: int, negated: bool, size: int) -> Iterator[tuple[int]]:
        spans = [(0, id_start), (id_end, size)] if negated else [(id_start, id_end)]
        for a, b in spans:
            for pos in range(a, b):
                yield (pos,)


@udtf(returnType="band int, lo bigint, hi bigint")
class BandBounds:
    """Bounds of a probe for offsets given as an array lo1, hi1, lo2, hi2, ..."""

    def eval(self, value: int, offsets: list[int]) -> Iterator[tuple[int, int, int]]:
        for k in range(0, len(offsets) - 1, 2):
            yield k // 2, value + offsets[k], value + offsets[k + 1]


def register_all(spark: SparkSession) -> None:
    spark.udf.register("wj_partition_of", partition_of)
    spark.udtf.register("wj_expand_range", ExpandRange)
    spark.udtf.register("wj_band_bounds", BandBounds)


def register_views(ranked: DataFrame, found: DataFrame) -> None:
    """Session views: the stream tuples and the pairs."""
    ranked.createOrReplaceTempView("wj_tuples")
    found.createOrReplaceTempView("wj_pairs")


def bucket_join_sql(eps: int, width: int, w: int) -> str:
    """SQL text of the value-bucket plan for a band and a count window, over wj_tuples."""
    return f"""
SELECT s.key AS s_key, r.key AS r_key, s.value AS s_value, r.value AS r_value
FROM (SELECT *, explode(sequence(floor((value - {eps}) / {width}), floor((value + {eps}) / {width}))) AS cell FROM wj_tuples WHERE side = 'S') s
JOIN (SELECT *, floor(value / {width}) AS cell FROM wj_tuples WHERE side = 'R') r
  ON s.cell = r.cell AND r.value BETWEEN s.value - {eps} AND s.value + {eps}
 AND ((s.seq > r.seq AND s.seen_r - r.rank < {w}) OR (r.seq > s.seq AND r.seen_s - s.rank < {w}))"""
