"""Inputs of the registered queries: the given tables as stream tuples, and the same in SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from windowjoin.operators.sequence import cents, prefilter, sequence


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def clicks_views(spark: SparkSession, sf_dir: str, value: str = "cents", extra: tuple[str, ...] = ()) -> DataFrame:
    """S: clicks, R: views, in event order; value in cents or a column."""
    side = F.when(F.col("event_type") == "click", "S").otherwise("R")
    v = cents("value") if value == "cents" else F.col(value).cast("bigint")
    rows = prefilter(table(spark, sf_dir, "events"), F.col("event_type").isin("click", "view"), side, F.col("event_id"), v, "ts", *extra)
    return sequence(rows, ["ts", "key"], F.date_trunc("hour", "ts"))


#: S and R of clicks_views with rank, seen counts; duckdb
EVENTS = """
e AS (SELECT event_id AS key, CASE event_type WHEN 'click' THEN 'S' ELSE 'R' END AS side, {value} AS value, ts, epoch_us(ts) AS us, user_id, event_type
      FROM events WHERE event_type IN ('click', 'view')),
x AS (SELECT *, row_number() OVER (ORDER BY ts, key) AS seq, row_number() OVER (PARTITION BY side ORDER BY ts, key) AS rank,
      count(*) FILTER (WHERE side = 'S') OVER (ORDER BY ts, key ROWS UNBOUNDED PRECEDING) AS seen_s,
      count(*) FILTER (WHERE side = 'R') OVER (ORDER BY ts, key ROWS UNBOUNDED PRECEDING) AS seen_r FROM e),
s AS (SELECT * FROM x WHERE side = 'S'), r AS (SELECT * FROM x WHERE side = 'R')"""
CENTS = "CAST(round(value * 100) AS BIGINT)"


def events_sql(value: str = CENTS) -> str:
    return "WITH " + EVENTS.format(value=value).strip()


PAIR = "s.key AS s_key, r.key AS r_key, s.value AS s_value, r.value AS r_value"


def count_window_sql(condition: str, w: int = 500, select: str = PAIR, value: str = CENTS, more: str = "") -> str:
    """Pairs of the exact count window in per-tuple mode."""
    return f"""{events_sql(value)}{more}
SELECT {select} FROM s JOIN r ON {condition}
 AND ((s.seq > r.seq AND s.seen_r - r.rank < {w}) OR (r.seq > s.seq AND r.seen_s - s.rank < {w}))"""


def batch_sql(condition: str, w: int, n: int) -> str:
    """Pairs of the two-buffer batch mode."""
    return f"""{events_sql()},
b AS (SELECT side, (rank - 1) // {n} AS bid, count(*) AS n, max(seq) AS last, max(seen_s) AS ms, max(seen_r) AS mr FROM x GROUP BY ALL),
t AS (SELECT max(seen_s) AS ts_, max(seen_r) AS tr FROM x),
c AS (SELECT side, bid,
  CASE WHEN n = {n} THEN last WHEN side = 'S' THEN {1 << 60} ELSE {(1 << 60) + 1} END AS done,
  CASE WHEN n = {n} AND side = 'S' THEN mr // {n} * {n} WHEN n = {n} THEN ms // {n} * {n} WHEN side = 'S' THEN tr // {n} * {n} ELSE ts_ END AS opp FROM b, t),
y AS (SELECT x.*, c.done, c.opp FROM x JOIN c ON x.side = c.side AND (x.rank - 1) // {n} = c.bid),
sb AS (SELECT * FROM y WHERE side = 'S'), rb AS (SELECT * FROM y WHERE side = 'R')
SELECT {PAIR} FROM sb AS s JOIN rb AS r ON {condition}
 AND ((s.done > r.done AND s.opp - r.rank < {w}) OR (r.done > s.done AND r.opp - s.rank < {w}))"""


def band(eps: int) -> str:
    return f"r.value BETWEEN s.value - {eps} AND s.value + {eps}"


def wait_sql(condition: str, w: int, n: int, seconds: int) -> str:
    """The same where a clock of so many seconds closes batches too, S before R."""
    return f"""{events_sql()},
k AS (SELECT *, us // {seconds}000000 AS tick FROM x),
t AS (SELECT tick, max(seen_s) AS ts_, max(seen_r) AS tr, max(seq) AS e, max(seen_s) - count(*) FILTER (WHERE side = 'S') AS bs, max(seen_r) - count(*) FILTER (WHERE side = 'R') AS br FROM k GROUP BY tick),
z AS (SELECT k.*, ts_, tr, e, bs, br, (rank - 1 - CASE side WHEN 'S' THEN bs ELSE br END) // {n} AS bid FROM k JOIN t ON k.tick = t.tick),
c AS (SELECT tick AS ct, side AS cs, bid AS cb,
  CASE WHEN count(*) = {n} THEN 4 * max(seq) WHEN side = 'S' THEN 4 * max(e) + 1 ELSE 4 * max(e) + 2 END AS done,
  CASE WHEN count(*) = {n} AND side = 'S' THEN max(br) + (max(seen_r) - max(br)) // {n} * {n} WHEN count(*) = {n} THEN max(bs) + (max(seen_s) - max(bs)) // {n} * {n} WHEN side = 'S' THEN max(br) + (max(tr) - max(br)) // {n} * {n} ELSE max(ts_) END AS opp FROM z GROUP BY tick, side, bid),
y AS (SELECT z.*, c.done, c.opp FROM z JOIN c ON z.tick = c.ct AND z.side = c.cs AND z.bid = c.cb),
sb AS (SELECT * FROM y WHERE side = 'S'), rb AS (SELECT * FROM y WHERE side = 'R')
SELECT {PAIR} FROM sb AS s JOIN rb AS r ON {condition}
 AND ((s.done > r.done AND s.opp - r.rank < {w}) OR (r.done > s.done AND r.opp - s.rank < {w}))"""
