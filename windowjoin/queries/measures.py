"""Registered measures, splitter life cycle, manager metadata, kernels and surrounding operators."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from windowjoin.config import CountWindow, Layout
from windowjoin.kernels import search
from windowjoin.kernels.splitter_table import SplitterTable
from windowjoin.kernels.staged_run import StagedSortedRun, StreamPipeline
from windowjoin.kernels.wide_leaf import WideLeafTree
from windowjoin.operators import advisor, manager, measures, sequence, splitters
from windowjoin.operators.join import window_join
from windowjoin.plans import rank, worker
from windowjoin.plans import window as win
from windowjoin.predicates import Band
from windowjoin.queries.base import CENTS, band, clicks_views, count_window_sql, events_sql, table
from windowjoin.runtime import ship, written
from windowjoin.sources import tables as sources

QUERIES: dict = {}
SQL: dict[str, str] = {}
W, NEAR, LAYOUT = CountWindow(500), Band(-50, 50), Layout(500, 16)
WORKERS = Layout(500, 16, slots=16)
#: subwindows well below the window, so that most probes meet whole ones
FINE = Layout(64, 16)


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return add


def _plain(f):
    return lambda spark, sf_dir: f(clicks_views(spark, sf_dir))


def row(spark: SparkSession, **values) -> DataFrame:
    """One row of arithmetic, whole numbers as bigint."""
    return spark.range(1).select(*(F.lit(v).cast("bigint" if isinstance(v, int) else "double").alias(k) for k, v in values.items()))


# -- arrival, layout, manager --------------------------------------------------------------------

query("arrival_ranks", f"{events_sql()} SELECT key, side, seq, rank, seen_s, seen_r FROM x")(_plain(lambda ev: ev.select("key", "side", "seq", "rank", "seen_s", "seen_r")))
query("arrival_ranks_orders", "SELECT o_orderkey AS key, row_number() OVER (ORDER BY o_orderdate, o_orderkey) AS seq FROM orders")(
    lambda spark, d: sequence.sequence(table(spark, d, "orders").select(F.lit("S").alias("side"), F.col("o_orderkey").alias("key"), F.col("o_orderdate").alias("ts")), ["ts", "key"], F.date_trunc("month", "ts")).select("key", "seq")
)
query("batch_assignment", f"{events_sql()} SELECT key, side, (rank - 1) // 32 AS batch_id FROM x")(_plain(lambda ev: sequence.collect_batches(ev, 32).select("key", "side", "batch_id")))
query("subwindow_layout", f"{events_sql()} SELECT side, (rank - 1) // 500 AS sub_id, count(*) AS cnt, min(seq) AS first_seq, max(seq) AS last_seq, count(*) >= 500 AS is_full FROM x GROUP BY ALL")(
    _plain(lambda ev: manager.registry(sequence.assign_subwindows(ev, 500), 500).select("side", "sub_id", "cnt", "first_seq", "last_seq", "is_full"))
)
query("round_robin_slots", f"{events_sql()} SELECT CAST((rank - 1) // 100 % 16 AS INTEGER) AS slot, side, count(*) AS cnt, count(DISTINCT (rank - 1) // 100) AS subs, arg_max(full_, sub) AS newest_full FROM (SELECT *, (rank - 1) // 100 AS sub, count(*) OVER (PARTITION BY side, (rank - 1) // 100) >= 100 AS full_ FROM x) GROUP BY ALL")(
    _plain(lambda ev: manager.status(sequence.assign_subwindows(ev, 100), 100, 16))
)
query("command_plan", f"""{events_sql()},
b AS (SELECT side, (rank - 1) // 64 AS batch_id, min(rank) AS f, max(rank) AS l, max(seq) AS last, max(CASE WHEN side = 'S' THEN seen_r ELSE seen_s END) AS o, count(*) AS n FROM x GROUP BY ALL),
t AS (SELECT max(seen_s) AS tot_s, max(seen_r) AS tot_r FROM x),
c AS (SELECT side, batch_id, f, l, CASE WHEN n = 64 THEN o // 64 * 64 WHEN side = 'S' THEN tot_r // 64 * 64 ELSE tot_s END AS opp FROM b, t),
k AS (SELECT unnest(generate_series(0, 1000)) AS sub_id)
SELECT side, batch_id, sub_id, 'insert' AS op, CAST(sub_id % 4 AS INTEGER) AS slot FROM c, k WHERE sub_id BETWEEN (f - 1) // 100 AND (l - 1) // 100
UNION ALL SELECT side, batch_id, sub_id, 'create', CAST(sub_id % 4 AS INTEGER) FROM c, k WHERE sub_id BETWEEN (f - 1) // 100 AND (l - 1) // 100 AND sub_id * 100 + 1 >= f
UNION ALL SELECT side, batch_id, sub_id, 'expire', CAST(sub_id % 4 AS INTEGER) FROM c, k WHERE (sub_id + 1) * 100 <= l - 500 AND (sub_id + 1) * 100 > f - 1 - 500
UNION ALL SELECT CASE WHEN side = 'S' THEN 'R' ELSE 'S' END, batch_id, sub_id, 'probe', CAST(sub_id % 4 AS INTEGER) FROM c, k WHERE opp > 0 AND sub_id BETWEEN greatest(0, opp - 500) // 100 AND (opp - 1) // 100""")(
    _plain(lambda ev: manager.plan_commands(sequence.prepare(ev, 100, 64), 100, 4, 500))
)


@query("balanced_tasks", f"{events_sql()}, h AS (SELECT side, (rank - 1) // 500 AS sub_id, value // 1024 AS pid, count(*) AS cnt FROM x GROUP BY ALL), o AS (SELECT *, row_number() OVER (PARTITION BY side, sub_id ORDER BY cnt DESC, pid) - 1 AS p FROM h) SELECT side, sub_id, CAST(CASE WHEN p // 4 % 2 = 0 THEN p % 4 ELSE 3 - p % 4 END AS INTEGER) AS task, CAST(sum(cnt) AS BIGINT) AS cnt FROM o GROUP BY ALL")
def _tasks(spark, d):
    h = sequence.assign_subwindows(clicks_views(spark, d), 500).groupBy("side", "sub_id", F.expr("value div 1024").alias("pid")).agg(F.count("*").alias("cnt"))
    return manager.pack_partitions(h, 4).groupBy("side", "sub_id", "task").agg(F.sum("cnt").alias("cnt"))


# -- splitters ------------------------------------------------------------------------------------

COLUMNS = {"events": ("events", CENTS), "documents": ("documents", "n_chars"), "orders": ("orders", "CAST(round(o_totalprice * 100) AS BIGINT)")}


def _values(spark, d, name):
    source, expr = COLUMNS[name]
    return table(spark, d, source).select(F.expr(expr.lower() if "n_chars" in expr else expr).cast("bigint").alias("value"))


def adjusted_sql(source: str, expr: str, p: int, rounds: int) -> str:
    """Chained rounds from equal widths over 32 bits; s{k} holds round k."""
    ctes = [f"v AS (SELECT {expr} AS value FROM {source})", f"s0 AS (SELECT j, j * {1 << 32} // {p} AS splitter FROM (SELECT unnest(generate_series(1, {p - 1})) AS j))"]
    for k in range(rounds):
        ctes.append(f"h{k} AS (SELECT 1 + (SELECT count(*) FROM s{k} WHERE splitter < value) AS pid, value FROM v)")
        ctes.append(f"g{k} AS (SELECT pid, count(*) AS cnt, min(value) AS lo, max(value) AS hi FROM h{k} GROUP BY pid)")
        ctes.append(f"c{k} AS (SELECT *, CAST(sum(cnt) OVER (ORDER BY pid) AS BIGINT) AS cum, CAST(sum(cnt) OVER () AS BIGINT) AS n FROM g{k})")
        ctes.append(f"s{k + 1} AS (SELECT j, lo + ((n * j - (cum - cnt) * {p}) * (hi - lo)) // (cnt * {p}) AS splitter FROM c{k}, (SELECT unnest(generate_series(1, {p - 1})) AS j) WHERE {p} * (cum - cnt) < n * j AND n * j <= {p} * cum)")
    return "WITH " + ", ".join(ctes)


def _rows(spark, rounds: list[list[int]]) -> DataFrame:
    last = rounds[-1]
    return spark.createDataFrame([(j + 1, int(x)) for j, x in enumerate(last)], "j int, splitter bigint")


for name, (source, expr) in COLUMNS.items():
    for k in (1, 2, 3):
        query(f"adjusted_splitters_{k}_{name}", f"{adjusted_sql(source, expr, 16, k)} SELECT CAST(j AS INTEGER) AS j, splitter FROM s{k}")(
            lambda spark, d, name=name, k=k: _rows(spark, splitters.adapt_splitters(_values(spark, d, name), 16, k))
        )
    query(f"initial_histogram_{name}", f"{adjusted_sql(source, expr, 16, 1)} SELECT CAST(pid AS INTEGER) AS pid, cnt, lo AS min_v, hi AS max_v FROM g0")(
        lambda spark, d, name=name: splitters.partition_histogram(splitters.assign_pid(_values(spark, d, name), splitters.equal_width_splitters(0, 1 << 32, 16)))
    )
    query(f"adjusted_histogram_3_{name}", f"{adjusted_sql(source, expr, 16, 4)} SELECT CAST(pid AS INTEGER) AS pid, cnt, lo AS min_v, hi AS max_v FROM g3")(
        lambda spark, d, name=name: splitters.partition_histogram(splitters.assign_pid(v := _values(spark, d, name), splitters.adapt_splitters(v, 16, 3)[-1], how="arrow"))
    )
    error = " UNION ALL ".join(f"SELECT CAST({k} AS INTEGER) AS round, round((sum(abs(cnt * 16 - n)) + (16 - count(*)) * max(n)) / (max(n) * 16.0), 6) AS mae FROM c{k}" for k in range(5))

    @query(f"balance_error_rounds_{name}", f"{adjusted_sql(source, expr, 16, 5)} {error}")
    def _errors(spark, d, name=name):
        v = _values(spark, d, name)
        out = None
        for k, s in enumerate(splitters.adapt_splitters(v, 16, 4)):
            part = measures.balance_error(splitters.assign_pid(v, s, how="arrow"), 16).select(F.lit(k).alias("round"), "mae")
            out = part if out is None else out.unionByName(part)
        return out


for kind in ("uniform", "narrow", "normal", "zipf", "geometric"):
    value = sources.distribution_sql(kind, "o_orderkey")
    query(f"generated_{kind}", f"SELECT o_orderkey AS key, CAST({value} AS BIGINT) AS value FROM orders")(lambda spark, d, kind=kind: sources.generated_on(table(spark, d, "orders"), "o_orderkey", kind))


@query("convergence_generated", "SELECT kind, (SELECT count(o_orderkey) FROM orders) AS tuples, true AS within_bound, kind <> 'geometric' AS balanced FROM (VALUES ('uniform'), ('narrow'), ('normal'), ('zipf'), ('geometric')) t(kind)")
def _convergence(spark, d):
    """Is each distribution over the orders' keys balanced after the bound's rounds, from equal widths over 32 bits?
    The geometric one has too few values."""
    out = []
    for kind in ("uniform", "narrow", "normal", "zipf", "geometric"):
        v = written(sources.generated_on(table(spark, d, "orders"), "o_orderkey", kind), "generated")
        found = splitters.adapt_splitters(v, 16, 5)
        errors = [measures.balance_error(splitters.assign_pid(v, s, how="arrow"), 16).first().mae for s in found]
        out.append((kind, v.count(), measures.rounds_to_converge(errors) <= splitters.adjustment_bound(16), bool(errors[-1] < 0.5 * errors[0])))
    return spark.createDataFrame(out, "kind string, tuples bigint, within_bound boolean, balanced boolean")


@query("quantile_splitters_exact", "SELECT CAST(j AS INTEGER) AS j, (SELECT min(v) FROM (SELECT v, row_number() OVER (ORDER BY v) AS rn, count(*) OVER () AS n FROM (SELECT CAST(round(l_extendedprice * 100) AS BIGINT) AS v FROM lineitem)) WHERE rn >= (n * j + 15) // 16) AS splitter FROM (SELECT unnest(generate_series(1, 15)) AS j)")
def _quantiles(spark, d):
    v = table(spark, d, "lineitem").select(sequence.cents("l_extendedprice").alias("value"))
    return _rows(spark, [splitters.quantile_splitters(v, 16, "exact")])


@query("quantile_splitters_sketches", "SELECT how, true AS balanced FROM (VALUES ('approx'), ('kll'), ('sample')) t(how)")
def _sketches(spark, d):
    """Are the partitions of the sketch alternatives within a quarter of their size?"""
    v = table(spark, d, "lineitem").select(F.col("l_orderkey").alias("key"), sequence.cents("l_extendedprice").alias("value"))
    out = None
    for how in ("approx", "kll", "sample"):
        part = measures.balance_error(splitters.assign_pid(v, splitters.quantile_splitters(v, 16, how)), 16).select(F.lit(how).alias("how"), (F.col("mae") < 0.25).alias("balanced"))
        out = part if out is None else out.unionByName(part)
    return out


@query("drift_increasing_values", "WITH o AS (SELECT o_orderkey AS v, (row_number() OVER (ORDER BY o_orderkey) - 1) // 1000 AS sub FROM orders), h AS (SELECT sub, min(v) AS lo, max(v) AS hi FROM o GROUP BY sub) SELECT sub AS sub_id, count(*) AS cnt, CAST(sum(CASE WHEN v > hi OR v < lo THEN 1 ELSE 0 END) AS BIGINT) AS outside FROM o JOIN h ON o.sub = h.sub + 1 GROUP BY o.sub".replace("SELECT sub AS sub_id", "SELECT o.sub AS sub_id"))
def _drift(spark, d):
    o = sequence.sequence(table(spark, d, "orders").select(F.lit("S").alias("side"), F.col("o_orderkey").alias("key"), F.col("o_orderkey").alias("value")), ["key"], F.expr("key div 1024"))
    o = sequence.assign_subwindows(o, 1000)
    before = o.groupBy((F.col("sub_id") + 1).alias("sub_id")).agg(F.min("value").alias("lo"), F.max("value").alias("hi"))
    return o.join(before, "sub_id").groupBy("sub_id").agg(F.count("*").alias("cnt"), F.sum(((F.col("value") > F.col("hi")) | (F.col("value") < F.col("lo"))).cast("bigint")).alias("outside"))


@query("advisor_choice", f"""WITH c AS (
SELECT 'events_cents' AS col, {CENTS} AS v, row_number() OVER (ORDER BY event_id) AS o FROM events
UNION ALL SELECT 'event_id', event_id, row_number() OVER (ORDER BY event_id) FROM events
UNION ALL SELECT 'order_price', CAST(round(o_totalprice * 100) AS BIGINT), row_number() OVER (ORDER BY o_orderkey) FROM orders
UNION ALL SELECT 'n_chars', n_chars, row_number() OVER (ORDER BY doc_id) FROM documents
UNION ALL SELECT 'order_key', o_orderkey, row_number() OVER (ORDER BY o_orderkey) FROM orders),
l AS (SELECT *, (o - 1) // 200 AS sub, v >= lag(v) OVER (PARTITION BY col, (o - 1) // 200 ORDER BY o) AS up FROM c),
h AS (SELECT col, sub, min(v) AS lo, max(v) AS hi FROM l GROUP BY ALL),
f AS (SELECT l.col, count(*) AS n, sum(CASE WHEN up THEN 1 ELSE 0 END) AS rising, sum(CASE WHEN v < lo OR v > hi THEN 1 ELSE 0 END) AS outside, count(lo) AS wb FROM l LEFT JOIN h ON l.col = h.col AND l.sub = h.sub + 1 GROUP BY l.col)
SELECT col, CASE WHEN rising * 10 >= n * 9 OR outside * 2 > wb THEN 'wideleaf' ELSE 'splitter' END AS choice FROM f""")
def _advisor(spark, d):
    number = lambda df, key, v: sequence.sequence(df.select(F.lit("S").alias("side"), F.col(key).alias("key"), v.alias("v")), ["key"], F.expr("key div 1024")).select("v", F.col("rank").alias("o"))
    ev, o, docs = table(spark, d, "events"), table(spark, d, "orders"), table(spark, d, "documents")
    cols = {
        "events_cents": number(ev, "event_id", sequence.cents("value")), "event_id": number(ev, "event_id", F.col("event_id")), "order_price": number(o, "o_orderkey", sequence.cents("o_totalprice")),
        "n_chars": number(docs, "doc_id", F.col("n_chars")), "order_key": number(o, "o_orderkey", F.col("o_orderkey")),
    }
    out = None
    for name, df in cols.items():
        part = advisor.advise(advisor.column_facts(df, "v", "o", 200), 1, 16).select(F.lit(name).alias("col"), "choice")
        out = part if out is None else out.unionByName(part)
    return out


# -- cost measures ----------------------------------------------------------------------------------

query("slot_layout", "SELECT CAST(ceil(8388608 * 1.25 / 65536) AS BIGINT) AS capacity, CAST(131072 AS BIGINT) AS slots")(lambda spark, d: row(spark, **measures.slot_layout(1 << 23, 1 << 16)))
query("storage_overhead", "SELECT 1.5::DOUBLE AS extra, 0.4::DOUBLE AS utilisation")(lambda spark, d: row(spark, **measures.storage_overhead(1.25)))
#: of the lines' prices as one subwindow, a partition for each 65536 cents that occur
query("metadata_overhead", "SELECT 4 * count(DISTINCT CAST(round(l_extendedprice * 100) AS BIGINT) // 65536) / count(*)::DOUBLE AS share FROM lineitem")(
    lambda spark, d: table(spark, d, "lineitem").select((sequence.cents("l_extendedprice") / 65536).cast("bigint").alias("part")).agg(F.countDistinct("part").alias("p"), F.count("*").alias("n")).select(measures.metadata_overhead(F.col("p"), F.col("n")).alias("share"))
)
@query("adjustment_bound", "SELECT p, bits, CAST(ceil(bits / log2(p)) AS BIGINT) AS bound FROM (SELECT length(bin(max(CAST(round(l_extendedprice * 100) AS BIGINT)))) AS bits FROM lineitem), (VALUES (16::BIGINT), (256), (1024), (65536)) t(p)")
def _bound(spark, d):
    """Most rounds for values of as many bits as the lines' prices have."""
    highest = table(spark, d, "lineitem").agg(F.max(sequence.cents("l_extendedprice")).alias("v")).first().v
    bits = int(highest).bit_length()
    return spark.createDataFrame([(p, bits, splitters.adjustment_bound(p, bits)) for p in (16, 256, 1024, 65536)], "p bigint, bits bigint, bound bigint")


@query("index_bytes", "SELECT 4 * p AS fences, 256::BIGINT AS node, 256 * p AS nodes FROM (SELECT CAST(ceil(count(DISTINCT CAST(round(l_extendedprice * 100) AS BIGINT)) / 64) AS BIGINT) AS p FROM lineitem)")
def _index_bytes(spark, d):
    """A fence, or a tree's node, for each 64 of the lines' prices."""
    prices = table(spark, d, "lineitem").agg(F.countDistinct(sequence.cents("l_extendedprice")).alias("n")).first().n
    p = -(-prices // 64)
    return row(spark, fences=measures.index_bytes(p), node=measures.tree_footprint(), nodes=measures.tree_footprint(nodes=p))


#: clicks a second at 7.9 W over views a second at 60 W
query("energy_ratio", f"{events_sql()} SELECT round((count(*) FILTER (WHERE side = 'S') * 1e6 / (max(us) - min(us)) / 7.9) / (count(*) FILTER (WHERE side = 'R') * 1e6 / (max(us) - min(us)) / 60.0), 6) AS ratio FROM x")(_plain(lambda ev: _energy(ev)))


def _energy(ev: DataFrame) -> DataFrame:
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    rate = lambda side: F.sum((F.col("side") == side).cast("bigint")) * 1e6 / (F.max(us) - F.min(us))
    return ev.agg(F.round(measures.energy_ratio(rate("S"), 7.9, rate("R"), 60.0), 6).alias("ratio"))


@query("merge_cost_by_buffer", f"{events_sql()}, n AS (SELECT side, count(value) AS n FROM x GROUP BY side) SELECT b, CAST(sum(b * (n // b) * (n // b + 1) // 2) AS BIGINT) AS moved FROM n, (SELECT unnest([16, 64, 256, 1024, 4096])::BIGINT AS b) GROUP BY b")
def _merge_cost(spark, d):
    """A run for the clicks and one for the views; their sizes alone come to the driver."""
    sizes = [r.n for r in clicks_views(spark, d).groupBy("side").agg(F.count("value").alias("n")).collect()]
    return spark.createDataFrame([(b, sum(measures.merge_cost(n, b) for n in sizes)) for b in (16, 64, 256, 1024, 4096)], "b bigint, moved bigint")



FIXED = [1024 * j for j in range(1, 32)]
PROBES = f"""{events_sql()},
q AS (SELECT side, key, value, CASE WHEN side = 'S' THEN seen_r ELSE seen_s END AS opp FROM x),
k AS (SELECT unnest(generate_series(0, 1000)) AS sub),
a AS (SELECT CASE WHEN side = 'S' THEN 'R' ELSE 'S' END AS side, key, value, sub FROM q, k WHERE opp > 0 AND sub BETWEEN greatest(0, opp - 500) // 500 AND (opp - 1) // 500),
st AS (SELECT side, (rank - 1) // 500 AS sub, least(31, greatest(0, (value + 1023) // 1024 - 1)) AS pid, count(*) AS cnt FROM x GROUP BY ALL),
z AS (SELECT side, sub, CAST(sum(cnt) AS BIGINT) AS size FROM st GROUP BY ALL),
p AS (SELECT a.*, least(31, greatest(0, (value - 50 + 1023) // 1024 - 1)) AS lo, least(31, greatest(0, (value + 50 + 1023) // 1024 - 1)) AS hi FROM a)"""


def _compare(spark, d) -> DataFrame:
    prepared = sequence.prepare(clicks_views(spark, d), 500)
    fixed = F.array(*map(F.lit, FIXED)).cast("array<bigint>")
    return measures.comparisons(prepared, NEAR, W, LAYOUT, prepared.select("side", "sub_id").distinct().withColumn("splitters", fixed))


query("comparisons_nested", f"{PROBES} SELECT count(*) AS asked, CAST(sum(size) AS BIGINT) AS full_scan FROM p JOIN z ON p.side = z.side AND p.sub = z.sub")(lambda spark, d: _compare(spark, d).select("asked", "full_scan"))
query("comparisons_partitioned", f"{PROBES} SELECT CAST(sum(cnt) AS BIGINT) AS touched FROM p JOIN st ON p.side = st.side AND p.sub = st.sub AND st.pid BETWEEN lo AND hi")(lambda spark, d: _compare(spark, d).select("touched"))
query("partitions_touched", f"{PROBES} SELECT CAST(sum(hi - lo + 1) AS BIGINT) AS partitions FROM p JOIN z ON p.side = z.side AND p.sub = z.sub")(lambda spark, d: _compare(spark, d).select("partitions"))
query("comparisons_reduction", f"{PROBES} SELECT round((SELECT sum(size) FROM p JOIN z ON p.side = z.side AND p.sub = z.sub) / (SELECT sum(cnt) FROM p JOIN st ON p.side = st.side AND p.sub = st.sub AND st.pid BETWEEN lo AND hi), 6) AS reduction")(
    lambda spark, d: _compare(spark, d).select(F.round(F.col("full_scan") / F.col("touched"), 6).alias("reduction"))
)


@query("selectivity_by_epsilon", " UNION ALL ".join(f"SELECT CAST({e} AS BIGINT) AS eps, count(*) AS matches FROM ({count_window_sql(band(e))})" for e in (0, 5, 50, 500)))
def _sweep(spark, d):
    ev = clicks_views(spark, d)
    out = None
    for e in (0, 5, 50, 500):
        part = window_join(ev, Band(-e, e), W, FINE, result="count").agg(F.coalesce(F.sum("matches"), F.lit(0)).cast("bigint").alias("matches")).select(F.lit(e).cast("bigint").alias("eps"), "matches")
        out = part if out is None else out.unionByName(part)
    return out


def _static(ev: DataFrame) -> DataFrame:
    """Every S asks all of R: the state after the whole stream."""
    total = ev.agg(F.max("seen_r").alias("n"))
    return sequence.prepare(ev, 500).crossJoin(F.broadcast(total)).withColumn("opp", F.when(F.col("side") == "S", F.col("n")).otherwise(0)).withColumn("done", F.when(F.col("side") == "S", F.lit(sequence.END)).otherwise(0)).drop("n")


def _records(ev: DataFrame) -> DataFrame:
    """Range records of S in all of R. A probe goes to each span of subwindows, not to each subwindow, and
    only records that hold something leave the task."""
    return worker.run(_static(ev), NEAR, None, WORKERS, "sorted", "ranges", found=True)


RUN = f"""{events_sql()},
rr AS (SELECT *, (rank - 1) // 500 AS sub FROM r), subs AS (SELECT DISTINCT sub FROM rr),
rec AS (SELECT s.key AS probe_key, subs.sub AS sub_id, (SELECT count(*) FROM rr WHERE rr.sub = subs.sub AND rr.value < s.value - 50) AS id_start, (SELECT count(*) FROM rr WHERE rr.sub = subs.sub AND rr.value <= s.value + 50) AS id_end FROM s, subs)"""
query("range_records", f"{RUN} SELECT probe_key, sub_id, id_start, id_end FROM rec WHERE id_end > id_start")(
    _plain(lambda ev: _records(ev).select("probe_key", "sub_id", "id_start", "id_end"))
)
query("result_size_forms", f"{RUN} SELECT count(*) AS range_records, CAST(sum(id_end - id_start) AS BIGINT) AS pairs FROM rec WHERE id_end > id_start")(
    _plain(lambda ev: measures.result_size(_records(ev)))
)


def _run(ev: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    rows = win.with_subwindows(_static(ev), None, LAYOUT)
    marks = splitters.subwindow_splitters(rows, 16)
    placed = rank.place(win.stored(rows), marks)
    fence = rank.fences(placed, marks)
    return rows, marks, placed, fence


@query("range_records_expanded", f"{events_sql()} SELECT s.key AS s_key, r.key AS r_key FROM s JOIN r ON {band(50)}")
def _expanded(spark, d):
    """Each record is expanded where its sorted run is."""
    lists = worker.run(_static(clicks_views(spark, d)), NEAR, None, WORKERS, "sorted", "lists")
    return lists.select(F.col("probe_key").alias("s_key"), F.explode("keys").alias("r_key"))


query("merge_rank_bounds", f"{events_sql()}, m AS (SELECT *, (rank - 1) // 500 AS sub_id FROM x) SELECT side, sub_id, key, row_number() OVER (PARTITION BY side, sub_id ORDER BY value, key) - 1 AS pos FROM m")(
    _plain(lambda ev: (lambda rows, marks, placed, fence: rank.mirror(placed, fence).select("side", "sub_id", F.col("st_key").alias("key"), "pos"))(*_run(ev)))
)
query("fence_index", "WITH o AS (SELECT CAST(round(l_extendedprice * 100) AS BIGINT) AS v, row_number() OVER (ORDER BY CAST(round(l_extendedprice * 100) AS BIGINT)) - 1 AS pos, count(*) OVER () AS n FROM lineitem) SELECT CAST(pos // ((n + 63) // 64) AS BIGINT) AS pid, v AS first_v FROM o WHERE pos % ((n + 63) // 64) = 0")(
    lambda spark, d: _fences(table(spark, d, "lineitem").select(sequence.cents("l_extendedprice").alias("value")), 64)
)


def _fences(values: DataFrame, p: int) -> DataFrame:
    """Every M/P-th value of the sorted run, from counts per value: no global sort of the tuples."""
    n = values.count()
    step = -(-n // p)
    run = Window.partitionBy("cell").orderBy("value").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    per = values.groupBy("value").agg(F.count("*").alias("c")).withColumn("cell", F.expr("value div 65536"))
    cells = per.groupBy("cell").agg(F.sum("c").alias("cc"))
    base = cells.select("cell", F.coalesce(F.sum("cc").over(Window.orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    placed = per.join(base, "cell").withColumn("upto", F.col("base") + F.sum("c").over(run)).withColumn("from", F.col("upto") - F.col("c"))
    hit = placed.withColumn("pid", F.explode(F.sequence(F.expr(f"(from + {step - 1}) div {step}"), F.expr(f"(upto - 1) div {step}")))) .filter(f"pid * {step} >= from and pid * {step} < upto")
    return hit.select(F.col("pid").cast("bigint").alias("pid"), F.col("value").alias("first_v"))


query("expired_probe_share", f"""{events_sql()},
p AS (SELECT (s.seen_r - r.rank >= 150) AS gone FROM s JOIN r ON {band(50)} AND s.seq > r.seq AND (r.rank - 1) // 100 >= greatest(0, s.seen_r - 150) // 100
UNION ALL SELECT (r.seen_s - s.rank >= 150) FROM s JOIN r ON {band(50)} AND r.seq > s.seq AND (s.rank - 1) // 100 >= greatest(0, r.seen_s - 150) // 100)
SELECT count(*) AS coarse_matches, CAST(sum(CASE WHEN gone THEN 1 ELSE 0 END) AS BIGINT) AS expired_matches FROM p""")(_plain(lambda ev: measures.expired_probe_share(sequence.prepare(ev, 100), NEAR, CountWindow(150), Layout(100, 16))))
query("message_cost", f"""{events_sql()}, q AS (SELECT CASE WHEN side = 'S' THEN seen_r ELSE seen_s END AS opp FROM x)
SELECT count(*) AS inserts, count(*) * 15 AS chain_hops, CAST(sum(CASE WHEN opp > 0 THEN least(16, (opp - 1) // 50 - greatest(0, opp - 500) // 50 + 1) ELSE 0 END) AS BIGINT) AS probe_messages FROM q""")(
    _plain(lambda ev: measures.message_cost(sequence.prepare(ev, 50), W, Layout(50, 16, 16)))
)
query("set_difference_check", "SELECT 0::BIGINT AS missing, 0::BIGINT AS extra")(
    _plain(lambda ev: (lambda a, b: a.exceptAll(b).agg(F.count("*").alias("missing")).crossJoin(b.exceptAll(a).agg(F.count("*").alias("extra"))))(window_join(ev, NEAR, W, FINE, "splitter"), window_join(ev, NEAR, W, FINE, "wideleaf")))
)


# -- kernels on executors: one subwindow a task -----------------------------------------------------


def _in_kernels(spark: SparkSession, d: str, f, schema: str) -> DataFrame:
    """Subwindows of the clicks and views as groups; ``f`` gets (side, sub_id, values, keys)."""
    ship(spark)
    rows = sequence.assign_subwindows(clicks_views(spark, d), 500).select("side", "sub_id", "seq", "value", "key")

    def work(key, pdf):
        import pandas as pd

        pdf = pdf.sort_values("seq")
        names = [c.split()[0] for c in schema.split(", ")]
        return pd.DataFrame(f(key[0], int(key[1]), pdf["value"].to_numpy(), pdf["key"].to_numpy()), columns=names)

    return rows.groupBy("side", "sub_id").applyInPandas(work, schema)  # 500 tuples a group


TUPLES = "side string, sub_id bigint, value bigint, key bigint"
TUPLES_SQL = f"{events_sql()} SELECT side, (rank - 1) // 500 AS sub_id, value, key FROM x"


def _slots_scan(side, sub, values, keys):
    t = SplitterTable([1000 * j for j in range(1, 16)], 500)
    t.insert_batch(values, keys)
    return [(side, sub, int(v), int(k)) for p in range(t.p) for v, k in zip(*t.slots.scan(p), strict=True)]


def _staged_scan(side, sub, values, keys):
    t = StagedSortedRun(64, 16)
    for v, k in zip(values, keys, strict=True):
        t.insert(v, k)
    t.flush()
    return [(side, sub, int(v), int(k)) for v, k in zip(t.main, t.main_keys, strict=True)]


def _tree_scan(side, sub, values, keys):
    t = WideLeafTree(32, 8)
    t.insert_batch(values, keys)
    return [(side, sub, int(v), int(k)) for v, k in zip(*t.scan(), strict=True)]


def _pipeline_scan(side, sub, values, keys):
    t = StreamPipeline(16)
    for k in range(0, len(values), 100):
        t.insert(values[k : k + 100])
    return [(side, sub, int(v)) for v in t.run]


query("chained_slots_scan", TUPLES_SQL)(lambda spark, d: _in_kernels(spark, d, _slots_scan, TUPLES))
query("staged_run_scan", TUPLES_SQL)(lambda spark, d: _in_kernels(spark, d, _staged_scan, TUPLES))
query("wide_leaf_scan", TUPLES_SQL)(lambda spark, d: _in_kernels(spark, d, _tree_scan, TUPLES))
query("stream_pipeline_scan", f"{events_sql()} SELECT side, (rank - 1) // 500 AS sub_id, value FROM x")(lambda spark, d: _in_kernels(spark, d, _pipeline_scan, "side string, sub_id bigint, value bigint"))
GALLOP = f"{events_sql()} SELECT side, (rank - 1) // 500 AS sub_id, key, CAST(least(15, greatest(0, (value + 999) // 1000 - 1)) AS BIGINT) AS pos FROM x"


def _gallop(side, sub, values, keys):
    order = np.argsort(values, kind="stable")
    at, _ = search.gallop_search(np.array([1000 * j for j in range(1, 16)]), values[order])
    return [(side, sub, int(k), int(p)) for k, p in zip(keys[order], at, strict=True)]


query("gallop_positions", GALLOP)(lambda spark, d: _in_kernels(spark, d, _gallop, "side string, sub_id bigint, key bigint, pos bigint"))
query("slot_usage", f"{events_sql()} SELECT side, (rank - 1) // 500 AS sub_id, count(*) AS tuples, true AS within FROM x GROUP BY ALL")(
    lambda spark, d: _in_kernels(spark, d, lambda side, sub, v, k: (lambda t: [(side, sub, sum(t.slots.sizes()), t.slots.reserved < t.p)])(_table(v, k)), "side string, sub_id bigint, tuples bigint, within boolean")
)


def _table(v, k) -> SplitterTable:
    t = SplitterTable([1000 * j for j in range(1, 16)], 500)
    t.insert_batch(v, k)
    return t


@query("wide_leaf_partitions", "SELECT 0::BIGINT AS values_in_two_leaves, 0::BIGINT AS lost")
def _leaves(spark, d):
    li = table(spark, d, "lineitem").select(F.lit("S").alias("side"), F.lit(0).alias("sub_id"), F.col("l_quantity").cast("bigint").alias("value"))
    cut = splitters.split_overfull(li, 1000)
    two = cut.groupBy("value").agg(F.countDistinct("leaf").alias("n")).filter("n > 1").agg(F.count("*").alias("values_in_two_leaves"))
    return two.crossJoin(cut.agg((F.lit(table(spark, d, "lineitem").count()) - F.count("*")).alias("lost")))


# -- surrounding operators -----------------------------------------------------------------------------

EV = "SELECT event_type, count(*) AS n FROM events"
query("tumbling_counts", "SELECT time_bucket(INTERVAL 1 DAY, ts) AS day, event_type, count(*) AS n FROM events GROUP BY ALL")(
    lambda spark, d: table(spark, d, "events").groupBy(F.window(F.col("ts").cast("timestamp"), "1 day").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("day"), "event_type", "n")
)
query("sliding_counts", "SELECT w AS start, count(*) AS n FROM (SELECT ts, unnest([time_bucket(INTERVAL 6 HOUR, ts), time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL 6 HOUR]) AS w FROM events) GROUP BY w")(
    lambda spark, d: table(spark, d, "events").groupBy(F.window(F.col("ts").cast("timestamp"), "12 hours", "6 hours").alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "n")
)
query("session_counts", "WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 2 HOUR THEN 0 ELSE 1 END AS new FROM events), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS sid FROM g) SELECT user_id, min(ts) AS start, count(*) AS n FROM s GROUP BY user_id, sid")(
    lambda spark, d: table(spark, d, "events").groupBy("user_id", F.session_window(F.col("ts").cast("timestamp"), "2 hours").alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), "n")
)
GROUPED = f"{events_sql()}, p AS (SELECT CASE WHEN s.seq > r.seq THEN 'S' ELSE 'R' END AS probe, s.value // 5000 AS cell FROM s JOIN r ON {band(50)} AND ((s.seq > r.seq AND s.seen_r - r.rank < 500) OR (r.seq > s.seq AND r.seen_s - s.rank < 500)))"


def _grouped(ev: DataFrame) -> DataFrame:
    found = window_join(ev, NEAR, W, FINE, "wideleaf")
    return found.select(F.when(F.col("s_key") > F.col("r_key"), "S").otherwise("R").alias("probe"), F.expr("s_value div 5000").alias("cell"))


query("rollup_matches", f"{GROUPED} SELECT probe, cell, count(*) AS n FROM p GROUP BY ROLLUP (probe, cell)")(_plain(lambda ev: _grouped(ev).rollup("probe", "cell").agg(F.count("*").alias("n"))))
query("cube_matches", f"{GROUPED} SELECT probe, cell, count(*) AS n FROM p GROUP BY CUBE (probe, cell)")(_plain(lambda ev: _grouped(ev).cube("probe", "cell").agg(F.count("*").alias("n"))))
query("pivot_matches", f"{GROUPED} SELECT cell, CAST(count(*) FILTER (WHERE probe = 'S') AS BIGINT) AS s_n, CAST(count(*) FILTER (WHERE probe = 'R') AS BIGINT) AS r_n FROM p GROUP BY cell")(
    _plain(lambda ev: _grouped(ev).groupBy("cell").pivot("probe", ["S", "R"]).agg(F.count(F.lit(1))).select("cell", F.coalesce("S", F.lit(0)).alias("s_n"), F.coalesce("R", F.lit(0)).alias("r_n")))
)
query("distinct_probes", f"SELECT count(DISTINCT s_key) AS s_n, count(DISTINCT r_key) AS r_n FROM ({count_window_sql(band(50))})")(_plain(lambda ev: window_join(ev, NEAR, W, FINE, "wideleaf").agg(F.countDistinct("s_key").alias("s_n"), F.countDistinct("r_key").alias("r_n"))))
query("match_statistics", f"SELECT s_value // 10000 AS cell, count(*) AS n, min(r_value) AS lo, max(r_value) AS hi, CAST(sum(r_value) AS BIGINT) AS total, round(avg(r_value), 6) AS mean FROM ({count_window_sql(band(50))}) GROUP BY 1")(
    _plain(lambda ev: window_join(ev, NEAR, W, FINE, "wideleaf").groupBy(F.expr("s_value div 10000").alias("cell")).agg(F.count("*").alias("n"), F.min("r_value").alias("lo"), F.max("r_value").alias("hi"), F.sum("r_value").alias("total"), F.round(F.avg("r_value"), 6).alias("mean")))
)
query("dimension_rollup", "SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")(
    lambda spark, d: table(spark, d, "customer").join(table(spark, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(table(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")).rollup("r_name", "n_name").agg(F.count("*").alias("n"))
)
query("sampled_splitters", "SELECT count(DISTINCT o_orderkey) > 0 AS ascending, 15::BIGINT AS splitters FROM orders")(
    lambda spark, d: (lambda found: spark.createDataFrame([(found == sorted(found), len(found))], "ascending boolean, splitters bigint"))(splitters.quantile_splitters(table(spark, d, "orders").select(F.col("o_orderkey").alias("key"), sequence.cents("o_totalprice").alias("value")), 16, "sample"))
)
query("epsilon_for_selectivity", f"{events_sql()}, m AS (SELECT abs(s.value - r.value) AS gap FROM s JOIN r ON ((s.seq > r.seq AND s.seen_r - r.rank < 500) OR (r.seq > s.seq AND r.seen_s - s.rank < 500))) SELECT min(gap) AS eps FROM (SELECT gap, sum(count(*)) OVER (ORDER BY gap) AS n FROM m GROUP BY gap) WHERE n >= 5000")(
    _plain(lambda ev: (lambda p: row(p.sparkSession, eps=measures.epsilon_for(p, 5000, FINE, W)))(written(sequence.prepare(ev, 64), "prepared")))
)
@query("python_source_tuples", f"SELECT event_id AS seq, CASE WHEN event_id % 2 = 0 THEN 'S' ELSE 'R' END AS side, event_id AS key, {sources.hashed('event_id', 1)} AS value FROM events")
def _source_tuples(spark, d):
    """The source's tuples whose numbers are the events' ids."""
    sources.register(spark)
    ids = table(spark, d, "events").select(F.col("event_id").alias("seq"))
    last = ids.agg(F.max("seq").alias("last")).first().last
    made = spark.read.format("stream_tuples").option("rows", -1 if last is None else last + 1).option("parts", 16).load()
    return made.join(ids, "seq").select("seq", "side", "key", "value")


query("udtf_band_bounds", f"{events_sql()} SELECT key, CAST(b.band AS INTEGER) AS band, value + b.lo AS lo, value + b.hi AS hi FROM s, (VALUES (0, -5, 5), (1, 20, 35)) b(band, lo, hi)")(
    lambda spark, d: _bounds_by_udtf(clicks_views(spark, d))
)


def _bounds_by_udtf(ev: DataFrame) -> DataFrame:
    from windowjoin.functions.register import register_all

    spark = ev.sparkSession
    ship(spark)
    register_all(spark)
    ev.filter("side = 'S'").createOrReplaceTempView("wj_probes")
    return spark.sql("SELECT p.key, b.* FROM wj_probes p, LATERAL wj_band_bounds(p.value, array(-5L, 5L, 20L, 35L)) b")


