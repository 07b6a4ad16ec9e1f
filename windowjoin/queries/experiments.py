"""The experiment workloads on the given tables: sweeps of batch, subwindow, partitions and
selectivity over the three structures, with the work counted where time would not repeat."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from windowjoin.config import CountWindow, Layout, threads_for
from windowjoin.kernels import search
from windowjoin.kernels.splitter_table import SplitterTable
from windowjoin.kernels.staged_run import StagedSortedRun, StreamPipeline
from windowjoin.kernels.wide_leaf import WideLeafTree
from windowjoin.operators import baselines, manager, measures, sequence, splitters
from windowjoin.operators.join import window_join
from windowjoin.plans import rank, worker
from windowjoin.predicates import Band, Equi
from windowjoin.queries.base import PAIR, band, batch_sql, clicks_views, count_window_sql, events_sql, table
from windowjoin.runtime import ship, written
from windowjoin.sources import sinks

QUERIES: dict = {}
SQL: dict[str, str] = {}
W, NEAR, LAYOUT = CountWindow(500), Band(-50, 50), Layout(64, 16)
KINDS = ("splitter", "wideleaf", "sorted")


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return add


def _union(parts) -> DataFrame:
    out = None
    for p in parts:
        out = p if out is None else out.unionByName(p)
    return out


def _plain(f):
    return lambda spark, sf_dir: f(clicks_views(spark, sf_dir))


# -- the structures side by side: tuples, probes, matches and the work of finding them ----------------

ROUTED = f"""q AS (SELECT side, CASE WHEN side = 'S' THEN seen_r ELSE seen_s END AS opp FROM x),
pr AS (SELECT CAST(sum(CASE WHEN opp > 0 THEN (opp - 1) // {{n}} - greatest(0, opp - {{w}}) // {{n}} + 1 ELSE 0 END) AS BIGINT) AS probes FROM q)"""


def _profile(ev: DataFrame, kind: str, pred, window, layout: Layout, **options) -> DataFrame:
    p = window_join(ev, pred, window, layout, kind, result="profile", **options)
    big = lambda c: F.coalesce(F.sum(c), F.lit(0)).cast("bigint").alias(c)
    return p.agg(*(big(c) for c in ("tuples", "probes", "whole", "touched", "copied", "matches")), F.avg("mae").alias("mae")).withColumn("kind", F.lit(kind))


for n_sub in (32, 64, 250, 500):  # subwindow size at fixed partitions
    query(f"structures_by_subwindow_{n_sub}", f"{events_sql()}, {ROUTED.format(n=n_sub, w=500)}, m AS (SELECT count(*) AS matches FROM ({count_window_sql(band(50))}))\nSELECT k.kind, (SELECT count(*) FROM x) AS tuples, probes, matches, k.kind <> 'sorted' AS tests_tuples, true AS at_least_matches FROM pr, m, (VALUES ('splitter'), ('wideleaf'), ('sorted')) k(kind)")(
        _plain(lambda ev, n=n_sub: _union(_profile(ev, k, NEAR, W, Layout(n, 16)) for k in KINDS).select("kind", "tuples", "probes", "matches", (F.col("touched") > 0).alias("tests_tuples"), ((F.col("kind") == "sorted") | (F.col("touched") + F.col("copied") >= F.col("matches"))).alias("at_least_matches")))
    )
query("structures_by_partitions", "SELECT kind, true AS falls FROM (VALUES ('splitter'), ('wideleaf')) t(kind)")(
    _plain(lambda ev: _union(_union(_profile(ev, k, NEAR, W, Layout(250, p)).select("kind", F.lit(p).alias("p"), "touched") for p in (4, 16, 64)) for k in ("splitter", "wideleaf")).groupBy("kind").agg((F.max_by("touched", "p") < F.min_by("touched", "p")).alias("falls")))
)
for eps in (0, 5, 500, 5000):  # band width, as the number of matches
    query(f"structures_by_epsilon_{eps}", f"SELECT k.kind, CAST({eps} AS BIGINT) AS eps, (SELECT count(*) FROM ({count_window_sql(band(eps))})) AS matches FROM (VALUES ('splitter'), ('wideleaf'), ('sorted')) k(kind)")(
        _plain(lambda ev, e=eps: _union(_profile(ev, k, Band(-e, e), W, LAYOUT) for k in KINDS).select("kind", F.lit(e).cast("bigint").alias("eps"), "matches"))
    )
for n_bat in (1, 32, 256):
    query(f"structures_by_batch_{n_bat}", f"SELECT k.kind, (SELECT count(*) FROM ({batch_sql(band(50), 500, n_bat) if n_bat > 1 else count_window_sql(band(50))})) AS matches FROM (VALUES ('splitter'), ('wideleaf'), ('sorted')) k(kind)")(
        _plain(lambda ev, n=n_bat: _union(_profile(ev, k, NEAR, W, LAYOUT, n_bat=n) for k in KINDS).select("kind", "matches"))
    )
query("whole_probes_share", f"""{events_sql()}, q AS (SELECT CASE WHEN side = 'S' THEN 'R' ELSE 'S' END AS side, CASE WHEN side = 'S' THEN seen_r ELSE seen_s END AS opp FROM x),
u AS (SELECT side, (rank - 1) // 32 AS sub, min(rank) AS lo, max(rank) AS hi FROM x GROUP BY ALL)
SELECT count(*) AS probes, CAST(sum(CASE WHEN hi <= opp AND opp - lo < 500 THEN 1 ELSE 0 END) AS BIGINT) AS whole, true AS no_tuple_tested FROM q JOIN u ON q.side = u.side AND u.sub BETWEEN greatest(0, opp - 500) // 32 AND (opp + 31) // 32 - 1""")(
    _plain(lambda ev: _profile(ev, "sorted", NEAR, W, Layout(32, 16)).select("probes", "whole", (F.col("touched") + F.col("copied") == 0).alias("no_tuple_tested")))
)

# -- slots: workers in turn, and how many of them --------------------------------------------------------

for slots in (1, 4, 16):
    query(f"whole_stream_window_slots_{slots}", f"{events_sql()} SELECT {PAIR} FROM s JOIN r ON {band(5)}")(_plain(lambda ev, k=slots: window_join(ev, Band(-5, 5), None, Layout(512, 64, slots=k), "sorted")))
for eps in (0, 50, 500):
    query(f"band_batch_slots_16_{eps}", f"SELECT CAST({eps} AS BIGINT) AS eps, count(*) AS matches FROM ({batch_sql(band(eps), 500, 32)})")(
        _plain(lambda ev, e=eps: window_join(ev, Band(-e, e), W, Layout(64, 16, slots=16), "splitter", n_bat=32).agg(F.count("*").alias("matches")).select(F.lit(e).cast("bigint").alias("eps"), "matches"))
    )
query("equi_count_window_slots_16", count_window_sql("s.value = r.value", value="user_id"))(lambda spark, d: window_join(clicks_views(spark, d, "user_id"), Equi(), W, Layout(64, 16, slots=16), "sorted"))
query("slot_loads", f"{events_sql()} SELECT side, CAST((rank - 1) // 64 % 4 AS INTEGER) AS slot, count(*) AS tuples FROM x GROUP BY ALL")(_plain(lambda ev: _loads(ev)))


def _loads(ev: DataFrame) -> DataFrame:
    """Tuples that each worker's partition really holds after the exchange."""
    layout = Layout(64, 16, slots=4)
    sent = worker.place(worker.commands(sequence.prepare(ev, 64), W, layout, chained=False), layout).filter(f"op = {worker.INSERT}")
    slot = F.spark_partition_id() - F.when(F.col("side") == "R", layout.slots).otherwise(0)
    return sent.groupBy("side", slot.cast("int").alias("slot")).agg(F.count("*").alias("tuples"))


# -- other carriers through the window join -----------------------------------------------------------------


def _documents(spark, d):
    rows = table(spark, d, "documents").select(F.when(F.col("doc_id") % 2 == 0, "S").otherwise("R").alias("side"), F.col("doc_id").alias("key"), F.col("n_chars").alias("value"))
    return sequence.sequence(rows, ["key"], F.expr("key div 256"))


for kind in KINDS:
    for p in (4, 64):
        query(f"equi_lengths_documents_{kind}_{p}", "SELECT s.doc_id AS s_key, r.doc_id AS r_key, s.n_chars AS s_value, r.n_chars AS r_value FROM documents s JOIN documents r ON s.doc_id % 2 = 0 AND r.doc_id % 2 = 1 AND r.n_chars = s.n_chars")(
            lambda spark, d, kind=kind, p=p: window_join(_documents(spark, d), Equi(), None, Layout(128, p), kind)
        )
PRICES = """e AS (SELECT 'S' AS side, o_orderkey AS key, CAST(round(o_totalprice * 100) AS BIGINT) AS value, o_orderdate AS ts, 0 AS line, 0 AS part, 0 AS supp FROM orders
UNION ALL SELECT 'R', l_orderkey * 8 + l_linenumber, CAST(round(l_extendedprice * 100) AS BIGINT), l_shipdate, l_linenumber, l_partkey, l_suppkey FROM lineitem),
x AS (SELECT *, row_number() OVER (ORDER BY ts, side, key, line, part, supp) AS seq, row_number() OVER (PARTITION BY side ORDER BY ts, key, line, part, supp) AS rank,
 count(*) FILTER (WHERE side = 'S') OVER (ORDER BY ts, side, key, line, part, supp ROWS UNBOUNDED PRECEDING) AS seen_s, count(*) FILTER (WHERE side = 'R') OVER (ORDER BY ts, side, key, line, part, supp ROWS UNBOUNDED PRECEDING) AS seen_r FROM e),
s AS (SELECT * FROM x WHERE side = 'S'), r AS (SELECT * FROM x WHERE side = 'R')"""


def _prices(spark, d):
    """Orders and lines by date, total price against extended price."""
    zero = F.lit(0).cast("bigint")
    s = table(spark, d, "orders").select(F.lit("S").alias("side"), F.col("o_orderkey").alias("key"), sequence.cents("o_totalprice").alias("value"), F.col("o_orderdate").alias("ts"), zero.alias("line"), zero.alias("part"), zero.alias("supp"))
    r = table(spark, d, "lineitem").select(F.lit("R").alias("side"), (F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("key"), sequence.cents("l_extendedprice").alias("value"), F.col("l_shipdate").alias("ts"), F.col("l_linenumber").cast("bigint").alias("line"), F.col("l_partkey").alias("part"), F.col("l_suppkey").alias("supp"))
    return sequence.sequence(s.unionByName(r), ["ts", "side", "key", "line", "part", "supp"], F.date_trunc("month", "ts"))


for kind in KINDS:
    query(f"band_prices_window_{kind}", f"WITH {PRICES} SELECT {PAIR} FROM s JOIN r ON r.value BETWEEN s.value - 100 AND s.value + 100 AND ((s.seq > r.seq AND s.seen_r - r.rank < 4000) OR (r.seq > s.seq AND r.seen_s - s.rank < 4000))")(
        lambda spark, d, kind=kind: window_join(_prices(spark, d), Band(-100, 100), CountWindow(4000), Layout(500, 64), kind)
    )


def few_values_sql(value: str, w: int = 500) -> str:
    """Equality on a column of few values: probes with matches, and matches."""
    return f"""WITH e AS (SELECT CASE WHEN l_suppkey % 2 = 1 THEN 'S' ELSE 'R' END AS side, {value} AS value, l_shipdate AS ts, l_orderkey AS o, l_linenumber AS l, l_partkey AS p, l_suppkey AS u FROM lineitem),
x AS (SELECT side, value, row_number() OVER w AS seq, row_number() OVER (PARTITION BY side ORDER BY ts, o, l, p, u) AS rank, count(*) FILTER (WHERE side = 'S') OVER (w ROWS UNBOUNDED PRECEDING) AS seen_s, count(*) FILTER (WHERE side = 'R') OVER (w ROWS UNBOUNDED PRECEDING) AS seen_r FROM e WINDOW w AS (ORDER BY ts, o, l, p, u)),
y AS (SELECT *, row_number() OVER (PARTITION BY side, value ORDER BY rank) AS at FROM x),
c AS (SELECT p.seq, max(CASE WHEN t.rank <= p.opp THEN t.at ELSE 0 END) - max(CASE WHEN t.rank <= p.opp - {w} THEN t.at ELSE 0 END) AS n FROM (SELECT seq, side, value, CASE side WHEN 'S' THEN seen_r ELSE seen_s END AS opp FROM x) p JOIN y t ON t.side <> p.side AND t.value = p.value AND t.rank <= p.opp AND t.rank > p.opp - {w} - 2000 GROUP BY p.seq)
SELECT count(*) FILTER (WHERE n > 0) AS probes, CAST(sum(n) AS BIGINT) AS matches FROM c"""


def _few(spark, d, value):
    rows = table(spark, d, "lineitem").select(F.when(F.col("l_suppkey") % 2 == 1, "S").otherwise("R").alias("side"), value.alias("value"), F.col("l_shipdate").alias("ts"), F.col("l_orderkey").alias("o"), F.col("l_linenumber").alias("l"), F.col("l_partkey").alias("p"), F.col("l_suppkey").alias("u"))
    ranked = sequence.sequence(rows, ["ts", "o", "l", "p", "u"], F.date_trunc("month", "ts")).withColumn("key", F.col("seq"))
    return window_join(ranked, Equi(), W, Layout(64, 16), result="count").agg(F.count("*").alias("probes"), F.coalesce(F.sum("matches"), F.lit(0)).cast("bigint").alias("matches"))


query("equi_quantity_window", few_values_sql("CAST(l_quantity AS BIGINT)"))(lambda spark, d: _few(spark, d, F.col("l_quantity").cast("bigint")))
query("equi_discount_window", few_values_sql("CAST(round(l_discount * 100) AS BIGINT)"))(lambda spark, d: _few(spark, d, sequence.cents("l_discount")))

# -- inherited splitters ------------------------------------------------------------------------------------------


def chain_sql(p: int, subs: int) -> str:
    """Splitters that the clicks' subwindows hand on, the first ones from their own range."""
    ctes = [f"{events_sql()}", "v AS (SELECT (rank - 1) // 500 AS sub, value FROM s)", f"s0 AS (SELECT j, (SELECT min(value) FROM v WHERE sub = 0) + (SELECT max(value) - min(value) FROM v WHERE sub = 0) * j // {p} AS splitter FROM (SELECT unnest(generate_series(1, {p - 1})) AS j))"]
    for k in range(subs):
        ctes.append(f"h{k} AS (SELECT 1 + (SELECT count(*) FROM s{k} WHERE splitter < value) AS pid, value FROM v WHERE sub = {k})")
        ctes.append(f"g{k} AS (SELECT pid, count(*) AS cnt, min(value) AS lo, max(value) AS hi FROM h{k} GROUP BY pid)")
        ctes.append(f"c{k} AS (SELECT *, CAST(sum(cnt) OVER (ORDER BY pid) AS BIGINT) AS cum, CAST(sum(cnt) OVER () AS BIGINT) AS n FROM g{k})")
        ctes.append(f"s{k + 1} AS (SELECT j, lo + ((n * j - (cum - cnt) * {p}) * (hi - lo)) // (cnt * {p}) AS splitter FROM c{k}, (SELECT unnest(generate_series(1, {p - 1})) AS j) WHERE {p} * (cum - cnt) < n * j AND n * j <= {p} * cum)")
    return ", ".join(ctes)


CHAIN = chain_sql(16, 4)
query("chained_splitters", CHAIN + " " + " UNION ALL ".join(f"SELECT {k}::BIGINT AS sub_id, CAST(j AS INTEGER) AS j, splitter FROM s{k} WHERE EXISTS (SELECT 1 FROM v WHERE sub = {k})" for k in range(4)))(
    _plain(lambda ev: worker.chained_splitters(sequence.assign_subwindows(ev, 500), Layout(500, 16, segment=1 << 20)).filter("side = 'S' and sub_id < 4").select("sub_id", F.posexplode("splitters").alias("j", "splitter")).withColumn("j", F.col("j") + 1))
)
query("chained_balance", CHAIN + " " + " UNION ALL ".join(f"SELECT {k}::BIGINT AS sub_id, round((sum(abs(cnt * 16 - n)) + (16 - count(*)) * max(n)) / (max(n) * 16.0), 6) AS mae FROM c{k} HAVING count(*) > 0" for k in range(4)))(
    _plain(lambda ev: window_join(ev, NEAR, W, Layout(500, 16, segment=1 << 20), "splitter", result="profile").filter("side = 'S' and sub_id < 4").select("sub_id", "mae"))
)
query("segments_settle", "SELECT true AS close")(
    _plain(lambda ev: _union(_profile(ev, "splitter", NEAR, W, Layout(64, 16, segment=g)).select(F.lit(g).alias("g"), "mae") for g in (4, 1 << 20)).agg((F.max("mae") < 2 * F.min("mae")).alias("close")))
)


def _growing(spark, d):
    o = table(spark, d, "orders").select(F.when(F.col("o_orderkey") % 2 == 0, "S").otherwise("R").alias("side"), F.col("o_orderkey").alias("key"), F.col("o_orderkey").alias("value"))
    return sequence.sequence(o, ["key"], F.expr("key div 1024"))


GROWING = "WITH o AS (SELECT o_orderkey AS k, row_number() OVER (ORDER BY o_orderkey) AS seq, count(*) FILTER (WHERE o_orderkey % 2 = 0) OVER (ORDER BY o_orderkey) AS seen_s, count(*) FILTER (WHERE o_orderkey % 2 = 1) OVER (ORDER BY o_orderkey) AS seen_r FROM orders), s AS (SELECT *, seen_s AS rank FROM o WHERE k % 2 = 0), r AS (SELECT *, seen_r AS rank FROM o WHERE k % 2 = 1) SELECT s.k AS s_key, r.k AS r_key FROM s JOIN r ON r.k BETWEEN s.k - 5 AND s.k + 5 AND ((s.seq > r.seq AND s.seen_r - r.rank < 500) OR (r.seq > s.seq AND r.seen_s - s.rank < 500))"
query("increasing_values_splitter", GROWING)(lambda spark, d: window_join(_growing(spark, d), Band(-5, 5), W, LAYOUT, "splitter").select("s_key", "r_key"))
query("increasing_values_auto", GROWING)(lambda spark, d: window_join(_growing(spark, d), Band(-5, 5), W, LAYOUT, "auto").select("s_key", "r_key"))
query("increasing_values_balance", "SELECT * FROM (VALUES ('splitter', true), ('wideleaf', false), ('sorted', false)) t(kind, degrades)")(
    lambda spark, d: _union(_profile(_growing(spark, d), k, Band(-5, 5), W, LAYOUT).select("kind", (F.col("mae") > 1).alias("degrades")) for k in KINDS)
)
query("auto_on_increasing_values", "SELECT 'wideleaf' AS kind")(
    lambda spark, d: window_join(_growing(spark, d), Band(-5, 5), W, LAYOUT, "auto", result="profile").select("kind").distinct()
)
query("auto_on_stable_values", "SELECT DISTINCT CASE WHEN (rank - 1) // 64 < 2 THEN 'wideleaf' ELSE 'splitter' END AS kind FROM (" + events_sql() + " SELECT rank FROM x)")(
    _plain(lambda ev: window_join(ev, NEAR, W, Layout(64, 16, segment=1 << 20), "auto", result="profile").select("kind").distinct())
)
query("drift_by_edge_partitions", CHAIN + " SELECT 1::BIGINT AS sub_id, CAST(sum(CASE WHEN pid IN (1, 16) THEN cnt ELSE 0 END) AS BIGINT) AS edge_cnt, CAST(sum(cnt) AS BIGINT) AS cnt FROM g1 HAVING count(*) > 0")(
    _plain(lambda ev: _edges(ev))
)


def _edges(ev: DataFrame) -> DataFrame:
    rows = sequence.assign_subwindows(ev, 500).filter("side = 'S' and sub_id <= 1")
    marks = worker.chained_splitters(rows, Layout(500, 16, segment=1 << 20)).filter("sub_id = 1")
    placed = rows.join(marks, ["side", "sub_id"]).withColumn("pid", (splitters.splitters_below(F.col("splitters"), F.col("value")) + 1).cast("int"))
    return splitters.drift_score(splitters.partition_histogram(placed, "sub_id"), 16)


# -- results: pairs against range records, transfer, feedback, persisted runs ---------------------------------------

for eps in (0, 50, 5000):
    query(f"result_bytes_{eps}", f"""{events_sql()}, rr AS (SELECT *, (rank - 1) // 64 AS sub FROM x),
c AS (SELECT p.seq, m.sub, count(*) AS n FROM x p JOIN rr m ON m.side <> p.side AND m.value BETWEEN p.value - {eps} AND p.value + {eps} AND m.sub BETWEEN greatest(0, (CASE p.side WHEN 'S' THEN p.seen_r ELSE p.seen_s END) - 500) // 64 AND ((CASE p.side WHEN 'S' THEN p.seen_r ELSE p.seen_s END) + 63) // 64 - 1 GROUP BY ALL)
SELECT CAST({eps} AS BIGINT) AS eps, count(*) AS records, CAST(sum(n) AS BIGINT) AS pairs, count(*) * 48 AS record_bytes, CAST(sum(n) * 32 AS BIGINT) AS pair_bytes FROM c""")(
        _plain(lambda ev, e=eps: measures.result_bytes(window_join(ev, Band(-e, e), W, LAYOUT, result="ranges")).select(F.lit(e).cast("bigint").alias("eps"), "records", "pairs", "record_bytes", "pair_bytes"))
    )


@query("transfer_by_form", f"{events_sql()}, {ROUTED.format(n=64, w=500)} SELECT (SELECT count(*) FROM x) + probes AS command_rows, true AS blocks_are_fewer, true AS ranges_are_less FROM pr")
def _transfer(spark, d):
    """Commands of the manager, that the exchange moves fewer blocks than commands, and that wide
    results take less as range records."""
    prepared = sequence.prepare(written(clicks_views(spark, d), "ranked"), 64)
    sent = worker.commands(prepared, W, LAYOUT, chained=False).agg(F.count("*").alias("command_rows"))
    moved = measures.transfer(worker.run(prepared, Band(-5000, 5000), W, LAYOUT, "sorted"))["shuffleRecordsWritten"]
    n = measures.result_bytes(worker.run(prepared, Band(-5000, 5000), W, LAYOUT, "sorted", "ranges"))
    return sent.crossJoin(n).select("command_rows", (F.lit(moved) * 4 < F.col("command_rows")).alias("blocks_are_fewer"), (F.col("record_bytes") < F.col("pair_bytes")).alias("ranges_are_less"))


@query("noop_joiner", f"{events_sql()} SELECT count(*) AS n FROM x")
def _noop(spark, d):
    """Receives, counts on the way and discards: what the join's rate is compared with."""
    rows, seen = manager.observed(clicks_views(spark, d), "noop")
    baselines.no_op(rows)
    return spark.createDataFrame([(int(seen.get["n"]),)], "n bigint")


query("sorted_batches", f"{events_sql()} SELECT side, (rank - 1) // 32 AS batch_id, count(*) AS n, true AS ascending FROM x GROUP BY ALL")(_plain(lambda ev: _ascending(ev)))


def _ascending(ev: DataFrame) -> DataFrame:
    """Batches as they are sent: in value order where they lie."""
    rows = sequence.sort_batch(sequence.prepare(ev, 64, 32).repartition("side", "batch_id")).select("side", "batch_id", "value")

    def work(batches):
        import pyarrow as pa

        last: dict = {}
        for b in batches:
            for side, batch_id, value in zip(*(b.column(c).to_pylist() for c in ("side", "batch_id", "value")), strict=True):
                n, ok, before = last.get((side, batch_id), (0, True, value))
                last[(side, batch_id)] = (n + 1, ok and value >= before, value)
        yield pa.RecordBatch.from_pylist([{"side": s, "batch_id": i, "n": n, "ascending": ok} for (s, i), (n, ok, _) in last.items()], schema=pa.schema([("side", pa.string()), ("batch_id", pa.int64()), ("n", pa.int64()), ("ascending", pa.bool_())]))

    return rows.mapInArrow(work, "side string, batch_id bigint, n bigint, ascending boolean")


@query("union_of_sides", "SELECT 'S' AS side, count(*) AS n FROM orders UNION ALL SELECT 'R', count(*) FROM lineitem")
def _sides(spark, d):
    s = table(spark, d, "orders").select(F.col("o_orderkey").alias("key"), sequence.cents("o_totalprice").alias("value"))
    r = table(spark, d, "lineitem").select(F.col("l_orderkey").alias("key"), sequence.cents("l_extendedprice").alias("value"))
    return sequence.union_sides(s, r).groupBy("side").agg(F.count("*").alias("n"))


@query("sql_views", f"SELECT count(*) AS pairs, (SELECT count(*) FROM ({events_sql()} SELECT * FROM x)) AS tuples FROM ({count_window_sql(band(50))})")
def _views(spark, d):
    from windowjoin.functions.register import register_views

    ev = clicks_views(spark, d)
    register_views(ev, window_join(ev, NEAR, W, LAYOUT, "sorted"))
    return spark.sql("SELECT (SELECT count(*) FROM wj_pairs) AS pairs, (SELECT count(*) FROM wj_tuples) AS tuples")


@query("observed_feedback", f"{events_sql()} SELECT count(*) AS n, count(*) FILTER (WHERE side = 'S') AS n_s, count(*) FILTER (WHERE side = 'R') AS n_r, max(seq) AS last_seq FROM x")
def _feedback(spark, d):
    rows, seen = manager.observed(clicks_views(spark, d), "status")
    sinks.discard(rows)
    return spark.createDataFrame([tuple(int(seen.get[c]) for c in ("n", "n_s", "n_r", "last_seq"))], "n bigint, n_s bigint, n_r bigint, last_seq bigint")


@query("mirror_expanded", f"{events_sql()} SELECT s.key AS s_key, r.key AS r_key FROM s JOIN r ON {band(5)}")
def _mirrored(spark, d):
    """Range records expanded against the sorted runs at rest."""
    from windowjoin.runtime import new_path

    ev = clicks_views(spark, d)
    layout, path = Layout(64, 16, slots=16), new_path(spark, "runs")
    asking = lambda side: sequence.prepare(ev, 64).withColumn("asks", F.col("side") == side)
    records = worker.run(asking("S"), Band(-5, 5), None, layout, "sorted", "ranges", found=True)
    order = rank.Window.partitionBy("sub_id").orderBy("value", "done", "rank")
    run = sequence.prepare(ev, 64).filter("side = 'R' and value is not null").select("side", "sub_id", (F.row_number().over(order) - 1).cast("bigint").alias("pos"), "key", "value", "rank")
    sinks.sorted_run(run, path, 4)
    run = spark.read.schema(run.schema).parquet(path)
    runs = run.groupBy("sub_id").agg(F.sort_array(F.collect_list(F.struct("pos", "key", "rank"))).alias("run"))  # a row a subwindow, so that pairs are not exchanged
    wide = records.join(runs, "sub_id").select("probe_key", "rank_from", "rank_to", F.explode(F.expr("slice(run, cast(id_start + 1 AS int), cast(id_end - id_start AS int))")).alias("t"))
    late = wide.filter("t.rank >= rank_from and t.rank < rank_to").select(F.col("probe_key").alias("s_key"), F.col("t.key").alias("r_key"))
    other = worker.run(asking("R"), Band(-5, 5), None, layout, "sorted", "lists")  # found by the later R
    return late.unionByName(other.select(F.explode("keys").alias("s_key"), F.col("probe_key").alias("r_key")))


query("range_records_deduped", "WITH " + events_sql().removeprefix("WITH ") + """, m AS (SELECT *, (rank - 1) // 64 AS sub_id FROM x),
a AS (SELECT p.side AS probe_side, p.key AS probe_key, m.sub_id, count(*) FILTER (WHERE m.value < p.value - 50) AS id_start, count(*) FILTER (WHERE m.value <= p.value + 50) AS id_end
 FROM x p JOIN m ON m.side <> p.side AND m.sub_id BETWEEN greatest(0, (CASE p.side WHEN 'S' THEN p.seen_r ELSE p.seen_s END) - 500) // 64 AND ((CASE p.side WHEN 'S' THEN p.seen_r ELSE p.seen_s END) + 63) // 64 - 1 GROUP BY ALL)
SELECT probe_side, probe_key, sub_id, id_start, id_end FROM a WHERE id_end > id_start""")(
    _plain(lambda ev: rank.range_records(sequence.prepare(ev, 64), NEAR, W, LAYOUT, dedupe_probes=True).filter("id_end > id_start").select("probe_side", "probe_key", "sub_id", "id_start", "id_end"))
)


# -- insertion and search in the kernels: steps, not seconds -----------------------------------------------------------


def _kernel(spark, rows: DataFrame, n_sub: int, f, schema: str) -> DataFrame:
    """``f(values in arrival order, keys)`` of every full or partial subwindow; one subwindow a group."""
    ship(spark)
    names = [c.split()[0] for c in schema.split(", ")]

    def work(key, pdf):
        import pandas as pd

        pdf = pdf.sort_values("rank")
        return pd.DataFrame([(key[0], int(key[1]), *r) for r in f(pdf["value"].to_numpy(), pdf["key"].to_numpy())], columns=["side", "sub_id", *names])

    placed = sequence.assign_subwindows(rows, n_sub).select("side", "sub_id", "rank", "value", "key")
    return placed.groupBy("side", "sub_id").applyInPandas(work, "side string, sub_id bigint, " + schema)


def _batches(v: np.ndarray, k: np.ndarray, n_bat: int):
    for at in range(0, len(v), n_bat):
        yield v[at : at + n_bat], k[at : at + n_bat]


def _inserted(make, n_bat: int, v, k):
    t = make()
    for a, b in _batches(v, k, n_bat):
        t.insert_batch(a, b)
    return t


SUBS = "SELECT CAST(count(*) AS BIGINT) AS n, CAST({n} AS BIGINT) AS n_sub FROM x GROUP BY side, (rank - 1) // {n}"


def _moved(v, k) -> list:
    out = []
    for n_bat, buffer in ((1, 64), (1, 1024), (32, 64), (32, 1024), (1024, 64)):
        t = _inserted(lambda b=buffer, n=n_bat: StagedSortedRun(b, 16, threads=threads_for(n)), n_bat, v, k)
        out.append((n_bat, buffer, int(t.moved), int(t.merges)))
    return out


def moved_sql(n_bat: int, buffer: int, n_sub: int) -> str:
    """Tuples moved by merges: every ``size`` tuples one, of all that are there by then."""
    if n_bat > buffer:  # each batch on its own; a last one not above the buffer waits in it
        return f"SELECT CAST(sum(CAST({n_bat} AS BIGINT) * (n // {n_bat}) * (n // {n_bat} + 1) // 2 + CASE WHEN n % {n_bat} > {buffer} OR n % {n_bat} = {buffer} THEN n ELSE 0 END) AS BIGINT) AS moved, CAST(sum(n // {n_bat} + CASE WHEN n % {n_bat} >= {buffer} THEN 1 ELSE 0 END) AS BIGINT) AS merges FROM u{n_sub}"
    return f"SELECT CAST(sum(CAST({buffer} AS BIGINT) * (n // {buffer}) * (n // {buffer} + 1) // 2) AS BIGINT) AS moved, CAST(sum(n // {buffer}) AS BIGINT) AS merges FROM u{n_sub}"


for n_sub in (500, 2000, 8000):
    query(f"insertion_moves_{n_sub}", f"{events_sql()}, u{n_sub} AS ({SUBS.format(n=n_sub)}) " + " UNION ALL ".join(f"SELECT CAST({n} AS BIGINT) AS n_bat, CAST({b} AS BIGINT) AS buffer, moved, merges FROM ({moved_sql(n, b, n_sub)})" for n, b in ((1, 64), (1, 1024), (32, 64), (32, 1024), (1024, 64))))(
        lambda spark, d, n=n_sub: _kernel(spark, clicks_views(spark, d), n, _moved, "n_bat bigint, buffer bigint, moved bigint, merges bigint").groupBy("n_bat", "buffer").agg(F.sum("moved").alias("moved"), F.sum("merges").alias("merges"))
    )


def _lines(spark, d):
    """Line prices by ship date, all on one side."""
    rows = table(spark, d, "lineitem").select(F.lit("S").alias("side"), sequence.cents("l_extendedprice").alias("value"), F.col("l_shipdate").alias("ts"), F.col("l_orderkey").alias("o"), F.col("l_linenumber").alias("l"), F.col("l_partkey").alias("p"), F.col("l_suppkey").alias("u"))
    return sequence.sequence(rows, ["ts", "o", "l", "p", "u"], F.date_trunc("month", "ts")).withColumn("key", F.col("seq"))


def _leaf_steps(v, k):
    out = []
    for width in (64, 256):
        steps = []
        for in_order in (False, True):
            t = WideLeafTree(width, 64, in_order)
            for a, b in zip(v.tolist(), k.tolist(), strict=True):
                t.insert(a, b)
            steps.append(t.moves + t.sort_steps)
        out.append((width, *steps))
    return out


query("tree_against_sorted_leaves", "SELECT * FROM (VALUES (64::BIGINT, true), (256, true)) t(leaf_width, unsorted_is_less)")(
    lambda spark, d: _kernel(spark, _lines(spark, d).filter("rank <= 6000"), 1500, _leaf_steps, "leaf_width bigint, unsorted_steps bigint, sorted_steps bigint").groupBy("leaf_width").agg((F.sum("unsorted_steps") < F.sum("sorted_steps")).alias("unsorted_is_less"))
)


def _search_steps(v, k):
    fences = np.sort(v)[:: max(1, len(v) // 64)]
    return [(b, *(sum(search.search_cost(fences, np.sort(x))[m] for x, _ in _batches(v, k, b)) for m in ("gallop", "binary"))) for b in (1, 32, 256)]


query("search_cost_by_batch", "SELECT * FROM (VALUES (1::BIGINT, false), (32, true), (256, true)) t(n_bat, gallop_is_less)")(
    lambda spark, d: _kernel(spark, clicks_views(spark, d), 500, _search_steps, "n_bat bigint, gallop bigint, binary bigint").groupBy("n_bat").agg((F.sum("gallop") < F.sum("binary")).alias("gallop_is_less"))
)
query("buffer_sweep", f"{events_sql()}, u AS ({SUBS.format(n=500)}) " + " UNION ALL ".join(f"SELECT CAST({b} AS BIGINT) AS buffer, CAST(sum(CAST({max(1, b)} AS BIGINT) * (n // {max(1, b)}) * (n // {max(1, b)} + 1) // 2) AS BIGINT) AS moved, CAST(sum(n // {max(1, b)}) AS BIGINT) AS merges FROM u" for b in (0, 16, 64, 256)))(
    lambda spark, d: _kernel(spark, clicks_views(spark, d), 500, lambda v, k: [(b, *(lambda t: (int(t.moved), int(t.merges)))(_inserted(lambda: StagedSortedRun(b, 16), 1, v, k))) for b in (0, 16, 64, 256)], "buffer bigint, moved bigint, merges bigint").groupBy("buffer").agg(F.sum("moved").alias("moved"), F.sum("merges").alias("merges"))
)
query("buffer_probe_cost", f"{events_sql()}, u AS ({SUBS.format(n=500)}) " + " UNION ALL ".join(f"SELECT CAST({b} AS BIGINT) AS buffer, CAST(sum(n % {b} * 32) AS BIGINT) AS comparisons FROM u" for b in (64, 256)))(
    lambda spark, d: _kernel(spark, clicks_views(spark, d), 500, lambda v, k: [(b, _buffer_comparisons(b, v, k)) for b in (64, 256)], "buffer bigint, comparisons bigint").groupBy("buffer").agg(F.sum("comparisons").alias("comparisons"))
)


def _buffer_comparisons(buffer: int, v, k) -> int:
    t = _inserted(lambda: StagedSortedRun(buffer, 16), 1, v, k)
    t.probe_batch(np.arange(32) * 100, np.arange(32) * 100 + 50)
    return int(t.buffer_comparisons)


def _switches(v, k):
    """Steps of 100 equal and unequal probes with fences and copies, and without either."""
    lo = np.sort(v)[:100] // 10 * 10
    out = []
    for fences, copy in ((True, True), (False, True), (True, False)):
        t = _inserted(lambda f=fences, c=copy: StagedSortedRun(64, 16, fences=f, copy_equal=c), 64, v, k)
        t.flush()
        r = t.probe_ranges(lo, lo + 50)
        out.append((fences, copy, int((r[:, 1] - r[:, 0]).sum()), int(t.copied_results)))
    return out


query("fences_and_copies", f"""{events_sql()}, m AS (SELECT *, (rank - 1) // 500 AS sub, row_number() OVER (PARTITION BY side, (rank - 1) // 500 ORDER BY value) AS place FROM x),
p AS (SELECT side, sub, value // 10 * 10 AS lo FROM m WHERE place <= 100), n AS (SELECT count(*) AS matches FROM p JOIN m ON p.side = m.side AND p.sub = m.sub AND m.value BETWEEN lo AND lo + 50), d AS (SELECT (SELECT count(*) FROM p) - (SELECT count(*) FROM (SELECT DISTINCT * FROM p)) AS copied)
SELECT f.fences, f.copy_equal, CAST(matches AS BIGINT) AS matches, CAST(CASE WHEN f.copy_equal THEN copied ELSE 0 END AS BIGINT) AS copied FROM n, d, (VALUES (true, true), (false, true), (true, false)) f(fences, copy_equal)""")(
    lambda spark, d: _kernel(spark, clicks_views(spark, d), 500, _switches, "fences boolean, copy_equal boolean, matches bigint, copied bigint").groupBy("fences", "copy_equal").agg(F.sum("matches").alias("matches"), F.sum("copied").alias("copied"))
)


def _engine(v, k):
    t = StreamPipeline(16)
    for a, _ in _batches(v, k, 100):
        t.insert(a)
    probes = np.sort(v)[:50]
    ends = t.probe(probes, -50, 50)
    return [(int(p), int(a), int(b)) for p, (a, b) in zip(probes, ends, strict=True)]


query("stream_pipeline_probes", f"""{events_sql()}, m AS (SELECT *, (rank - 1) // 500 AS sub, row_number() OVER (PARTITION BY side, (rank - 1) // 500 ORDER BY value) AS place FROM x)
SELECT p.side, p.sub AS sub_id, p.value AS probe, count(*) FILTER (WHERE m.value < p.value - 50) AS id_start, count(*) FILTER (WHERE m.value <= p.value + 50) AS id_end FROM m p JOIN m ON p.side = m.side AND p.sub = m.sub WHERE p.place <= 50 GROUP BY p.side, p.sub, p.value, p.place""")(
    lambda spark, d: _kernel(spark, clicks_views(spark, d), 500, _engine, "probe bigint, id_start bigint, id_end bigint")
)


def _same_scan(v, k):
    """Do the structures' batch probes give the same keys as a scan?"""
    lo = np.sort(v)[::7]
    hi = lo + 60
    want = [sorted(k[(v >= a) & (v <= b)].tolist()) for a, b in zip(lo, hi, strict=True)]
    out = []
    for name, make in (("splitter", lambda: SplitterTable(np.quantile(v, np.arange(1, 16) / 16).astype(np.int64).tolist(), len(v))), ("wideleaf", lambda: WideLeafTree(32, 8)), ("sorted", lambda: StagedSortedRun(64, 16))):
        t = _inserted(make, 32, v, k)
        out.append((name, [sorted(x.tolist()) for x in t.probe_batch(lo, hi)] == want))
    return out


query("batch_probes_agree", f"{events_sql()} SELECT k.kind, true AS agree, count(*) AS subwindows FROM (SELECT DISTINCT side, (rank - 1) // 500 FROM x), (VALUES ('splitter'), ('wideleaf'), ('sorted')) k(kind) GROUP BY k.kind")(
    lambda spark, d: _kernel(spark, clicks_views(spark, d), 500, _same_scan, "kind string, agree boolean").groupBy("kind").agg(F.min("agree").alias("agree"), F.count("*").alias("subwindows"))
)
