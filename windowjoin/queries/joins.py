"""Registered window joins: structures, baselines, predicates, windows, batch mode, streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from windowjoin.config import BatchPolicy, CountWindow, Layout, TimeWindow
from windowjoin.operators import baselines, sequence
from windowjoin.operators.join import outer_join, theta_pairs, top_matches, window_join
from windowjoin.predicates import Band, Equi, Inequality, MultiBand, NotEqual, Theta
from windowjoin.queries.base import CENTS, EVENTS, PAIR, band, batch_sql, clicks_views, count_window_sql, events_sql, table, wait_sql
from windowjoin.streaming import replay

QUERIES: dict = {}
SQL: dict[str, str] = {}
W, NEAR, LAYOUT = CountWindow(500), Band(-50, 50), Layout(50, 16)
DAY = 86_400


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return add


def _plain(f):
    """A query over the clicks and views in cents."""
    return lambda spark, sf_dir: f(clicks_views(spark, sf_dir))


EXACT = count_window_sql(band(50))
for kind in ("splitter", "wideleaf", "sorted", "auto"):
    query(f"band_count_window_{kind}", EXACT)(_plain(lambda ev, kind=kind: window_join(ev, NEAR, W, LAYOUT, kind)))
query("band_count_window_mixed", EXACT)(_plain(lambda ev: window_join(ev, NEAR, W, LAYOUT, lambda sub: ("splitter", "wideleaf", "sorted")[sub % 3])))
query("band_count_window_shares", EXACT)(_plain(lambda ev: window_join(ev, NEAR, W, Layout(64, 16, shares=3), "sorted")))
for p in (256, 4096):  # more partitions than tuples, too
    query(f"band_count_window_splitter_{p}", EXACT)(_plain(lambda ev, p=p: window_join(ev, NEAR, W, Layout(64, p), "splitter")))
for kind in ("wideleaf", "sorted"):
    query(f"band_count_window_relational_{kind}", EXACT)(_plain(lambda ev, kind=kind: window_join(ev, NEAR, W, LAYOUT, kind, engine="relational")))
WIDE = count_window_sql(band(50), 2000)
for kind in ("splitter", "wideleaf", "sorted"):
    query(f"band_count_window_2000_{kind}", WIDE)(_plain(lambda ev, kind=kind: window_join(ev, NEAR, CountWindow(2000), Layout(256, 64), kind)))
query("band_count_window_2000_nested", WIDE)(_plain(lambda ev: baselines.nested_loop(ev, NEAR, CountWindow(2000))))
query("band_count_window_2000_split_replicate", WIDE)(_plain(lambda ev: baselines.split_replicate(ev, NEAR, CountWindow(2000))))
query("band_count_window_nested", EXACT)(_plain(lambda ev: baselines.nested_loop(ev, NEAR, W)))
query("band_count_window_split_replicate", EXACT)(_plain(lambda ev: baselines.split_replicate(ev, NEAR, W)))
query("band_count_window_chained_tree", EXACT)(_plain(lambda ev: baselines.chained_tree(ev, NEAR, W)))
query("band_count_window_static", EXACT)(_plain(lambda ev: baselines.static_partitions(ev, NEAR, W, LAYOUT, 0, 1 << 16)))
query("band_count_window_chain_flow", count_window_sql(band(50), select=PAIR + ", CAST(CASE WHEN s.seq > r.seq THEN r.rank % 16 ELSE 15 - s.rank % 16 END AS INTEGER) AS hops"))(_plain(lambda ev: baselines.chain_flow(ev, NEAR, W)))
for n in (32, 256, 1000):
    query(f"band_batch_window_{n}", batch_sql(band(50), 500, n))(_plain(lambda ev, n=n: window_join(ev, NEAR, W, LAYOUT, "wideleaf", n_bat=n)))
query("band_batch_window_sorted_32", batch_sql(band(50), 500, 32))(_plain(lambda ev: window_join(ev, NEAR, W, LAYOUT, "sorted", n_bat=32)))
query("coarse_expiry_window", f"""{events_sql()}
SELECT {PAIR} FROM s JOIN r ON {band(50)}
 AND ((s.seq > r.seq AND (r.rank - 1) // 200 >= greatest(0, s.seen_r - 500) // 200) OR (r.seq > s.seq AND (s.rank - 1) // 200 >= greatest(0, r.seen_s - 500) // 200))""")(
    _plain(lambda ev: window_join(ev, NEAR, CountWindow(500, exact=False), Layout(200, 16), "wideleaf"))
)
for kind in ("splitter", "sorted"):
    query(f"band_time_window_{kind}", f"{events_sql()} SELECT {PAIR} FROM s JOIN r ON {band(50)} AND abs(s.us - r.us) <= {DAY}000000")(_plain(lambda ev, kind=kind: window_join(ev, NEAR, TimeWindow(DAY), Layout(DAY // 8, 16), kind)))
TIMED = f"""{events_sql()},
p AS (SELECT s.key AS k, 'S' AS side FROM s JOIN r ON {band(50)} AND s.seq > r.seq AND s.us - r.us <= {DAY}000000
UNION ALL SELECT r.key, 'R' FROM s JOIN r ON {band(50)} AND r.seq > s.seq AND r.us - s.us <= {DAY}000000)
SELECT side AS probe_side, k AS probe_key, count(*) AS matches FROM p GROUP BY ALL"""
query("time_window_counts", TIMED)(_plain(lambda ev: window_join(ev, NEAR, TimeWindow(DAY), Layout(DAY // 8, 16), result="count")))
query("time_window_counts_relational", TIMED)(_plain(lambda ev: window_join(ev, NEAR, TimeWindow(DAY), Layout(DAY // 8, 16), result="count", engine="relational")))
#: times before 1970 and two arrivals a second: slot numbers are negative and small against arrival numbers
query("time_window_counts_1969", TIMED)(_plain(lambda ev: window_join(ev.withColumn("ts", F.col("ts") - F.expr("INTERVAL 55 YEARS")), NEAR, TimeWindow(DAY), Layout(DAY // 8, 16), result="count")))
RANGED = f"""{{events}}, m AS (SELECT *, {{sub}} AS sub_id, row_number() OVER (PARTITION BY side, {{sub}} ORDER BY value, key) - 1 AS pos FROM x),
a AS (SELECT p.side AS probe_side, p.key AS probe_key, m.sub_id, count(*) FILTER (WHERE m.value < p.value - 50) AS id_start, count(*) FILTER (WHERE m.value <= p.value + 50) AS id_end
 FROM x p JOIN m ON m.side <> p.side AND {{live}} GROUP BY ALL)
SELECT probe_side, probe_key, sub_id, id_start, id_end FROM a WHERE id_end > id_start"""


def _records(ev: DataFrame, window, layout: Layout) -> DataFrame:
    return window_join(ev, NEAR, window, layout, result="ranges").filter("id_end > id_start").select("probe_side", "probe_key", "sub_id", "id_start", "id_end")


query("count_window_ranges", RANGED.format(events=events_sql(), sub="(rank - 1) // 50", live="m.sub_id BETWEEN greatest(0, (CASE p.side WHEN 'S' THEN p.seen_r ELSE p.seen_s END) - 500) // 50 AND ((CASE p.side WHEN 'S' THEN p.seen_r ELSE p.seen_s END) + 49) // 50 - 1"))(_plain(lambda ev: _records(ev, W, LAYOUT)))
query("time_window_ranges", RANGED.format(events=events_sql(), sub=f"us // {DAY // 4}000000", live=f"m.sub_id BETWEEN (p.us - {DAY}000000) // {DAY // 4}000000 AND p.us // {DAY // 4}000000"))(_plain(lambda ev: _records(ev, TimeWindow(DAY), Layout(DAY // 4, 16))))
query("batch_or_wait_window", wait_sql(band(50), 500, 32, 21_600))(_plain(lambda ev: window_join(ev, NEAR, W, LAYOUT, "sorted", n_bat=BatchPolicy(32, 21_600))))
query("band_time_window", f"{events_sql()} SELECT {PAIR} FROM s JOIN r ON {band(50)} AND abs(s.us - r.us) <= {DAY}000000")(_plain(lambda ev: window_join(ev, NEAR, TimeWindow(DAY), Layout(DAY // 8, 16), "wideleaf")))
for sign, name in (("<", "lt"), ("<=", "le"), (">", "gt"), (">=", "ge")):
    query(f"inequality_window_{name}", f"""{events_sql()},
p AS (SELECT s.key AS k, 'S' AS side FROM s JOIN r ON s.value {sign} r.value AND s.seq > r.seq AND s.seen_r - r.rank < 500
UNION ALL SELECT r.key, 'R' FROM s JOIN r ON s.value {sign} r.value AND r.seq > s.seq AND r.seen_s - s.rank < 500)
SELECT side AS probe_side, k AS probe_key, count(*) AS matches FROM p GROUP BY ALL""")(_plain(lambda ev, sign=sign: window_join(ev, Inequality(sign), W, LAYOUT, result="count")))
query("not_equal_window", f"""{events_sql()},
p AS (SELECT s.key AS k, 'S' AS side FROM s JOIN r ON s.value <> r.value AND s.seq > r.seq AND s.seen_r - r.rank < 500
UNION ALL SELECT r.key, 'R' FROM s JOIN r ON s.value <> r.value AND r.seq > s.seq AND r.seen_s - s.rank < 500)
SELECT side AS probe_side, k AS probe_key, count(*) AS matches FROM p GROUP BY ALL""")(_plain(lambda ev: window_join(ev, NotEqual(), W, LAYOUT, result="count")))
query("range_counts_per_probe", f"""{events_sql()},
p AS (SELECT s.key AS k, 'S' AS side FROM s JOIN r ON {band(50)} AND s.seq > r.seq AND s.seen_r - r.rank < 500
UNION ALL SELECT r.key, 'R' FROM s JOIN r ON {band(50)} AND r.seq > s.seq AND r.seen_s - s.rank < 500)
SELECT side AS probe_side, k AS probe_key, count(*) AS matches FROM p GROUP BY ALL""")(_plain(lambda ev: window_join(ev, NEAR, W, LAYOUT, result="count")))
TWO = "(r.value BETWEEN s.value - 5 AND s.value + 5 OR r.value BETWEEN s.value + 20 AND s.value + 35)"
query("multi_band_window", count_window_sql(TWO))(_plain(lambda ev: window_join(ev, MultiBand(((-5, 5), (20, 35))), W, LAYOUT, "wideleaf")))
query("multi_band_window_sorted", count_window_sql(TWO))(_plain(lambda ev: window_join(ev, MultiBand(((-5, 5), (20, 35))), W, LAYOUT, "sorted")))
query("not_equal_pairs_small", count_window_sql("s.value <> r.value", 20))(_plain(lambda ev: window_join(ev, NotEqual(), CountWindow(20), Layout(4, 4), "sorted")))


@query("theta_extra_field_window", count_window_sql(band(200) + " AND s.user_id % 2 = r.user_id % 2"))
def _theta(spark: SparkSession, sf_dir: str) -> DataFrame:
    ev = clicks_views(spark, sf_dir, extra=("user_id",))
    return window_join(ev, Theta("s_user_id % 2 = r_user_id % 2", Band(-200, 200)), W, LAYOUT, "wideleaf", extra=("user_id",)).drop("s_user_id", "r_user_id")


@query("equi_time_window", f"{events_sql('user_id')} SELECT {PAIR} FROM s JOIN r ON s.value = r.value AND abs(s.us - r.us) <= 21600000000")
def _equi_time(spark, sf_dir):
    return window_join(clicks_views(spark, sf_dir, "user_id"), Equi(), TimeWindow(21_600), Layout(2_700, 16), "wideleaf")


query("equi_hash_window", count_window_sql("s.value = r.value", value="user_id"))(lambda spark, d: baselines.symmetric_hash(clicks_views(spark, d, "user_id"), W))
query("equi_count_window_splitter", count_window_sql("s.value = r.value", value="user_id"))(lambda spark, d: window_join(clicks_views(spark, d, "user_id"), Equi(), W, LAYOUT, "splitter"))
query("equi_count_window_sorted", count_window_sql("s.value = r.value", value="user_id"))(lambda spark, d: window_join(clicks_views(spark, d, "user_id"), Equi(), W, LAYOUT, "sorted"))

# -- whole-table joins of other carriers ------------------------------------------------------

JOINED = "s_key, r_key, s_value, r_value"


def _orders(spark, d):
    return table(spark, d, "orders").select(F.col("o_orderkey").alias("key"), sequence.cents("o_totalprice").alias("value"), F.col("o_orderdate").alias("day"))


def _lines(spark, d, value="l_extendedprice"):
    return table(spark, d, "lineitem").select(F.col("l_orderkey").alias("key"), sequence.cents(value).alias("value"), F.col("l_shipdate").alias("day"), F.col("l_linenumber").alias("line"))


@query("band_orders_lineitem", "SELECT o_orderkey AS s_key, l_orderkey AS r_key, CAST(round(o_totalprice * 100) AS BIGINT) AS s_value, CAST(round(l_extendedprice * 100) AS BIGINT) AS r_value FROM orders JOIN lineitem ON CAST(round(l_extendedprice * 100) AS BIGINT) BETWEEN CAST(round(o_totalprice * 100) AS BIGINT) - 100 AND CAST(round(o_totalprice * 100) AS BIGINT) + 100")
def _band_orders(spark, d):
    return theta_pairs(_orders(spark, d), _lines(spark, d), Band(-100, 100), 1024).select(*JOINED.split(", "))


@query("band_orders_lineitem_dated", "SELECT o_orderkey AS s_key, l_orderkey AS r_key, CAST(round(o_totalprice * 100) AS BIGINT) AS s_value, CAST(round(l_extendedprice * 100) AS BIGINT) AS r_value FROM orders JOIN lineitem ON CAST(round(l_extendedprice * 100) AS BIGINT) BETWEEN CAST(round(o_totalprice * 100) AS BIGINT) - 5000 AND CAST(round(o_totalprice * 100) AS BIGINT) + 5000 AND date_diff('day', o_orderdate, l_shipdate) BETWEEN 0 AND 1")
def _band_orders_dated(spark, d):
    return theta_pairs(_orders(spark, d), _lines(spark, d), Band(-5000, 5000), 16384, "datediff(r_day, s_day) BETWEEN 0 AND 1", ("array(cast(s_day AS date), date_add(s_day, 1))", "cast(r_day AS date)")).select(*JOINED.split(", "))


@query("equi_interval_orders_lineitem", "SELECT o_orderkey AS s_key, l_linenumber AS line, CAST(round(l_extendedprice * 100) AS BIGINT) AS r_value FROM orders JOIN lineitem ON o_orderkey = l_orderkey AND date_diff('day', o_orderdate, l_shipdate) BETWEEN 0 AND 30")
def _interval(spark, d):
    s = table(spark, d, "orders").select(F.col("o_orderkey").alias("s_key"), "o_orderdate")
    r = table(spark, d, "lineitem").select(F.col("l_orderkey").alias("s_key"), F.col("l_linenumber").alias("line"), sequence.cents("l_extendedprice").alias("r_value"), "l_shipdate")
    return s.join(r, "s_key").filter("datediff(l_shipdate, o_orderdate) BETWEEN 0 AND 30").select("s_key", "line", "r_value")


def _parity(df: DataFrame, key: str, value, odd: int) -> DataFrame:
    return df.filter(F.pmod(F.col(key), F.lit(2)) == odd).select(F.col(key).alias("key"), value.cast("bigint").alias("value"))


for name, eps in (("band_lengths_documents", 5), ("equi_lengths_documents", 0)):
    query(name, f"SELECT s.doc_id AS s_key, r.doc_id AS r_key, s.n_chars AS s_value, r.n_chars AS r_value FROM documents s JOIN documents r ON s.doc_id % 2 = 0 AND r.doc_id % 2 = 1 AND r.n_chars BETWEEN s.n_chars - {eps} AND s.n_chars + {eps}")(
        lambda spark, d, eps=eps: theta_pairs(_parity(table(spark, d, "documents"), "doc_id", F.col("n_chars"), 0), _parity(table(spark, d, "documents"), "doc_id", F.col("n_chars"), 1), Band(-eps, eps), 32).select(*JOINED.split(", "))
    )
query("length_band_pages", "SELECT s.page_id AS s_key, r.page_id AS r_key, CAST(length(s.html) AS BIGINT) AS s_value, CAST(length(r.html) AS BIGINT) AS r_value FROM pages s JOIN pages r ON s.page_id % 2 = 0 AND r.page_id % 2 = 1 AND length(r.html) BETWEEN length(s.html) - 20 AND length(s.html) + 20")(
    lambda spark, d: theta_pairs(_parity(table(spark, d, "pages"), "page_id", F.length("html"), 0), _parity(table(spark, d, "pages"), "page_id", F.length("html"), 1), Band(-20, 20), 64).select(*JOINED.split(", "))
)
query("benchmark_length_band", "SELECT b.item_id AS s_key, d.doc_id AS r_key, CAST(length(b.text) AS BIGINT) AS s_value, d.n_chars AS r_value FROM benchmark b JOIN documents d ON d.n_chars BETWEEN length(b.text) - 10 AND length(b.text) + 10")(
    lambda spark, d: theta_pairs(table(spark, d, "benchmark").select(F.col("item_id").alias("key"), F.length("text").cast("bigint").alias("value")), table(spark, d, "documents").select(F.col("doc_id").alias("key"), F.col("n_chars").alias("value")), Band(-10, 10), 32).select(*JOINED.split(", "))
)


@query("conversation_turn_join", "SELECT s.conv_id, s.turn AS s_turn, r.turn AS r_turn FROM conversations s JOIN conversations r ON s.conv_id = r.conv_id AND r.turn > s.turn AND r.turn - s.turn <= 2 AND abs(length(s.text) - length(r.text)) <= 100")
def _turns(spark, d):
    c = table(spark, d, "conversations").select("conv_id", "turn", F.length("text").alias("n"))
    s, r = c.select("conv_id", F.col("turn").alias("s_turn"), F.col("n").alias("s_n")), c.select("conv_id", F.col("turn").alias("r_turn"), F.col("n").alias("r_n"))
    return s.join(r, "conv_id").filter("r_turn > s_turn and r_turn - s_turn <= 2 and abs(s_n - r_n) <= 100").select("conv_id", "s_turn", "r_turn")


@query("embedding_label_pairs", "SELECT s.label, count(*) AS pairs FROM embeddings s JOIN embeddings r ON s.label = r.label AND s.vec_id % 2 = 0 AND r.vec_id % 2 = 1 GROUP BY s.label")
def _labels(spark, d):
    e = table(spark, d, "embeddings").groupBy("label").agg(F.sum((F.pmod("vec_id", F.lit(2)) == 0).cast("bigint")).alias("a"), F.sum((F.pmod("vec_id", F.lit(2)) == 1).cast("bigint")).alias("b"))
    return e.select("label", (F.col("a") * F.col("b")).alias("pairs")).filter("pairs > 0")  # duplicates as counts, not as pairs


@query("label_semi_anti", "SELECT (l.doc_id IS NOT NULL) AS labelled, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents d LEFT JOIN (SELECT DISTINCT doc_id FROM labels) l ON d.doc_id = l.doc_id GROUP BY 1")
def _semi(spark, d):
    docs, known = table(spark, d, "documents").select("doc_id", "n_chars"), table(spark, d, "labels").select("doc_id")
    both = docs.join(known, "doc_id", "left_semi").withColumn("labelled", F.lit(True)).unionByName(docs.join(known, "doc_id", "left_anti").withColumn("labelled", F.lit(False)))
    return both.groupBy("labelled").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


@query("band_acctbal_nation", "SELECT c_custkey AS s_key, s_suppkey AS r_key FROM customer JOIN supplier ON c_nationkey = s_nationkey AND CAST(round(s_acctbal * 100) AS BIGINT) BETWEEN CAST(round(c_acctbal * 100) AS BIGINT) - 50000 AND CAST(round(c_acctbal * 100) AS BIGINT) + 50000")
def _acctbal(spark, d):
    c = table(spark, d, "customer").select(F.col("c_custkey").alias("s_key"), F.col("c_nationkey").alias("n"), sequence.cents("c_acctbal").alias("s_value"))
    s = table(spark, d, "supplier").select(F.col("s_suppkey").alias("r_key"), F.col("s_nationkey").alias("n"), sequence.cents("s_acctbal").alias("r_value"))
    return c.join(s, "n").filter(Band(-50_000, 50_000).residual(F.col("s_value"), F.col("r_value"))).select("s_key", "r_key")


@query("json_key_join", f"""WITH {EVENTS.format(value="CAST(json_extract(props, '$.k') AS BIGINT)").strip()}
SELECT {PAIR} FROM s JOIN r ON s.value = r.value AND ((s.seq > r.seq AND s.seen_r - r.rank < 200) OR (r.seq > s.seq AND r.seen_s - s.rank < 200))""")
def _json(spark, d):
    e = table(spark, d, "events").filter(F.col("event_type").isin("click", "view"))
    rows = e.select(F.when(F.col("event_type") == "click", "S").otherwise("R").alias("side"), F.col("event_id").alias("key"), F.get_json_object("props", "$.k").cast("bigint").alias("value"), "ts")
    return window_join(sequence.sequence(rows, ["ts", "key"], F.date_trunc("hour", "ts")), Equi(), CountWindow(200), Layout(25, 8), "wideleaf")


@query("increasing_values_wideleaf", "WITH s AS (SELECT o_orderkey AS k FROM orders WHERE o_orderkey % 2 = 0), r AS (SELECT o_orderkey AS k FROM orders WHERE o_orderkey % 2 = 1) SELECT s.k AS s_key, r.k AS r_key FROM s JOIN r ON r.k BETWEEN s.k - 5 AND s.k + 5")
def _increasing(spark, d):
    o = table(spark, d, "orders").select(F.when(F.col("o_orderkey") % 2 == 0, "S").otherwise("R").alias("side"), F.col("o_orderkey").alias("key"), F.col("o_orderkey").alias("value"))
    ranked = sequence.sequence(o, ["key"], F.expr("key div 1024"))
    return window_join(ranked, Band(-5, 5), CountWindow(64), Layout(512, 16), "wideleaf").select("s_key", "r_key")


# -- outer forms, top-k, as-of ----------------------------------------------------------------

FOUND = f"{events_sql()}, p AS (SELECT s.key AS s_key, r.key AS r_key FROM s JOIN r ON {band(1)} AND ((s.seq > r.seq AND s.seen_r - r.rank < 500) OR (r.seq > s.seq AND r.seen_s - s.rank < 500)))"
TIGHT = Band(-1, 1)
OUTER = "s.key AS s_key, r.key AS r_key, s.value AS s_value, r.value AS r_value"
query("left_window_join", f"{FOUND} SELECT {OUTER} FROM s LEFT JOIN p ON s.key = p.s_key LEFT JOIN r ON p.r_key = r.key")(_plain(lambda ev: outer_join(ev, TIGHT, W, "left", LAYOUT)))
query("right_window_join", f"{FOUND} SELECT {OUTER} FROM r LEFT JOIN p ON r.key = p.r_key LEFT JOIN s ON p.s_key = s.key")(_plain(lambda ev: outer_join(ev, TIGHT, W, "right", LAYOUT)))
query("full_window_join", f"{FOUND} SELECT {OUTER} FROM s LEFT JOIN p ON s.key = p.s_key LEFT JOIN r ON p.r_key = r.key UNION ALL SELECT NULL, r.key, NULL, r.value FROM r WHERE r.key NOT IN (SELECT r_key FROM p)")(_plain(lambda ev: outer_join(ev, TIGHT, W, "full", LAYOUT)))
query("semi_window_join", f"{FOUND} SELECT key AS s_key, value AS s_value FROM s WHERE key IN (SELECT s_key FROM p)")(_plain(lambda ev: outer_join(ev, TIGHT, W, "semi", LAYOUT)))
query("anti_window_join", f"{FOUND} SELECT key AS s_key, value AS s_value FROM s WHERE key NOT IN (SELECT s_key FROM p)")(_plain(lambda ev: outer_join(ev, TIGHT, W, "anti", LAYOUT)))
query("topk_matches_per_probe", f"SELECT s_key, r_key, place FROM (SELECT *, CAST(row_number() OVER (PARTITION BY s_key ORDER BY abs(r_value - s_value), r_key) AS INTEGER) AS place FROM ({EXACT})) WHERE place <= 3")(
    _plain(lambda ev: top_matches(window_join(ev, NEAR, W, LAYOUT, "wideleaf"), 3).select("s_key", "r_key", "place"))
)
query("asof_match", f"{events_sql()} SELECT s.key AS s_key, r.key AS r_key, s.value AS s_value, r.value AS r_value FROM s LEFT JOIN r ON r.rank = s.seen_r")(_plain(baselines.asof_join))
query("spark_native_theta", f"SELECT s_key, r_key FROM ({EXACT.replace('500', '1000000000')})")(
    _plain(lambda ev: baselines.spark_native(ev.filter("side = 'S'").select(F.col("key").alias("s_key"), F.col("value").alias("s_value")), ev.filter("side = 'R'").select(F.col("key").alias("r_key"), F.col("value").alias("r_value")), NEAR).select("s_key", "r_key"))
)

# -- streams ------------------------------------------------------------------------------------

query("stream_native_band", SQL["band_time_window"])(_plain(lambda ev: replay.native_band(ev, 50, DAY)))
query("stream_stateful_band", EXACT)(_plain(lambda ev: replay.stateful_join(ev, NEAR, W, Layout(250))[0]))
query("stream_stateful_time_band", SQL["band_time_window"])(_plain(lambda ev: replay.stateful_join(ev, NEAR, TimeWindow(DAY), Layout(DAY))[0]))
query("stream_microbatch_band", EXACT)(_plain(lambda ev: replay.microbatch_join(ev, NEAR, W, LAYOUT)[0]))
query("stream_overlapped_band", EXACT)(_plain(lambda ev: replay.microbatch_join(ev, NEAR, W, LAYOUT, overlap=True)[0]))
LIVE = f"{events_sql()}, n AS (SELECT side, max(rank) AS top FROM x GROUP BY side) SELECT x.side, (x.rank - 1) // {{n}} AS sub_id FROM x JOIN n ON x.side = n.side WHERE (x.rank - 1) // {{n}} >= greatest(0, n.top - 500) // {{n}} GROUP BY ALL"
query("stream_live_subwindows", LIVE.format(n=250))(_plain(lambda ev: replay.live_subwindows(ev.sparkSession, replay.stateful_join(ev, NEAR, W, Layout(250))[1])))
query("stream_live_folders", LIVE.format(n=50))(_plain(lambda ev: replay.stored_subwindows(ev.sparkSession, replay.microbatch_join(ev, NEAR, W, LAYOUT)[1])))
query("stream_hash_equi", SQL["equi_time_window"])(lambda spark, d: replay.native_equi(clicks_views(spark, d, "user_id"), 21_600))
query("stream_noop_counts", f"{events_sql()} SELECT side, count(*) AS n FROM x GROUP BY side")(_plain(replay.counted))

LATE = f"""WITH e AS (SELECT event_id AS key, event_id + (event_id * 37) % 40 AS arrival, CASE event_type WHEN 'click' THEN 'S' ELSE 'R' END AS side, {CENTS} AS value, epoch_us(ts) AS us
 FROM events WHERE event_type IN ('click', 'view')),
m AS (SELECT *, max(us) OVER (ORDER BY arrival, key ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS top FROM e),
a AS (SELECT * FROM m WHERE top IS NULL OR us >= top - 43200000000)
"""


@query("band_out_of_order", LATE + f"SELECT {PAIR} FROM a s JOIN a r ON s.side = 'S' AND r.side = 'R' AND {band(50)} AND abs(s.us - r.us) <= {DAY}000000")
def _late(spark, d):
    """Admitted tuples in order of arrival; those that come after the next subwindow has begun go to
    their subwindow's side buffer."""
    e = table(spark, d, "events").filter(F.col("event_type").isin("click", "view"))
    rows = e.select(F.when(F.col("event_type") == "click", "S").otherwise("R").alias("side"), F.col("event_id").alias("key"), sequence.cents("value").alias("value"), "ts", F.expr("event_id + (event_id * 37) % 40").alias("arrival"))
    length = DAY // 4
    taken = replay.admitted(rows, "arrival", 43_200).filter("not dropped")
    taken = taken.withColumn("late", F.coalesce(sequence.time_slot("us", length) < sequence.time_slot("top", length), F.lit(False)))
    ranked = sequence.sequence(taken.select("side", "key", "value", "ts", "arrival", "late"), ["arrival", "key"], F.expr("arrival div 256"))
    return window_join(ranked, NEAR, TimeWindow(DAY, disorder=43_200), Layout(length, 16), "sorted")


@query("out_of_order_counts", LATE + f""", p AS (SELECT s.side, s.key, s.value, s.us, s.arrival FROM a s)
SELECT p.side AS probe_side, p.key AS probe_key, count(*) AS matches FROM p JOIN a r ON p.side <> r.side AND abs(p.value - r.value) <= 50 AND abs(p.us - r.us) <= {DAY}000000 AND (p.arrival, p.key) > (r.arrival, r.key) GROUP BY ALL""")
def _late_pairs(spark, d):
    e = table(spark, d, "events").filter(F.col("event_type").isin("click", "view"))
    rows = e.select(F.when(F.col("event_type") == "click", "S").otherwise("R").alias("side"), F.col("event_id").alias("key"), sequence.cents("value").alias("value"), "ts", F.expr("event_id + (event_id * 37) % 40").alias("arrival"))
    taken = replay.admitted(rows, "arrival", 43_200).filter("not dropped")
    ranked = sequence.sequence(taken.select("side", "key", "value", "ts", "arrival"), ["arrival", "key"], F.expr("arrival div 256"))
    return window_join(ranked, NEAR, TimeWindow(DAY, disorder=43_200), Layout(DAY // 4, 16), result="count")


@query("late_tuples", LATE + "SELECT CAST(sum(CASE WHEN us < top - 43200000000 THEN 1 ELSE 0 END) AS BIGINT) AS dropped, CAST(sum(CASE WHEN us < top AND us >= top - 43200000000 THEN 1 ELSE 0 END) AS BIGINT) AS late FROM m")
def _late_counts(spark, d):
    e = table(spark, d, "events").filter(F.col("event_type").isin("click", "view"))
    rows = e.select(F.col("event_id").alias("key"), "ts", F.expr("event_id + (event_id * 37) % 40").alias("arrival"))
    return replay.admitted(rows, "arrival", 43_200).agg(F.sum(F.col("dropped").cast("bigint")).alias("dropped"), F.sum(F.col("late").cast("bigint")).alias("late"))


@query("multi_way_equi", """SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN orders ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey AND date_diff('day', o_orderdate, l_shipdate) BETWEEN 0 AND 365 GROUP BY n_name""")
def _multi(spark, d):
    o = table(spark, d, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    li = table(spark, d, "lineitem").select("l_orderkey", "l_shipdate")
    c = table(spark, d, "customer").select("c_custkey", "c_nationkey")
    n = table(spark, d, "nation").select("n_nationkey", "n_name")
    both = o.join(li, o.o_orderkey == li.l_orderkey).filter("datediff(l_shipdate, o_orderdate) BETWEEN 0 AND 365")
    return both.join(c, both.o_custkey == c.c_custkey).join(n, F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"))


@query("sql_bucket_join", EXACT)
def _sql(spark, d):
    from windowjoin.functions.register import bucket_join_sql

    clicks_views(spark, d).createOrReplaceTempView("wj_tuples")
    return spark.sql(bucket_join_sql(50, 128, 500))

