"""Queries whose work must grow with the result or the window and not with the product of the tables."""

import duckdb
import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from windowjoin.config import CountWindow, Layout, TimeWindow
from windowjoin.operators import baselines
from windowjoin.operators.join import theta_pairs, window_join
from windowjoin.operators.sequence import prepare
from windowjoin.plans import worker
from windowjoin.predicates import Band, MultiBand, NotEqual
from windowjoin.queries import experiments, joins, measures
from windowjoin.queries.base import clicks_views
from windowjoin.sources import sinks
from windowjoin.streaming import replay


@pytest.fixture(scope="module")
def ev(spark, sf):
    return clicks_views(spark, sf).cache()


def plan(df):
    return df._jdf.queryExecution().optimizedPlan().toString()


def pairs(df):
    return sorted((r.s_key, r.r_key) for r in df.select("s_key", "r_key").collect())


@pytest.mark.parametrize("method", [baselines.nested_loop, baselines.split_replicate, baselines.chain_flow])
def test_baselines_ask_the_window_only(ev, method):
    for window, layout in ((CountWindow(7), Layout(5, 4)), (TimeWindow(7200), Layout(3600, 4))):
        df = method(ev, Band(-900, 900), window)
        assert "sub_id" in plan(df).split("Join Inner")[1].splitlines()[0]
        assert pairs(df) == pairs(window_join(ev, Band(-900, 900), window, layout, "sorted")) != []


def test_dated_band_meets_by_day(spark, sf):
    assert "also" in plan(joins.QUERIES["band_orders_lineitem_dated"](spark, sf)).split("Join Inner")[1].splitlines()[0]
    days = [("2024-01-01", 1, 10), ("2024-01-02", 2, 10), ("2024-01-03", 3, 11), (None, 4, 10)]
    t = spark.createDataFrame(days, "day string, key bigint, value bigint").withColumn("day", F.to_date("day"))
    where = "datediff(r_day, s_day) BETWEEN 0 AND 1"
    assert pairs(theta_pairs(t, t, Band(-1, 1), 4, where, ("array(s_day, date_add(s_day, 1))", "r_day"))) == pairs(theta_pairs(t, t, Band(-1, 1), 4, where)) == [(1, 1), (1, 2), (2, 2), (2, 3), (3, 3)]


def test_native_theta_has_an_equality(spark, sf):
    text = joins.QUERIES["spark_native_theta"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin [cell" in text and "NestedLoop" not in text and "Cartesian" not in text


@pytest.mark.parametrize(("n_s", "n_r", "most"), [(60, 24_000, 1.0), (3000, 700, None)])
def test_native_theta_gives_pairs_that_a_file_holds_in_few_bytes(spark, tmp_path, n_s, n_r, most):
    """where a probe has more matches than a page has rows, its pairs took several bytes each."""
    rng, near = np.random.default_rng(3), Band(-50, 37)
    low, high = (0, 38) if most else (-900, 900)
    sides = {x: (rng.permutation(6_000_000)[:n], rng.integers(low, high, n)) for x, n in (("s", n_s), ("r", n_r))}
    tables = {x: spark.createDataFrame([*zip(k.tolist(), v.tolist(), strict=True), (-1, None)], f"{x}_key bigint, {x}_value bigint") for x, (k, v) in sides.items()}
    baselines.spark_native(tables["s"], tables["r"], near).select("s_key", "r_key").write.parquet(f"{tmp_path}/pairs")
    got = duckdb.sql(f"SELECT s_key, r_key FROM '{tmp_path}/pairs/*.parquet' ORDER BY ALL").fetchnumpy()
    (s_key, s_value), (r_key, r_value) = sides["s"], sides["r"]
    order_s, order_r = np.argsort(s_key), np.argsort(r_key)
    away = r_value[order_r][None, :] - s_value[order_s][:, None]
    at_s, at_r = np.nonzero((away >= -50) & (away <= 37))
    assert len(at_s) > 50_000 and np.array_equal(got["s_key"], s_key[order_s][at_s]) and np.array_equal(got["r_key"], r_key[order_r][at_r])
    if most:
        assert sum(p.stat().st_size for p in (tmp_path / "pairs").glob("*.parquet")) < most * len(at_s)


@pytest.mark.parametrize("name", ["range_records", "result_size_forms", "range_records_expanded"])
def test_probes_without_a_window_go_to_spans(spark, sf, name):
    """Not a row for every probe and subwindow through the exchange."""
    text = measures.QUERIES[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "MapInArrow" in text and "hashpartitioning(side" not in text and "hashpartitioning(sub_id" not in text


@pytest.mark.parametrize("pred", [Band(-300, 300), MultiBand(((-9, 5), (200, 300))), NotEqual()])
@pytest.mark.parametrize("window", [None, CountWindow(30)])
def test_lists_are_the_pairs_and_found_records_those_that_hold_something(ev, pred, window):
    prepared, layout = prepare(ev, 16), Layout(16, 4)
    lists = worker.run(prepared, pred, window, layout, "sorted", "lists").select("probe_side", "probe_key", F.explode("keys").alias("key"))
    from_s = F.col("probe_side") == "S"
    as_pairs = lists.select(F.when(from_s, F.col("probe_key")).otherwise(F.col("key")).alias("s_key"), F.when(from_s, F.col("key")).otherwise(F.col("probe_key")).alias("r_key"))
    assert pairs(as_pairs) == pairs(worker.run(prepared, pred, window, layout, "sorted")) != []
    every = worker.run(prepared, pred, window, layout, "sorted", "ranges")
    some = worker.run(prepared, pred, window, layout, "sorted", "ranges", found=True)
    assert sorted(some.collect()) == sorted((every if pred.negated else every.filter("id_end > id_start")).collect())


def test_mirror_expanded_where_keys_do_not_follow_time(spark, sf, tmp_path):
    """Copies of the events under shifted keys: who came later is not told by the keys."""
    con = duckdb.connect()
    con.execute(f"COPY (SELECT e.* REPLACE (event_id + 100000 * i.range AS event_id) FROM '{sf}/events.parquet' e, range(2) i) TO '{tmp_path}/events.parquet' (FORMAT parquet)")
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{tmp_path}/events.parquet'")
    want = sorted(con.execute(f"SELECT s_key, r_key FROM ({experiments.SQL['mirror_expanded']})").fetchall())
    assert pairs(experiments.QUERIES["mirror_expanded"](spark, str(tmp_path))) == want


def test_a_batch_stores_what_later_batches_can_want(ev, monkeypatch):
    """And no folder for each subwindow that it brings."""
    laid_down, write = [], sinks.subwindow_store
    monkeypatch.setattr(sinks, "subwindow_store", lambda rows, path: (laid_down.append(rows.select("side", "sub_id").distinct().count()), write(rows, path)))
    window, layout = CountWindow(20), Layout(5)
    got, store = replay.microbatch_join(ev, Band(-900, 900), window, layout)
    assert len(laid_down) > 1 and max(laid_down) <= 2 * layout.live(window)
    assert pairs(got) == pairs(window_join(ev, Band(-900, 900), window, layout, "sorted")) != []
    tops = {r.side: r.top for r in ev.groupBy("side").agg(F.max("rank").alias("top")).collect()}
    left = {(r.side, r.sub_id) for r in replay.stored_subwindows(ev.sparkSession, store).collect()}
    assert left == {(side, x) for side, top in tops.items() for x in range((top - 20) // 5, (top - 1) // 5 + 1)}


def test_native_stream_join_meets_by_time_and_value(ev, monkeypatch):
    """a probe of the stream-stream join reads its own time slots, not all that is in state."""
    monkeypatch.setattr(replay, "_ended", lambda stream, spark: stream)
    stream = replay.native_band(ev, 50, 86_400)._jdf.queryExecution().analyzed().toString()
    met = stream.split("Join Inner")[1].splitlines()[0]
    assert "S_slot" in met and "S_cell" in met


@pytest.mark.parametrize(("eps", "seconds", "width", "packed", "matched"), [(50, 7, 16, 1 << 17, 1 << 18), (3, 1, 256, 40, 5), (0, 0, 1, 1 << 17, 7), (5, 100, 3, 64, 100)])
def test_blocks_of_the_native_stream_join_bring_every_pair_once(monkeypatch, eps, seconds, width, packed, matched):
    monkeypatch.setattr(replay, "PACKED", packed)
    monkeypatch.setattr(replay, "MATCHED", matched)
    rng = np.random.default_rng(5)
    us, fields = seconds * 1_000_000, ("key", "value", "us")
    sides = {side: [(None if k == 7 else k, int(rng.integers(-60, 60)), int(rng.integers(-30, 30)) * 500_000) for k in range(150)] for side in "SR"}

    def blocks(side, reach, near):
        batches = pa.Table.from_pydict({c: [t[i] for t in sides[side]] for i, c in enumerate(fields)}, pa.schema([(c, pa.int64()) for c in fields])).to_batches(20)
        return [r for b in replay._packed(iter(batches), max(1, us // 2), width, reach, near) for r in b.to_pylist()]

    slot = max(1, us // 2)
    both = [(s, r) for s in blocks("S", us, eps) for r in blocks("R", 0, 0) if (s["slot"], s["cell"]) == (r["slot"], r["cell"])]
    assert all(abs(s["last"] - r["last"]) <= us + slot for s, r in both)
    batch = pa.RecordBatch.from_arrays([pa.array([s["data"] for s, _ in both], pa.binary()), pa.array([r["data"] for _, r in both], pa.binary())], names=["S_data", "R_data"])
    got = [tuple(row.values()) for b in replay._matches(iter([batch]), eps, us) for row in b.to_pylist()]
    want = [(s[0], r[0], s[1], r[1]) for s in sides["S"] for r in sides["R"] if abs(s[1] - r[1]) <= eps and abs(s[2] - r[2]) <= us]
    assert sorted(got, key=str) == sorted(want, key=str) != []
