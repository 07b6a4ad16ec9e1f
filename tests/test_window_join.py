import itertools

import pytest
from pyspark.sql import functions as F

from windowjoin.config import CountWindow, Layout, TimeWindow
from windowjoin.operators import baselines, measures, splitters
from windowjoin.operators.join import window_join
from windowjoin.operators.sequence import prepare, sequence
from windowjoin.plans import worker
from windowjoin.predicates import Band, Equi, Inequality, MultiBand, NotEqual
from windowjoin.queries.base import clicks_views
from windowjoin.sources import tables

W = CountWindow(50)


@pytest.fixture(scope="module")
def ev(spark, sf):
    return clicks_views(spark, sf).cache()


def brute(rows, test, w, n=1):
    """Two buffers of n; a full one probes the other's inserted window, then is inserted."""
    window, buffer, out = {"S": [], "R": []}, {"S": [], "R": []}, set()

    def work(side):
        other = "R" if side == "S" else "S"
        for key, value in buffer[side]:
            for k2, v2 in window[other][-w:]:
                s, r = ((key, value), (k2, v2)) if side == "S" else ((k2, v2), (key, value))
                if value is not None and v2 is not None and test(s[1], r[1]):
                    out.add((s[0], r[0]))
        window[side] += buffer[side]
        buffer[side] = []

    for side, key, value in rows:
        buffer[side].append((key, value))
        if len(buffer[side]) == n:
            work(side)
    for side in "SR":
        work(side)
    return out


def as_rows(ev):
    return [(r.side, r.key, r.value) for r in ev.orderBy("seq").collect()]


def found(df):
    got = [(r.s_key, r.r_key) for r in df.select("s_key", "r_key").collect()]
    assert len(got) == len(set(got))
    return set(got)


@pytest.mark.parametrize("kind,n", [("splitter", 1), ("wideleaf", 7), ("sorted", 1), ("sorted", 16)])
def test_kinds_against_simulation(ev, kind, n):
    want = brute(as_rows(ev), lambda s, r: abs(s - r) <= 300, 50, n)
    assert found(window_join(ev, Band(-300, 300), W, Layout(30, 4), kind, n_bat=n)) == want


@pytest.mark.parametrize("pred,test", [(Band(-100, 400), lambda s, r: s - 100 <= r <= s + 400), (Equi(), lambda s, r: s == r), (MultiBand(((-9, 5), (3, 80), (200, 300))), lambda s, r: s - 9 <= r <= s + 80 or s + 200 <= r <= s + 300), (NotEqual(), lambda s, r: s != r)])
@pytest.mark.parametrize("kind", ["wideleaf", "sorted"])
def test_predicates(ev, pred, test, kind):
    assert found(window_join(ev, pred, CountWindow(20), Layout(16, 4), kind)) == brute(as_rows(ev), test, 20)


@pytest.mark.parametrize("op", ["<", "<=", ">", ">="])
def test_inequality_counts(ev, op):
    want = baselines.nested_loop(ev, Inequality(op), W).count()
    assert window_join(ev, Inequality(op), W, Layout(30, 4), result="count").agg(F.sum("matches")).first()[0] == want


def test_baselines_agree(ev):
    want = found(baselines.nested_loop(ev, Band(-300, 300), W))
    for other in (baselines.split_replicate(ev, Band(-300, 300), W, 4), baselines.chain_flow(ev, Band(-300, 300), W, 4), baselines.chained_tree(ev, Band(-300, 300), W, 30)):
        assert found(other) == want


def test_time_window_closed(spark):
    rows = [("S", 1, 10, "2024-01-01 00:00:00"), ("R", 2, 10, "2024-01-01 01:00:00"), ("R", 3, 10, "2024-01-01 01:00:01"), ("S", 4, None, "2024-01-01 01:00:02")]
    t = spark.createDataFrame(rows, "side string, key bigint, value bigint, ts string").withColumn("ts", F.col("ts").cast("timestamp_ntz"))
    ranked = sequence(t, ["ts", "key"], F.date_trunc("hour", "ts"))
    for kind in ("wideleaf", "splitter", "sorted"):
        assert found(window_join(ranked, Equi(), TimeWindow(3600), Layout(600, 4), kind)) == {(1, 2)}


CASES = {
    "empty R": [("S", 1, 5), ("S", 2, 5)],
    "all equal": [(s, i, 7) for i, s in enumerate("SRSRRSSRSR")],
    "one side late": [("S", i, i) for i in range(6)] + [("R", 10 + i, i) for i in range(6)],
    "negative and limits": [("S", 1, -5), ("R", 2, -5), ("R", 3, 2**60), ("S", 4, 2**60), ("R", 5, -(2**60)), ("S", 6, -(2**60) + 1)],
    "nulls": [("S", 1, None), ("R", 2, None), ("S", 3, 4), ("R", 4, 4)],
    "growing": [("SR"[i % 2], i, i) for i in range(40)],
    "nothing": [],
}


@pytest.mark.parametrize("name", CASES)
def test_small_cases(spark, name):
    rows = CASES[name]
    t = spark.createDataFrame(rows, "side string, key bigint, value bigint").withColumn("o", F.monotonically_increasing_id())
    t = spark.createDataFrame([(s, k, v, i) for i, (s, k, v) in enumerate(rows)], "side string, key bigint, value bigint, o bigint")
    ranked = sequence(t, ["o"], F.expr("o div 8"))
    for (pred, test), w, n, kind in itertools.product([(Band(-2, 1), lambda s, r: s - 2 <= r <= s + 1)], (3,), (1, 4), ("wideleaf", "sorted")):
        assert found(window_join(ranked, pred, CountWindow(w), Layout(2, 8), kind, n_bat=n)) == brute(rows, test, w, n), (kind, n)


def test_multiband_is_normalised():
    assert MultiBand(((5, 9), (-1, 2), (2, 6), (20, 10))).normal == ((-1, 9),)


def test_sequence_equals_one_window(ev):
    from pyspark.sql import Window

    one = ev.withColumn("want", F.row_number().over(Window.orderBy("ts", "key")))
    assert one.filter("want <> seq").isEmpty()


def test_coarse_window_is_a_superset(ev):
    exact = window_join(ev, Band(-300, 300), W, Layout(30, 4), "wideleaf")
    coarse = window_join(ev, Band(-300, 300), CountWindow(50, exact=False), Layout(30, 4), "wideleaf")
    assert exact.exceptAll(coarse).isEmpty() and not coarse.exceptAll(exact).isEmpty()
    facts = measures.expired_probe_share(prepare(ev, 30), Band(-300, 300), W, Layout(30, 4)).first()
    assert facts.coarse_matches - facts.expired_matches == exact.count()


def test_no_nested_loop_in_plans(ev):
    for kind in ("splitter", "wideleaf", "sorted"):
        plan = window_join(ev, Band(-300, 300), W, Layout(30, 4), kind)._jdf.queryExecution().executedPlan().toString()
        assert "NestedLoop" not in plan and "Cartesian" not in plan


def test_assign_pid_forms_agree(spark):
    v = spark.range(0, 500).selectExpr("id * 37 % 211 as value")
    s = [10, 10, 50, 51, 120, 200]
    want = sorted((r.value, r.pid) for r in splitters.assign_pid(v, s, how="hof").collect())
    for how in ("arrow", "merge"):
        assert sorted((r.value, r.pid) for r in splitters.assign_pid(v, s, how=how).collect()) == want


def test_published_arithmetic():
    assert measures.storage_overhead(1.25) == {"extra": 1.5, "utilisation": 0.4}
    assert measures.metadata_overhead(1 << 16, 1 << 23) == 0.03125
    assert measures.index_bytes(1 << 16) == 256 << 10
    assert measures.tree_footprint() == 256 and (1 << 20) // 256 == 4096
    assert [splitters.adjustment_bound(p) for p in (1024, 65536)] == [4, 2]
    assert measures.merge_cost(8, 2) == 2 + 4 + 6 + 8


def test_worst_case_peels_one_value_a_round(spark):
    v = spark.createDataFrame([(x,) for x in splitters.worst_case_values(16)], "value bigint")
    rounds = splitters.adapt_splitters(v, 16, 3)
    errors = [measures.balance_error(splitters.assign_pid(v, s), 16).first().mae for s in rounds]
    assert errors == sorted(errors, reverse=True)


def test_known_adjustment(spark):
    e = spark.read.parquet("/root/testdata/sf0.01/events.parquet").selectExpr("cast(round(value * 100) as bigint) as value")
    sums = [sum(s) for s in splitters.adapt_splitters(e, 16, 4)]
    assert sums == [32212254720, 367515, 70505, 68244, 68080]


# -- worker plan ------------------------------------------------------------------------------------


def timed(spark, stamps, late=0):
    """Alternating sides, one arrival after the other, at the given seconds."""
    rows = [("SR"[i % 2], i, (i * 7) % 23, s, i) for i, s in enumerate(stamps)]
    t = spark.createDataFrame(rows, "side string, key bigint, value bigint, s bigint, o bigint").withColumn("ts", F.timestamp_seconds("s").cast("timestamp_ntz"))
    return rows, sequence(t, ["o"], F.expr("o div 64")).drop("s", "o")


def brute_time(rows, eps, seconds):
    out = set()
    for side, key, value, s, o in rows:
        for side2, key2, value2, s2, o2 in rows:
            if o2 < o and side2 != side and abs(value - value2) <= eps and abs(s - s2) <= seconds:
                out.add((key, key2) if side == "S" else (key2, key))
    return out


@pytest.mark.parametrize("start", [1_700_000_000, 0, -400_000, -200 * 86_400 * 365])
@pytest.mark.parametrize("n_sub", [3_600, 20_000, 86_400])
def test_time_windows_before_and_after_1970(spark, start, n_sub):
    rows, ranked = timed(spark, [start + 3600 * i for i in range(120)])
    want = brute_time(rows, 3, 86_400)
    for kind in ("sorted", "splitter"):
        assert found(window_join(ranked, Band(-3, 3), TimeWindow(86_400), Layout(n_sub, 4), kind)) == want
    for engine in ("worker", "relational"):
        n = window_join(ranked, Band(-3, 3), TimeWindow(86_400), Layout(n_sub, 4), result="count", engine=engine)
        assert n.agg(F.sum("matches")).first()[0] == len(want)


@pytest.mark.parametrize("flagged", [False, True])
def test_out_of_order_and_late_tuples(spark, flagged):
    rows, ranked = timed(spark, [5000 * i - (i * 37 % 11) * 4000 for i in range(150)])
    want = brute_time(rows, 4, 30_000)
    if flagged:  # some lie in the side buffers
        ranked = ranked.withColumn("late", F.col("key") % 5 == 0)
    window = TimeWindow(30_000, disorder=60_000)
    for kind in ("sorted", "wideleaf"):
        assert found(window_join(ranked, Band(-4, 4), window, Layout(10_000, 4), kind)) == want
    assert window_join(ranked, Band(-4, 4), window, Layout(10_000, 4), result="count").agg(F.sum("matches")).first()[0] == len(want)


def test_ranges_say_what_pairs_say(ev):
    """Records, expanded by hand with their rank limits, are the pairs."""
    layout = Layout(16, 4)
    records = window_join(ev, MultiBand(((-300, -10), (5, 300))), W, layout, result="ranges").collect()
    assert {r.band for r in records} == {0, 1}
    runs = {}
    for r in ev.orderBy("rank").collect():
        runs.setdefault((r.side, (r["rank"] - 1) // 16), []).append((r.value, r["rank"], r.key))
    got = set()
    for r in records:
        stored = "R" if r.probe_side == "S" else "S"
        for _, rank, key in sorted(runs[(stored, r.sub_id)], key=lambda x: x[:2])[r.id_start : r.id_end]:
            if r.rank_from <= rank < r.rank_to:
                got.add((r.probe_key, key) if stored == "R" else (key, r.probe_key))
    assert got == brute(as_rows(ev), lambda s, r: -300 <= r - s <= -10 or 5 <= r - s <= 300, 50)


@pytest.mark.parametrize("pred,test", [(NotEqual(), lambda s, r: s != r), (Inequality("<"), lambda s, r: s < r), (Inequality(">="), lambda s, r: s >= r), (MultiBand(((-9, 5), (200, 300))), lambda s, r: -9 <= r - s <= 5 or 200 <= r - s <= 300)])
@pytest.mark.parametrize("n", [1, 16])
def test_counts_make_no_pairs(ev, pred, test, n):
    counted = window_join(ev, pred, W, Layout(8, 4), n_bat=n, result="count")
    assert counted.agg(F.sum("matches")).first()[0] == len(brute(as_rows(ev), test, 50, n))
    plan = counted._jdf.queryExecution().executedPlan().toString()
    assert "Cartesian" not in plan and (n > 1 or "NestedLoop" not in plan)  # with batches: the totals, one row
    work = window_join(ev, pred, W, Layout(8, 4), "sorted", n_bat=n, result="profile").agg(F.sum("touched") + F.sum("copied")).first()[0]
    assert work == 0


@pytest.mark.parametrize("layout", [Layout(8, 4, slots=3), Layout(8, 4, shares=3), Layout(8, 300), Layout(8, 4, segment=2, warm=1), Layout(8, 4, lowest=0, highest=1 << 32)])
@pytest.mark.parametrize("kind", ["splitter", "sorted", "auto"])
def test_layouts_give_the_same_pairs(ev, layout, kind):
    assert found(window_join(ev, Band(-300, 300), W, layout, kind)) == brute(as_rows(ev), lambda s, r: abs(s - r) <= 300, 50)


def test_inherited_splitters_balance_and_fixed_ones_do_not(ev):
    ev = ev.filter("value is not null")
    mae = lambda **k: window_join(ev, Band(0, 0), W, Layout(100, 4, lowest=0, highest=1 << 32, segment=100), "splitter", result="profile", **k).agg(F.max_by("mae", "sub_id")).first()[0]
    assert mae() < 0.6 and mae(adjust=False) > 1.4


def test_batches_close_by_count_or_wait(spark):
    """A simulation of two buffers and a clock."""
    from windowjoin.config import BatchPolicy

    rows, ranked = timed(spark, [i * i % 97 + 60 * (i // 4) for i in sorted(range(90), key=lambda i: i * i % 97 + 60 * (i // 4))])
    rows = sorted(rows, key=lambda r: r[4])
    stamps = sorted(r[3] for r in rows)
    rows = [(*r[:3], s, r[4]) for r, s in zip(rows, stamps)]
    t = spark.createDataFrame(rows, "side string, key bigint, value bigint, s bigint, o bigint").withColumn("ts", F.timestamp_seconds("s").cast("timestamp_ntz"))
    ranked = sequence(t, ["o"], F.expr("o div 16"))
    window, buffer, want = {"S": [], "R": []}, {"S": [], "R": []}, set()

    def work(side):
        other = "R" if side == "S" else "S"
        for key, value in buffer[side]:
            for key2, value2 in window[other][-20:]:
                if abs(value - value2) <= 4:
                    want.add((key, key2) if side == "S" else (key2, key))
        window[side] += buffer[side]
        buffer[side] = []

    tick = None
    for side, key, value, s, _ in rows:
        if tick is not None and s // 120 != tick:
            work("S")
            work("R")
        tick = s // 120
        buffer[side].append((key, value))
        if len(buffer[side]) == 5:
            work(side)
    work("S")
    work("R")
    for kind in ("sorted", "wideleaf"):
        assert found(window_join(ranked, Band(-4, 4), CountWindow(20), Layout(8, 4), kind, n_bat=BatchPolicy(5, 120))) == want


def test_same_pairs_and_late_materialisation(spark, ev):
    from windowjoin.operators.join import attach

    a = window_join(ev, Band(-300, 300), W, Layout(8, 4), "sorted")
    assert measures.same_pairs(a, window_join(ev, Band(-300, 300), W, Layout(8, 4), "splitter"))
    assert not measures.same_pairs(a, window_join(ev, Band(-299, 300), W, Layout(8, 4), "sorted"))
    payload = lambda side: ev.filter(f"side = '{side}'").select(F.col("key").alias(f"{side.lower()}k"), F.col("ts").alias(f"{side.lower()}_ts"))
    assert attach(a, payload("S"), payload("R"), "sk", "rk").count() == a.count()


def test_transfer_counts_what_moves(ev):
    moved = measures.transfer(window_join(ev, Band(-300, 300), W, Layout(16, 4), "sorted"))
    assert moved["shuffleRecordsWritten"] > 0 and moved["shuffleBytesWritten"] > 0


def test_cluster_must_name_its_folder(spark):
    from windowjoin import runtime

    class Cluster:
        class sparkContext:  # noqa: N801
            master, applicationId = "spark://there:7077", "x"

        class conf:  # noqa: N801
            get = staticmethod(lambda name, default=None: default)

    with pytest.raises(RuntimeError):
        runtime.shared_root(Cluster)


@pytest.mark.parametrize("kind", ["splitter", "wideleaf", "sorted"])
def test_generated_streams_against_the_nested_loop(spark, kind):
    from windowjoin.sources.tables import two_streams

    ranked = two_streams(spark, 600, "zipf")
    assert found(window_join(ranked, Band(-40, 40), CountWindow(70), Layout(16, 8), kind)) == found(baselines.nested_loop(ranked, Band(-40, 40), CountWindow(70)))


@pytest.mark.parametrize("slots", [None, 1, 3])
def test_without_a_window_a_probe_is_sent_once_a_span(spark, monkeypatch, slots):
    """Several subwindows share a span: all pairs and counts are there, and far fewer rows are sent than one a subwindow."""
    monkeypatch.setattr(worker, "SPAN", 32)
    monkeypatch.setattr(worker, "PROBES", 50)
    ev = tables.two_streams(spark, 600, "narrow")
    layout = Layout(8, 4, slots=slots)
    got = sorted(tuple(r) for r in window_join(ev, Band(-40, 40), None, layout, "sorted").collect())
    rows = [(r.side, r.key, r.value) for r in ev.collect()]
    assert got == sorted((a, b, x, y) for p, a, x in rows if p == "S" for q, b, y in rows if q == "R" and abs(x - y) <= 40)
    counted = window_join(ev, Band(-40, 40), None, layout, result="count").groupBy().sum("matches").first()[0]
    assert counted == len(got)
    sent = worker.packed(prepare(ev, 8), Band(-40, 40), None, layout, (), False)[0].filter(f"op = {worker.PROBE}")
    most = max(r.n for r in sent.groupBy("side", "rows").agg(F.count("*").alias("n")).collect())
    assert most <= -(-300 // 32) + (slots or 1)
