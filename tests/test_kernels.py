import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from windowjoin.kernels import structures
from windowjoin.kernels.chained_slots import ChainedSlots
from windowjoin.kernels.search import balanced_merge_cuts, binary_search, gallop_search, merge_parts
from windowjoin.kernels.splitter_table import SplitterTable, interpolate
from windowjoin.kernels.staged_run import StagedSortedRun, StreamPipeline
from windowjoin.kernels.wide_leaf import WideLeafTree

values = st.lists(st.integers(-1000, 1000), max_size=120)


@given(values, values)
@settings(max_examples=60, deadline=None)
def test_gallop_is_searchsorted(fences, targets):
    f, t = np.sort(np.array(fences, np.int64)), np.sort(np.array(targets, np.int64))
    assert (gallop_search(f, t)[0] == np.searchsorted(f, t, side="left")).all()
    assert all(binary_search(f, x)[0] == np.searchsorted(f, x, side="left") for x in t)


def test_gallop_is_cheaper_on_dense_batches():
    fences = np.arange(0, 100_000, 10)
    batch = np.arange(0, 100_000, 7)
    assert gallop_search(fences, batch)[1] < sum(binary_search(fences, t)[1] for t in batch) / 3


@given(values, values, st.integers(1, 9))
@settings(max_examples=60, deadline=None)
def test_balanced_merge(main, batch, parts):
    a, b = np.sort(np.array(main, np.int64)), np.sort(np.array(batch, np.int64))
    assert (merge_parts(a, b, parts) == np.sort(np.concatenate((a, b)))).all()
    cuts = balanced_merge_cuts(a, b, parts)
    sizes = [c - x + d - y for (x, y), (c, d) in zip(cuts, cuts[1:])]
    assert max(sizes) - min(sizes) <= 1


@given(values, st.integers(1, 16))
@settings(max_examples=60, deadline=None)
def test_slots_hold_everything_within_two_p(vals, p):
    s = ChainedSlots(p, max(1, len(vals)), 1.1)
    for i, v in enumerate(vals):
        s.insert(v % p, v, i)
    assert sum(s.sizes()) == len(vals)
    assert s.reserved <= p / 1.1 + 1e-9
    for pid in range(p):
        got, keys = s.scan(pid)
        assert [(v, k) for v, k in zip(got, keys)] == [(v, i) for i, v in enumerate(vals) if v % p == pid]


def test_slots_overflow_and_expiry():
    s = ChainedSlots(4, 16, 1.1)
    for i in range(16):
        s.insert(0, i, i)
    assert s.sizes() == [16, 0, 0, 0] and s.reserved < 4
    assert s.expire(0, 7) == 7 and list(s.scan(0)[0]) == list(range(7, 16))


def test_interpolation_worked_example():
    # 16 tuples in 4 partitions, running counts 5 and 10 around the third: the middle lies in it
    assert interpolate([2, 3, 5, 6], [0, 10, 20, 30], [9, 19, 29, 39], 4) == [10 + (16 - 8) * 9 // 12, 20 + (32 - 20) * 9 // 20, 30 + (48 - 40) * 9 // 24]


def test_adjustment_balances_and_can_be_switched_off():
    rng = np.random.default_rng(3)
    v = (rng.exponential(2000, 4000)).astype(np.int64)
    t = SplitterTable([(1 << 32) * j // 16 for j in range(1, 16)], 4000)
    errors = []
    for _ in range(4):
        t.insert_batch(v)
        errors.append(np.abs(t.count - 250).mean() / 250)
        t = t.successor()
    assert errors[0] > 1.8 and errors[3] < 0.05
    fixed = SplitterTable([10, 20], 10, adjust=False)
    fixed.insert_batch(np.arange(30))
    assert fixed.next_splitters() == [10, 20]


@pytest.mark.parametrize("seed", range(3))
def test_structures_give_the_same_matches(seed):
    rng = np.random.default_rng(seed)
    v = rng.integers(0, 300, 400)
    lo = rng.integers(-20, 300, 50)
    hi = lo + rng.integers(0, 40, 50)
    want = [sorted(np.flatnonzero((v >= a) & (v <= b))) for a, b in zip(lo, hi)]
    table = SplitterTable([20 * j for j in range(1, 16)], 400)
    table.insert_batch(v)
    tree, plain = WideLeafTree(16, 4), WideLeafTree(16, 4, sorted_leaves=True)
    tree.insert_batch(v)
    plain.insert_batch(v)
    run = StagedSortedRun(32, 16)
    for i, x in enumerate(v):
        run.insert(x, i)
    for found in (table.probe_batch(lo, hi), tree.probe_batch(lo, hi), plain.probe_batch(lo, hi), run.probe_batch(lo, hi)):
        assert [sorted(map(int, f)) for f in found] == want


def test_wide_leaves_cost_less_and_keep_values_together():
    v = np.random.default_rng(1).integers(0, 50, 3000)
    tree, plain = WideLeafTree(256), WideLeafTree(256, sorted_leaves=True)
    for i, x in enumerate(v.tolist()):  # in arrival order, one by one
        tree.insert(x, i)
        plain.insert(x, i)
    assert tree.moves < plain.moves
    owners = {}
    bounds = [upper for _, upper in tree.leaves()]
    assert bounds[:-1] == sorted(set(bounds[:-1])) and bounds[-1] is None
    for i, (leaf, upper) in enumerate(tree.leaves()):
        held = tree.slots.scan(leaf.pid)[0]
        assert len(held) == leaf.n and (upper is None or max(held) <= upper)
        for x in set(held.tolist()):
            assert owners.setdefault(x, i) == i
    assert sorted(zip(*map(np.ndarray.tolist, tree.scan()))) == sorted(zip(v.tolist(), range(3000)))


def test_equal_values_go_on_in_chained_slots():
    tree = WideLeafTree(16)
    tree.insert_batch(np.concatenate((np.full(100, 7), np.arange(40))))
    leaf = next(x for x, upper in tree.leaves() if upper is None or upper >= 7)
    assert leaf.n >= 100 and len(list(tree.slots.chain(leaf.pid))) > 5


def test_path_reuse_descends_less():
    v = np.random.default_rng(2).integers(0, 10_000, 4000)
    batch, single = WideLeafTree(32, 4), WideLeafTree(32, 4)
    batch.insert_batch(v)
    for i, x in enumerate(v.tolist()):
        single.insert(x, i)
    lo = np.arange(0, 10_000, 3)
    before = batch.descents
    found = batch.probe_batch(lo, lo + 5)
    assert batch.descents - before + batch.climbed < 2 * len(lo) * 5
    assert [sorted(f.tolist()) for f in found] == [np.flatnonzero((v >= a) & (v <= a + 5)).tolist() for a in lo]
    assert sorted(zip(*map(np.ndarray.tolist, single.scan()))) == sorted(zip(v.tolist(), range(4000)))


def test_staged_run_buffer_and_bypass():
    big, small = StagedSortedRun(256), StagedSortedRun(0)
    for x in range(512):
        big.insert(511 - x, x)
        small.insert(511 - x, x)
    assert big.moved < small.moved / 50 and (big.main == small.main).all()
    b = StagedSortedRun(100)
    b.insert_batch(np.arange(100))
    assert b.merges == 1 and not len(b.staged)
    c = StagedSortedRun(100, threads=3)
    c.insert_batch(np.arange(50, 90))
    c.insert_batch(np.arange(101), np.arange(1000, 1101))  # larger than the buffer: past it, what is staged first
    assert c.merges == 2 and not len(c.staged) and (c.main == np.sort(np.concatenate((np.arange(50, 90), np.arange(101))))).all()
    plain = StagedSortedRun(100, fences=False, copy_equal=False)
    plain.insert_batch(np.arange(100))
    assert plain.probe_ranges(np.array([7, 5, 5]), np.array([9, 9, 9])).tolist() == [[7, 10], [5, 10], [5, 10]] and not plain.copied_results and plain.search_comparisons > 0
    same = b.probe_ranges(np.array([5, 5, 7]), np.array([9, 9, 9]))
    assert same.tolist() == [[5, 10], [5, 10], [7, 10]] and b.copied_results == 1


def test_pipeline_counts_units():
    p = StreamPipeline(8, 4, 4)
    p.insert(np.arange(100))
    p.insert(np.arange(50, 150))
    assert len(p.run) == 200 and max(p.work["merger"]) - min(p.work["merger"]) <= 2
    assert p.probe(np.array([10, 60]), -5, 5).tolist() == [[5, 16], [60, 82]]
    assert 0 < sum(p.work["prober"]) <= 4 * 5


@given(values, st.integers(2, 40), st.integers(1, 30))
@settings(max_examples=60, deadline=None)
def test_leaf_bounds_cut_no_value(vals, width, chunk):
    v = np.array(vals, np.int64)
    b = structures.leaf_bounds(v, width, chunk)
    assert (np.diff(b) > 0).all()
    sizes = np.bincount(np.searchsorted(b, v, side="left"), minlength=len(b) + 1)
    pid = np.searchsorted(b, v, side="left")
    assert all(n <= width or len(set(v[pid == i].tolist())) == 1 for i, n in enumerate(sizes))


@given(st.permutations(list(range(40))), st.integers(0, 41), st.integers(0, 40), st.integers(0, 40))
@settings(max_examples=80, deadline=None)
def test_arrival_counts(order, c, a, b):
    a, b = min(a, b), max(a, b)
    counts = structures.ArrivalCounts(np.array(order))
    assert counts.before(np.array([a]), np.array([b]), np.array([c]))[0] == sum(x < c for x in order[a:b])


def test_adjustment_forms_agree():
    v = (np.random.default_rng(5).exponential(3000, 5000)).astype(np.int64)
    b = structures.equal_widths(v, 200)
    table = SplitterTable(b.tolist(), 5000)
    table.insert_batch(v)
    got = structures.adjusted(v, b)
    assert np.abs(got - np.array(table.next_splitters())).max() <= 1


@pytest.mark.parametrize("n,probes,width,open_end", [(4000, 300, 400, None), (4000, 300, 9000, None), (300, 40, 30, None), (4000, 300, 400, "lo"), (4000, 300, 400, "hi"), (0, 5, 3, None)])
@pytest.mark.parametrize("closed", [(True, True), (False, False)])
def test_partition_matches_are_a_scan(n, probes, width, open_end, closed):
    rng = np.random.default_rng(n + width)
    v = rng.integers(0, 10_000, n)
    held = structures.Partitions(v, np.array([500, 1000, 1000, 4000, 9000]), "splitter")
    lo = rng.integers(-50, 10_000, probes)
    hi = lo + width
    bounds = [(x, np.full(probes, open_end != e)) for x, e in ((lo, "lo"), (hi, "hi"))]
    got = [set() for _ in lo]
    for probe, place in held.matches(*bounds, np.full(probes, closed[0]), np.full(probes, closed[1]), most=5000):
        for i, k in zip(probe.tolist(), held.order[place].tolist()):
            assert k not in got[i]
            got[i].add(k)
    for i, (a, b) in enumerate(zip(lo, hi)):
        above = np.ones(n, bool) if open_end == "lo" else (v >= a if closed[0] else v > a)
        below = np.ones(n, bool) if open_end == "hi" else (v <= b if closed[1] else v < b)
        assert got[i] == set(np.flatnonzero(above & below).tolist())
