"""The three index structures of a subwindow in whole-array form, as the workers hold them.

Each takes the tuples of one subwindow, in arrival order or sorted, and answers a batch of
probe intervals. The one-tuple-at-a-time forms with their step counters are in the other
modules of this folder; these do the same partitioning with array operations.
"""

from __future__ import annotations

import numpy as np

from windowjoin.kernels.splitter_table import interpolate


def spans(starts: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(row, place) of every place of every span start, start+1, ..."""
    row = np.repeat(np.arange(len(starts)), lengths)
    return row, np.arange(len(row)) - np.repeat(np.cumsum(lengths) - lengths, lengths) + np.repeat(starts, lengths)


def slices(lengths: np.ndarray, most: int):
    """Bounds of runs of rows whose lengths add up to about ``most``, one row at least."""
    ends, at = np.cumsum(lengths), 0
    while at < len(lengths):
        to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + most, side="right")))
        yield at, to
        at = to


def places(values: np.ndarray, bound: np.ndarray | None, after_equal: np.ndarray, default: int) -> np.ndarray | None:
    """Place of each bound in ascending values, before or after equal ones; a masked bound is open."""
    if bound is None:
        return None
    known, mask = bound
    out = np.full(len(known), default, np.int64)
    for after in (False, True):
        pick = mask & (after_equal == after)
        if pick.any():
            out[pick] = np.searchsorted(values, known[pick], side="right" if after else "left")
    return out


class SortedRun:
    """Values in order with a fence every M/P of them; a probe's answer is a range of places."""

    kind = "sorted"

    def __init__(self, values: np.ndarray, partitions: int = 64):
        self.values = values
        self.step = max(1, -(-len(values) // max(1, partitions)))
        self.fences = values[:: self.step]
        self.sizes = np.diff(np.append(np.arange(0, len(values), self.step), len(values)))
        self.touched = self.copied = 0  # a sorted run tests and copies none

    def ranges(self, lo, hi, lo_closed: np.ndarray, hi_closed: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """[start, end) of each probe; ascending bounds walk through the run once."""
        start = places(self.values, lo, ~lo_closed, 0)
        end = places(self.values, hi, hi_closed, len(self.values))
        return start, np.maximum(start, end)


class Partitions:
    """Tuples by value partition, unsorted inside; borders are tested, partitions between are copied."""

    def __init__(self, values: np.ndarray, bounds: np.ndarray, kind: str):
        self.kind, self.bounds = kind, bounds
        pid = np.searchsorted(bounds, values, side="left")
        self.order = np.argsort(pid, kind="stable")
        self.sizes = np.bincount(pid, minlength=len(bounds) + 1)
        self.at = np.concatenate(([0], np.cumsum(self.sizes)))
        self.values = values[self.order]
        self.touched = self.copied = 0

    def candidates(self, lo, hi, lo_closed: np.ndarray, hi_closed: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """First and last partition that each probe asks."""
        first = places(self.bounds, lo, np.zeros(len(lo_closed), bool), 0)
        last = places(self.bounds, hi, np.zeros(len(hi_closed), bool), len(self.bounds))
        return first, last

    def matches(self, lo, hi, lo_closed: np.ndarray, hi_closed: np.ndarray, most: int = 1 << 20):
        """(probe, place) of the tuples in each probe's interval, a bounded number of candidates at once."""
        first, last = self.candidates(lo, hi, lo_closed, hi_closed)
        asking = np.flatnonzero(last >= first)
        if not len(asking):
            return
        tested = int(self.sizes[first[asking]].sum())
        uniform = all(len(x) and (x == x[0]).all() for x in (lo[1], hi[1], lo_closed, hi_closed))
        if uniform and tested > 512 * len(np.unique(first[asking])):
            yield from self._copies(first, last, asking, most)
            yield from self._grids(first, asking, lo, hi, lo_closed[0], hi_closed[0], most)
            yield from self._grids(last, asking[last[asking] > first[asking]], lo, hi, lo_closed[0], hi_closed[0], most)
        else:
            yield from self._lists(first, last, lo, hi, lo_closed, hi_closed, most)

    def _copies(self, first, last, asking, most: int):
        """All tuples of the partitions between the borders."""
        wide = asking[last[asking] - first[asking] > 1]
        start = self.at[first[wide] + 1]
        n = self.at[last[wide]] - start
        for a, b in slices(n, most):
            row, place = spans(start[a:b], n[a:b])
            self.copied += len(row)
            yield wide[a + row], place

    def _grids(self, border, rows, lo, hi, lo_closed: bool, hi_closed: bool, most: int):
        """Each border partition against the probes that ask for it: its tuples on one side of a
        grid, the probes on the other."""
        rows = rows[np.argsort(border[rows], kind="stable")]
        held: list[tuple[np.ndarray, np.ndarray]] = []
        n = 0
        for group in np.split(rows, np.flatnonzero(np.diff(border[rows])) + 1) if len(rows) else ():
            at, to = self.at[border[group[0]]], self.at[border[group[0]] + 1]
            if at == to:
                continue
            v = self.values[at:to]
            step = max(1, most // len(v))
            for k in range(0, len(group), step):
                asked = group[k : k + step]
                grid = np.ones((len(asked), len(v)), bool)
                if lo[1][0]:
                    grid &= v >= lo[0][asked, None] if lo_closed else v > lo[0][asked, None]
                if hi[1][0]:
                    grid &= v <= hi[0][asked, None] if hi_closed else v < hi[0][asked, None]
                self.touched += grid.size
                r, c = np.nonzero(grid)
                held.append((asked[r], c + at))
                n += len(r)
            if n > 1 << 16:
                yield tuple(map(np.concatenate, zip(*held, strict=True)))
                held, n = [], 0
        if held:
            yield tuple(map(np.concatenate, zip(*held, strict=True)))

    def _lists(self, first, last, lo, hi, lo_closed, hi_closed, most: int):
        """The same candidate by candidate, for small partitions that few probes ask for."""
        start, stop = self.at[first], self.at[np.maximum(last, first) + 1]
        n = np.where(last >= first, stop - start, 0)
        for a, b in slices(n, most):
            row, place = spans(start[a:b], n[a:b])
            row += a
            inner = (place >= self.at[first[row] + 1]) & (place < self.at[last[row]])
            test = np.flatnonzero(~inner)
            self.copied += len(row) - len(test)
            self.touched += len(test)
            v, r = self.values[place[test]], row[test]
            hit = np.ones(len(row), bool)
            hit[test] = within(v, r, lo, lo_closed, "lo") & within(v, r, hi, hi_closed, "hi")
            yield row[hit], place[hit]


def within(v: np.ndarray, row: np.ndarray, bound, closed: np.ndarray, end: str) -> np.ndarray:
    """Does each value lie inside its row's bound at that end?"""
    known, mask = bound
    b, c = known[row], closed[row]
    inside = (v > b) if end == "lo" else (v < b)
    return inside | (c & (v == b)) | ~mask[row]


def adjusted(values: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """Boundaries for the following subwindow from this one's counts, least and greatest values."""
    if not len(values):
        return bounds
    p = len(bounds) + 1
    pid = np.searchsorted(bounds, values, side="left")
    counts = np.bincount(pid, minlength=p)
    order = np.argsort(pid, kind="stable")
    grouped, used = values[order], np.flatnonzero(counts)
    first = (np.cumsum(counts) - counts)[used]
    least, greatest = np.zeros(p, values.dtype), np.zeros(p, values.dtype)
    least[used], greatest[used] = np.minimum.reduceat(grouped, first), np.maximum.reduceat(grouped, first)
    if values.dtype.kind == "f" or p > 64:
        return _interpolated(counts, least, greatest, p)
    return np.array(interpolate(counts.tolist(), least.tolist(), greatest.tolist(), p), values.dtype)


def _interpolated(counts: np.ndarray, least: np.ndarray, greatest: np.ndarray, p: int) -> np.ndarray:
    """The same for many partitions at once: whole numbers up to a share, then the spread times it."""
    cum, n = np.cumsum(counts), int(counts.sum())
    j = np.arange(1, p, dtype=np.int64)
    i = np.searchsorted(cum * p, n * j, side="left")
    share = (n * j - p * (cum[i] - counts[i])) / (counts[i] * p)
    low, spread = least[i], greatest[i].astype(np.float64) - least[i]
    if least.dtype.kind == "f":
        return low + spread * share
    return np.minimum(low + np.floor(spread * share).astype(np.int64), greatest[i])


def equal_widths(values: np.ndarray, p: int, lo=None, hi=None) -> np.ndarray:
    """P-1 boundaries of equal width over a given or the observed range."""
    lo = values.min() if lo is None else lo
    hi = values.max() if hi is None else hi
    if values.dtype.kind == "f":
        return lo + (hi - lo) * np.arange(1, p) / p
    return np.array([int(lo) + (int(hi) - int(lo)) * j // p for j in range(1, p)], np.int64)


def leaf_bounds(values: np.ndarray, width: int, chunk: int) -> np.ndarray:
    """Upper bounds of the leaves after the values came in chunks: a leaf above ``width`` is
    sorted and cut at the value boundary nearest its middle; equal values stay together."""
    bounds = values[:0]
    leaves: list[list[np.ndarray]] = [[]]
    for at in range(0, len(values), max(1, chunk)):
        part = values[at : at + max(1, chunk)]
        pid = np.searchsorted(bounds, part, side="left")
        order = np.argsort(pid, kind="stable")
        cuts = np.flatnonzero(np.diff(pid[order])) + 1
        for group in np.split(order, cuts):
            leaves[pid[group[0]]].append(part[group])
        new_leaves, new_bounds = [], []
        for k, held in enumerate(leaves):
            for piece, upper in _cut(held, width):
                new_leaves.append(piece)
                new_bounds.append(upper)
            new_bounds[-1] = bounds[k] if k < len(bounds) else None
        leaves, bounds = new_leaves, np.array(new_bounds[:-1], values.dtype)
    return bounds


def _cut(held: list[np.ndarray], width: int):
    """Pieces of a leaf, each with its greatest value; one piece where nothing is to be cut."""
    if sum(map(len, held)) <= width:
        return [(held, None)]
    todo, out = [np.sort(np.concatenate(held))], []
    while todo:
        leaf = todo.pop()
        if len(leaf) <= width or leaf[0] == leaf[-1]:
            out.append(([leaf], leaf[-1]))
            continue
        mid = len(leaf) // 2
        left, right = np.searchsorted(leaf, leaf[mid], side="left"), np.searchsorted(leaf, leaf[mid], side="right")
        at = left if left and (right == len(leaf) or mid - left <= right - mid) else right
        todo += [leaf[at:], leaf[:at]]
    return out


class ArrivalCounts:
    """How many of the places [a, b) of a sorted run arrived before the c-th tuple: bits of the
    arrival numbers, level by level, so that no pair is made. n log n to build, log n a question."""

    def __init__(self, arrival: np.ndarray):
        self.n = len(arrival)
        self.levels = []
        now = arrival.astype(np.int64)
        for bit in range(max(1, (self.n - 1).bit_length()) - 1, -1, -1):
            one = ((now >> bit) & 1).astype(bool)
            zeros = np.concatenate(([0], np.cumsum(~one))).astype(np.int32)
            self.levels.append((bit, zeros))
            now = np.concatenate((now[~one], now[one]))

    def before(self, a: np.ndarray, b: np.ndarray, c: np.ndarray) -> np.ndarray:
        a, b = a.astype(np.int64), b.astype(np.int64)
        c = np.clip(c, 0, self.n)
        out = np.where(c >= self.n, b - a, 0)
        for bit, zeros in self.levels:
            take = ((c >> bit) & 1).astype(bool)
            za, zb, all_zeros = zeros[a].astype(np.int64), zeros[b].astype(np.int64), int(zeros[-1])
            out += np.where(take & (c < self.n), zb - za, 0)
            a, b = np.where(take, all_zeros + a - za, za), np.where(take, all_zeros + b - zb, zb)
        return out
