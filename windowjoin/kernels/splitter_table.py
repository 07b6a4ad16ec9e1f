"""Splitter table of one subwindow: binary or gallop search, chained slots, histograms."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np

from windowjoin.kernels.chained_slots import ChainedSlots
from windowjoin.kernels.search import binary_search, gallop_search


def interpolate(counts: Sequence[int], least: Sequence[int], greatest: Sequence[int], p: int) -> list[int]:
    """New splitters from a histogram, whole numbers, floor."""
    n, cum, out, i = sum(counts), 0, [], 0
    prev = 0
    for j in range(1, p):
        while p * (cum := prev + counts[i]) < n * j:
            prev, i = cum, i + 1
        out.append(least[i] + (n * j - p * prev) * (greatest[i] - least[i]) // (p * counts[i]))
    return out


class SplitterTable:
    """``search``: "gallop" for ascending batches, else "binary" for each tuple."""

    def __init__(self, splitters: Sequence[int], n_sub: int, sigma: float = 1.25, search: str = "gallop", adjust: bool = True):
        self.splitters = np.asarray(splitters, np.int64)
        self.p, self.n_sub, self.sigma, self.search, self.adjust = len(splitters) + 1, n_sub, sigma, search, adjust
        self.slots = ChainedSlots(self.p, n_sub, sigma)
        self.count = np.zeros(self.p, np.int64)
        self.least, self.greatest = [None] * self.p, [None] * self.p
        self.search_comparisons = self.scan_comparisons = self.copied = 0

    def _locate(self, sorted_values: np.ndarray) -> np.ndarray:
        if self.search == "gallop":
            pids, n = gallop_search(self.splitters, sorted_values)
        else:
            found = [binary_search(self.splitters, v) for v in sorted_values]
            pids, n = np.array([f[0] for f in found], np.int64), sum(f[1] for f in found)
        self.search_comparisons += n
        return pids

    def insert_batch(self, values: np.ndarray, keys: np.ndarray | None = None) -> None:
        """A batch in value order: tuples of one partition are stored together, its counts updated once."""
        if not len(values):
            return
        order = np.argsort(values, kind="stable")
        keys = np.arange(len(values)) if keys is None else keys
        v, k = values[order], keys[order]
        pids = self._locate(v)
        at = np.append(np.flatnonzero(np.concatenate(([True], pids[1:] != pids[:-1]))), len(pids))
        for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
            pid = int(pids[a])
            self.slots.insert_many(pid, v[a:b], k[a:b])
            self.count[pid] += b - a
            self.least[pid] = v[a] if self.least[pid] is None else min(v[a], self.least[pid])
            self.greatest[pid] = v[b - 1] if self.greatest[pid] is None else max(v[b - 1], self.greatest[pid])

    def probe_batch(self, lo: np.ndarray, hi: np.ndarray) -> list[np.ndarray]:
        """Keys with lo <= value <= hi for each probe. First all targets, then the partitions one
        by one: a partition's tuples outside, its probes inside; partitions between are copied."""
        first, last = (self._targets(x) for x in (lo, hi))
        out: list[list[np.ndarray]] = [[] for _ in lo]
        for pid in range(self.p):
            asking = np.flatnonzero((first <= pid) & (pid <= last))
            if not len(asking):
                continue
            values, keys = self.slots.scan(pid)
            if not len(keys):
                continue
            between = (first[asking] < pid) & (pid < last[asking])
            for i in asking[between]:
                self.copied += len(keys)
                out[i].append(keys)
            tested = asking[~between]
            self.scan_comparisons += len(keys) * len(tested)
            hit = (values[:, None] >= lo[tested]) & (values[:, None] <= hi[tested])
            for column, i in enumerate(tested):
                if hit[:, column].any():
                    out[i].append(keys[hit[:, column]])
        return [np.concatenate(parts) if parts else np.zeros(0, np.int64) for parts in out]

    def _targets(self, bounds: np.ndarray) -> np.ndarray:
        order = np.argsort(bounds, kind="stable")
        out = np.empty(len(bounds), np.int64)
        out[order] = self._locate(bounds[order])
        return out

    def expire(self, pid: int, n: int = 1) -> int:
        return self.slots.expire(pid, n)

    def next_splitters(self) -> list[int]:
        """For the following subwindow."""
        if not self.adjust or not self.count.sum():
            return self.splitters.tolist()
        fill = lambda x: [0 if v is None else int(v) for v in x]
        return interpolate(self.count.tolist(), fill(self.least), fill(self.greatest), self.p)

    def successor(self) -> SplitterTable:
        return SplitterTable(self.next_splitters(), self.n_sub, self.sigma, self.search, self.adjust)
