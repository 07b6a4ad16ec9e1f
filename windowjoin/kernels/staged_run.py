"""Staging buffer, sorted main run and sampled fence index of one subwindow."""

from __future__ import annotations

import numpy as np

from windowjoin.kernels.search import balanced_merge_cuts, binary_search, gallop_search, merge_parts, merge_with_keys


class StagedSortedRun:
    """``buffer=0`` shifts the run on every insertion, ``fences=False`` searches the whole run,
    ``copy_equal=False`` searches for equal probes again."""

    def __init__(self, buffer: int = 1024, partitions: int = 64, fences: bool = True, threads: int = 1, copy_equal: bool = True):
        self.size, self.partitions, self.use_fences, self.threads, self.copy_equal = buffer, partitions, fences, threads, copy_equal
        none = np.zeros(0, np.int64)
        self.main, self.main_keys, self.fence, self.step = none, none, none, 1
        self.staged, self.staged_keys = none, none
        self.moved = self.merges = self.buffer_comparisons = self.search_comparisons = self.scan_steps = self.copied_results = 0

    def _merge(self, values: np.ndarray, keys: np.ndarray) -> None:
        order = np.argsort(values, kind="stable")
        self.main, self.main_keys = merge_with_keys(self.main, self.main_keys, values[order], keys[order], self.threads)
        self.moved += len(self.main)
        self.merges += 1
        self._index()

    def _index(self) -> None:
        """Every (M/P)-th value: the first of each fence partition."""
        self.step = max(1, -(-len(self.main) // self.partitions))
        self.fence = self.main[:: self.step]

    def flush(self) -> None:
        if len(self.staged):
            v, k = self.staged, self.staged_keys
            self.staged = self.staged_keys = np.zeros(0, np.int64)
            self._merge(v, k)

    def insert(self, value: int, key: int = 0) -> None:
        self.insert_batch(np.array([value], np.int64), np.array([key], np.int64))

    def insert_batch(self, values: np.ndarray, keys: np.ndarray | None = None) -> None:
        """A batch larger than the buffer goes straight into the run, what is staged before it."""
        keys = np.arange(len(values)) if keys is None else keys
        if len(values) > self.size:
            self.flush()
            self._merge(values, keys)
            return
        self.staged, self.staged_keys = np.concatenate((self.staged, values)), np.concatenate((self.staged_keys, keys))
        if len(self.staged) >= max(1, self.size):
            self.flush()

    def _position(self, ascending: np.ndarray, side: str) -> np.ndarray:
        """Two steps: gallop over the fences to the partition, then one loop over the partition and
        its bounds together, each passed once; without fences a binary search for each bound."""
        target = ascending if side == "left" else ascending + 1
        out = np.empty(len(target), np.int64)
        if not self.use_fences or not len(self.fence):
            for i, t in enumerate(target):
                out[i], n = binary_search(self.main, t)
                self.search_comparisons += n
            return out
        part, n = gallop_search(self.fence, target)
        self.search_comparisons += n
        at, now = 0, -1
        for i, (p, t) in enumerate(zip(part.tolist(), target.tolist(), strict=True)):
            if p != now:
                at, now = max(0, p - 1) * self.step, p
            end = min(len(self.main), p * self.step)
            while at < end and self.main[at] < t:
                at += 1
                self.scan_steps += 1
            self.scan_steps += at < end
            out[i] = at
        return out

    def probe_ranges(self, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        """(id_start, id_end) in the main run; equal probes copy the answer before."""
        if self.copy_equal:
            pairs, back = np.unique(np.stack((lo, hi), axis=1), axis=0, return_inverse=True)
            self.copied_results += len(lo) - len(pairs)
        else:
            order = np.lexsort((hi, lo))
            pairs, back = np.stack((lo, hi), axis=1)[order], np.argsort(order)
        order = np.argsort(pairs[:, 1], kind="stable")
        end = np.empty(len(pairs), np.int64)
        end[order] = self._position(pairs[order, 1], "right")
        found = np.stack((self._position(pairs[:, 0], "left"), end), axis=1)
        return found[back.ravel()]

    def probe_batch(self, lo: np.ndarray, hi: np.ndarray) -> list[np.ndarray]:
        """Keys per probe: the run by ranges, the buffer by comparison with every tuple."""
        self.buffer_comparisons += len(self.staged) * len(lo)
        hit = (self.staged[:, None] >= lo) & (self.staged[:, None] <= hi)
        return [np.concatenate((self.main_keys[a:b], self.staged_keys[hit[:, i]])) for i, (a, b) in enumerate(self.probe_ranges(lo, hi))]


class StreamPipeline:
    """Dataflow of the hardware engine in software: mergers, indexer, boundary generator,
    partitioners and probers, with the steps of each unit counted."""

    def __init__(self, partitions: int = 64, mergers: int = 8, probers: int = 8):
        self.partitions, self.mergers, self.probers = partitions, mergers, probers
        self.run = np.zeros(0, np.int64)
        self.work = {"merger": [0] * mergers, "indexer": 0, "boundaries": 0, "partitioner": 0, "prober": [0] * probers}

    def insert(self, batch: np.ndarray) -> np.ndarray:
        batch = np.sort(batch)
        cuts = balanced_merge_cuts(self.run, batch, self.mergers)
        for k, ((a, b), (c, d)) in enumerate(zip(cuts, cuts[1:], strict=False)):
            self.work["merger"][k] += c - a + d - b
        self.run = merge_parts(self.run, batch, self.mergers)
        step = max(1, -(-len(self.run) // self.partitions))
        self.fence, self.step = self.run[::step], step
        self.work["indexer"] += len(self.run)
        return self.fence

    def probe(self, values: np.ndarray, lo_off: int, hi_off: int) -> np.ndarray:
        """(id_start, id_end) per value, values ascending: the prober whose turn it is searches the
        partition that the partitioner found."""
        values = np.sort(values)
        bounds = np.stack((values + lo_off, values + hi_off + 1), axis=1)
        self.work["boundaries"] += bounds.size
        ends = np.empty((len(values), 2), np.int64)
        for column in range(2):
            part, n = gallop_search(self.fence, bounds[:, column])
            self.work["partitioner"] += n
            for k, (p, t) in enumerate(zip(part.tolist(), bounds[:, column].tolist(), strict=True)):
                a = max(0, p - 1) * self.step
                place, n = binary_search(self.run[a : p * self.step], t)
                self.work["prober"][k % self.probers] += n
                ends[k, column] = a + place
        return ends
