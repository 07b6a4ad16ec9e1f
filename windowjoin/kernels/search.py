"""Searches in sorted arrays, with their comparisons counted."""

from __future__ import annotations

import numpy as np


def binary_search(fences: np.ndarray, target: float) -> tuple[int, int]:
    """First index with fence >= target, and comparisons."""
    lo, hi, n = 0, len(fences), 0
    while lo < hi:
        mid = (lo + hi) // 2
        n += 1
        if fences[mid] < target:
            lo = mid + 1
        else:
            hi = mid
    return lo, n


def gallop_search(fences: np.ndarray, targets: np.ndarray) -> tuple[np.ndarray, int]:
    """The same for ascending targets: doubling steps from the last answer, then bisection of the last step."""
    out, at, n = np.empty(len(targets), np.int64), 0, 0
    size = len(fences)
    for k, target in enumerate(targets):
        step, lo, hi = 1, at, at
        while hi < size:
            n += 1
            if fences[hi] >= target:
                break
            lo = hi + 1
            hi += step
            step *= 2
        hi = min(hi, size)
        while lo < hi:
            mid = (lo + hi) // 2
            n += 1
            if fences[mid] < target:
                lo = mid + 1
            else:
                hi = mid
        out[k] = at = lo
    return out, n


def search_cost(fences: np.ndarray, targets: np.ndarray) -> dict[str, int]:
    """Comparisons of either search over a whole ascending batch."""
    return {"gallop": gallop_search(fences, targets)[1], "binary": sum(binary_search(fences, t)[1] for t in targets)}


def balanced_merge_cuts(main: np.ndarray, batch: np.ndarray, parts: int) -> list[tuple[int, int]]:
    """Cuts (in main, in batch) that split a merge of two sorted arrays into equal outputs."""
    cuts = []
    for k in range(parts + 1):
        want = (len(main) + len(batch)) * k // parts
        lo, hi = max(0, want - len(batch)), min(want, len(main))
        while lo < hi:  # elements of main among the first ``want`` of the output
            mid = (lo + hi) // 2
            if main[mid] <= batch[want - mid - 1]:
                lo = mid + 1
            else:
                hi = mid
        cuts.append((lo, want - lo))
    return cuts


def merge_parts(main: np.ndarray, batch: np.ndarray, parts: int) -> np.ndarray:
    """The merge, each part on its own."""
    cuts = balanced_merge_cuts(main, batch, parts)
    return np.concatenate([np.sort(np.concatenate((main[a:c], batch[b:d])), kind="stable") for (a, b), (c, d) in zip(cuts, cuts[1:], strict=False)])


def merge_with_keys(main: np.ndarray, main_keys: np.ndarray, batch: np.ndarray, keys: np.ndarray, parts: int) -> tuple[np.ndarray, np.ndarray]:
    """The merge of sorted values with their keys, each part on its own; equal values keep the run's first."""
    values, ids = [], []
    cuts = balanced_merge_cuts(main, batch, parts)
    for (a, b), (c, d) in zip(cuts, cuts[1:], strict=False):
        v = np.concatenate((main[a:c], batch[b:d]))
        order = np.argsort(v, kind="stable")
        values.append(v[order])
        ids.append(np.concatenate((main_keys[a:c], keys[b:d]))[order])
    return np.concatenate(values), np.concatenate(ids)
