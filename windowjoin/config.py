"""What a window join is told: windows, layout, batches."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class CountWindow:
    """The last ``size`` tuples of each stream; ``exact`` filters the oldest subwindow."""

    size: int
    exact: bool = True

    def __post_init__(self) -> None:
        if self.size < 1:
            raise ValueError("a window holds one tuple at least")


@dataclass(frozen=True)
class TimeWindow:
    """Tuples at most ``seconds`` apart, both ends included.

    ``disorder``: how far a tuple's time may lie before one that came earlier; probes then
    also look that far ahead of their own time.
    """

    seconds: int
    exact: bool = True
    disorder: int = 0


@dataclass(frozen=True)
class Layout:
    """Subwindow size (tuples, or seconds for time windows), value partitions, worker slots.

    ``slots``: workers that take each side's subwindows (or segments of them) in turn; without
    it the session's shuffle partitions do, both sides together;
    ``shares``: tasks among which a subwindow's probes are dealt (its tuples go to each);
    ``segment``: subwindows whose boundaries one task carries on, after ``warm`` before them;
    ``lowest``, ``highest``: range of the first boundaries, else the observed one.
    """

    n_sub: int = 500
    partitions: int = 16
    slots: int | None = None
    shares: int = 1
    segment: int = 8
    warm: int = 3
    lowest: int | None = None
    highest: int | None = None

    def live(self, window: CountWindow) -> int:
        """Subwindows that a probe can meet at most."""
        return -(-window.size // self.n_sub) + 1


@dataclass(frozen=True)
class BatchPolicy:
    """A batch closes at ``max_count`` tuples or after ``max_wait`` seconds, whichever is first."""

    max_count: int = 1
    max_wait: float | None = None


def threads_for(n_bat: int, full: int = 8, least_batch: int = 128) -> int:
    """Threads that the reported experiments give a batch: one below 128 tuples."""
    return full if n_bat >= least_batch else 1
