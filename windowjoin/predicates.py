"""Join predicates as value bounds of the stored side, given the probing value.

A predicate is read as a condition on the R value relative to the S value. ``bounds``
gives the intervals of R values that an S value asks for; ``mirrored`` is the same
condition seen from R. A null value matches nothing.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Interval:
    """Bounds of stored values; None is open. ``closed`` tells which ends belong to it."""

    lo: Column | None
    hi: Column | None
    lo_closed: bool = True
    hi_closed: bool = True

    def holds(self, value: Column) -> Column:
        test = value.isNotNull()
        if self.lo is not None:
            test = test & ((value >= self.lo) if self.lo_closed else (value > self.lo))
        if self.hi is not None:
            test = test & ((value <= self.hi) if self.hi_closed else (value < self.hi))
        return test


class Predicate:
    def bounds(self, value: Column) -> list[Interval]:
        raise NotImplementedError

    def mirrored(self) -> Predicate:
        raise NotImplementedError

    def residual(self, s_value: Column, r_value: Column) -> Column:
        """The condition itself."""
        found = [i.holds(r_value) for i in self.bounds(s_value)]
        out = found[0]
        for f in found[1:]:
            out = out | f
        return out & s_value.isNotNull()

    negated = False


@dataclass(frozen=True)
class Band(Predicate):
    """s + lo_off <= r <= s + hi_off."""

    lo_off: float | int
    hi_off: float | int

    def bounds(self, value: Column) -> list[Interval]:
        return [Interval(value + F.lit(self.lo_off), value + F.lit(self.hi_off))]

    def mirrored(self) -> Band:
        return Band(-self.hi_off, -self.lo_off)


@dataclass(frozen=True)
class Equi(Predicate):
    """s = r."""

    def bounds(self, value: Column) -> list[Interval]:
        return [Interval(value, value)]

    def mirrored(self) -> Equi:
        return self


FLIPPED = {"<": ">", "<=": ">=", ">": "<", ">=": "<="}


@dataclass(frozen=True)
class Inequality(Predicate):
    """s op r, one of < <= > >=."""

    op: str

    def bounds(self, value: Column) -> list[Interval]:
        if self.op in ("<", "<="):
            return [Interval(value, None, lo_closed=self.op == "<=")]
        return [Interval(None, value, hi_closed=self.op == ">=")]

    def mirrored(self) -> Inequality:
        return Inequality(FLIPPED[self.op])


@dataclass(frozen=True)
class MultiBand(Predicate):
    """Any of several bands; overlapping or touching ones are joined first."""

    bands: tuple[tuple[int, int], ...]
    normal: tuple[tuple[int, int], ...] = field(init=False)

    def __post_init__(self) -> None:
        out: list[tuple[int, int]] = []
        for lo, hi in sorted(b for b in self.bands if b[0] <= b[1]):
            if out and lo <= out[-1][1]:
                out[-1] = (out[-1][0], max(hi, out[-1][1]))
            else:
                out.append((lo, hi))
        object.__setattr__(self, "normal", tuple(out))

    def bounds(self, value: Column) -> list[Interval]:
        return [Interval(value + F.lit(lo), value + F.lit(hi)) for lo, hi in self.normal]

    def mirrored(self) -> MultiBand:
        return MultiBand(tuple((-hi, -lo) for lo, hi in self.normal))


@dataclass(frozen=True)
class NotEqual(Predicate):
    """s <> r: the equal range, negated."""

    negated = True

    def bounds(self, value: Column) -> list[Interval]:
        return [Interval(None, value, hi_closed=False), Interval(value, None, lo_closed=False)]

    def equal_range(self, value: Column) -> Interval:
        return Interval(value, value)

    def mirrored(self) -> NotEqual:
        return self


@dataclass(frozen=True)
class Theta(Predicate):
    """Any SQL condition over columns ``s_*`` and ``r_*`` that implies the ``envelope`` band."""

    expr: str
    envelope: Band

    def bounds(self, value: Column) -> list[Interval]:
        return self.envelope.bounds(value)

    def mirrored(self) -> Theta:
        return Theta(self.expr, self.envelope.mirrored())
