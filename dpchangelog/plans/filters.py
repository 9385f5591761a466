"""Filters as objects: time ranges, sets of values of a column, and their conjunctions, with a test of disjointness.

Releases whose filters are pairwise disjoint in what one entry can pass share a budget: an entry pays for the dearest of them, not
for all. Time ranges of one changelog are disjoint for mutations but not for entries, so only filters on columns that an entry
keeps for good (`fixed`) make releases parallel; on a mutable column a move leaves one group and joins another, two folds.
"""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .accounting import Budget, compose_basic


@dataclass(frozen=True)
class Filter:
    """Mutations with low < ts <= high (None: unbounded) whose columns hold one of the stated values."""

    low: int | None = None
    high: int | None = None
    values: tuple[tuple[str, frozenset], ...] = ()
    fixed: frozenset = field(default=frozenset())

    @staticmethod
    def time(low: int | None, high: int | None) -> "Filter":
        if low is not None and high is not None and low >= high:
            raise ValueError("a time range ends after it starts")
        return Filter(low, high)

    @staticmethod
    def among(column: str, values: Iterable, fixed: bool = False) -> "Filter":
        return Filter(values=((column, frozenset(values)),), fixed=frozenset([column]) if fixed else frozenset())

    def and_(self, other: "Filter") -> "Filter":
        lows, highs = ([x for x in pair if x is not None] for pair in ((self.low, other.low), (self.high, other.high)))
        held = dict(self.values)
        for c, v in other.values:
            held[c] = held[c] & v if c in held else v
        return Filter(max(lows, default=None), min(highs, default=None), tuple(sorted(held.items())), self.fixed | other.fixed)

    def empty(self) -> bool:
        return any(not v for _, v in self.values) or (self.low is not None and self.high is not None and self.low >= self.high)

    def column(self) -> Column:
        """For DataFrame.where: comparisons with literals on the columns themselves, which reach the scan."""
        out = F.lit(True)
        for bound, test in ((self.low, lambda x: F.col("ts") > x), (self.high, lambda x: F.col("ts") <= x)):
            out = out if bound is None else out & test(bound)
        for c, v in self.values:
            some = F.col(c).isin(*sorted((x for x in v if x is not None), key=str)) if any(x is not None for x in v) else F.lit(False)
            out = out & (F.coalesce(some, F.lit(False)) | F.col(c).isNull() if None in v else some)
        return out

    def apply(self, cl: DataFrame) -> DataFrame:
        return cl.where(self.column())


def are_disjoint(f: Filter, g: Filter) -> bool:
    """Whether no mutation passes both."""
    return f.and_(g).empty()


def are_parallel(f: Filter, g: Filter) -> bool:
    """Whether no entry has mutations in both: the filters differ on a column that an entry keeps for good."""
    mine, theirs = dict(f.values), dict(g.values)
    return f.empty() or g.empty() or any(c in theirs and not (v & theirs[c]) and c in f.fixed and c in g.fixed for c, v in mine.items())


def filtered_budget(releases: list[tuple[Filter, Budget]]) -> Budget:
    """Total of releases by their filters: the dearest set of releases that one entry can pay for. Releases are put into groups
    of pairwise parallel filters, in order; a group costs its componentwise largest budget, and groups add up."""
    groups: list[list[tuple[Filter, Budget]]] = []
    for f, b in releases:
        for g in groups:
            if all(are_parallel(f, other) for other, _ in g):
                g.append((f, b))
                break
        else:
            groups.append([(f, b)])
    return compose_basic([Budget.sup(b for _, b in g) for g in groups])


def by_group(column: str, values: Iterable, budget: Budget, fixed: bool = True) -> Budget:
    """A release for each value of a column: one budget where an entry keeps its value, two where it can move."""
    n = len(set(values))
    return budget if fixed or n < 2 else compose_basic([budget, budget])
