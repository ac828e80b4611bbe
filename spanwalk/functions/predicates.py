"""Ordering predicates between consecutive edges of a path, and the range queries they imply."""

from __future__ import annotations

from dataclasses import dataclass
from enum import Enum

from pyspark.sql import Column
from pyspark.sql import functions as F


class Ordering(str, Enum):
    """What the interval of a next edge B must be to that of the edge A before it.

    `OVERLAPS` starts and ends later; `OVERLAPS_PROPER` also starts before A ends.
    """

    SUCCEEDS = "succeeds"
    STRICTLY_SUCCEEDS = "strictly_succeeds"
    OVERLAPS = "overlaps"
    OVERLAPS_PROPER = "overlaps_proper"

    @property
    def one_sided(self) -> bool:
        """True if only the end of A matters, so that a scalar label decides what may follow."""
        return self in (Ordering.SUCCEEDS, Ordering.STRICTLY_SUCCEEDS)

    def column(self, a_start, a_end, b_start, b_end) -> Column:
        a_start, a_end, b_start, b_end = (F.col(c) if isinstance(c, str) else c for c in (a_start, a_end, b_start, b_end))
        if self is Ordering.SUCCEEDS:
            return a_end <= b_start
        if self is Ordering.STRICTLY_SUCCEEDS:
            return a_end < b_start
        later = (a_start < b_start) & (a_end < b_end)
        return later if self is Ordering.OVERLAPS else later & (b_start < a_end)

    def follows_label(self, label, b_start) -> Column:
        """May an edge that starts at `b_start` leave a vertex reached at `label`?"""
        return b_start > label if self is Ordering.STRICTLY_SUCCEEDS else b_start >= label

    def precedes_label(self, label, a_end) -> Column:
        """May an edge that ends at `a_end` come before a departure at `label`?"""
        return a_end < label if self is Ordering.STRICTLY_SUCCEEDS else a_end <= label

    def seed(self, start: int) -> int:
        """The label of a source: the empty path asks nothing but the window of the first edge."""
        return start - 1 if self is Ordering.STRICTLY_SUCCEEDS else start

    def three_sided(self, label, end) -> ThreeSided:
        """What an index with the largest start on top must find to go on from `label`."""
        first = label + 1 if self is Ordering.STRICTLY_SUCCEEDS else label
        return ThreeSided(heap_bound=first, tree_lo=first, tree_hi=F.lit(end) if not isinstance(end, Column) else end)


@dataclass(frozen=True)
class ThreeSided:
    """One bound on the heap axis and both bounds on the tree axis, each inclusive."""

    heap_bound: Column
    tree_lo: Column
    tree_hi: Column


@dataclass(frozen=True)
class Window:
    """A closed query window; edges count if they lie inside it."""

    start: int
    end: int

    def contains(self) -> Column:
        return (F.col("t_start") >= self.start) & (F.col("t_end") <= self.end)

    def intersects(self) -> Column:
        return (F.col("t_start") <= self.end) & (F.col("t_end") >= self.start)
