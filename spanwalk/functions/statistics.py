"""Exact order statistics and windows of a graph's times."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .predicates import Window


def exact_percentile(df: DataFrame, column: str, p: float, most: int = 50_000) -> int | None:
    """The smallest value of which at least the share `p` of all rows is at or below.

    Sketches narrow a bracket until few distinct values are left, so no task holds all values.
    """
    total, low, high = df.agg(F.count(column), F.min(column), F.max(column)).head()
    if not total:
        return None
    rank = max(1, math.ceil(round(p * total, 9)))
    below = 0
    while True:
        inside = df.where(F.col(column).between(low, high))
        n = inside.count()
        if n <= most or low == high:
            break
        share = (rank - below) / n
        a, b = inside.agg(F.percentile_approx(column, [max(0.0, share - 0.001), min(1.0, share + 0.001)], 10_000).alias("q")).head().q
        if (a, b) == (low, high):  # the sketch can't part them: halve the range
            b = (low + high) // 2
        before, upto = below + inside.where(F.col(column) < a).count(), below + inside.where(F.col(column) <= b).count()
        if rank <= before:
            high = a - 1
        elif rank > upto:
            low, below = b + 1, upto
        else:
            low, high, below = a, b, before
    counts = inside.groupBy(column).agg(F.count("*").alias("n")).orderBy(column)
    for row in counts.collect():  # at most `most` values
        below += row.n
        if below >= rank:
            return int(row[0])
    return int(high)


def window_percentile(edges: DataFrame, p: float = 0.95) -> Window | None:
    """From the percentile of start times to the last end."""
    start = exact_percentile(edges, "t_start", p)
    return None if start is None else Window(start, int(edges.agg(F.max("t_end")).head()[0]))


def window_recent(edges: DataFrame, share: float) -> Window | None:
    """The most recent share of the edges by start time; equal starts may make it a little more."""
    return window_percentile(edges, 1 - share)
