"""Temporal subgraph matching: small patterns of edges with orders between them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.predicates import Ordering, Window
from ..session import settle, settle_partitioned
from .graph import TemporalGraph, with_edge_ids


def match_pattern(graph: TemporalGraph, pattern: list[tuple[str, str]], window: Window, order: list[tuple[int, int, Ordering]] = (), delta: int | None = None, distinct_vertices: bool = True) -> DataFrame:
    """One row per match of `pattern`, a list of (variable, variable) edges.

    Columns: the variables, and s0, e0, s1, e1, ... (times of the pattern's edges). `order` asks
    that edge j stands to edge i as the predicate says; `delta` bounds the span of the whole match.
    Edges of a match are distinct. Joins go left-deep in the given order, each on the variables
    that it shares with what is bound already; predicates are residual range conditions.
    """
    rows_by_src = with_edge_ids(graph.restrict(window).walkable().select("src", "dst", "t_start", "t_end"))
    edges = settle_partitioned(rows_by_src, int(rows_by_src.sparkSession.conf.get("spark.sql.shuffle.partitions")), "src")
    bound: list[str] = []
    rows = None
    for k, (a, b) in enumerate(pattern):
        step = edges.select(F.col("src").alias("__a"), F.col("dst").alias("__b"), F.col("t_start").alias(f"s{k}"), F.col("t_end").alias(f"e{k}"), F.col("edge_id").alias(f"id{k}"))
        if a == b:
            step = step.where("__a = __b")
        if rows is None:
            rows = step
        else:
            condition = None
            for variable, column in ((a, "__a"), (b, "__b")):
                if variable in bound:
                    hit = F.col(variable) == F.col(column)
                    condition = hit if condition is None else condition & hit
            if condition is None:
                raise ValueError(f"edge {k} shares no variable with the edges before it")
            for j in range(k):
                condition = condition & (F.col(f"id{j}") != F.col(f"id{k}"))
            for i, j, kind in order:
                if max(i, j) == k:
                    condition = condition & kind.column(f"s{i}", f"e{i}", f"s{j}", f"e{j}")
            if delta is not None:
                first, last = F.least(*[F.col(f"s{j}") for j in range(k + 1)]), F.greatest(*[F.col(f"e{j}") for j in range(k + 1)])
                condition = condition & (last - first <= delta)
            rows = rows.join(step, condition)
        for variable, column in dict([(a, "__a"), (b, "__b")]).items():
            if variable not in bound:
                rows = rows.withColumn(variable, F.col(column))
                if distinct_vertices:
                    for other in bound:
                        rows = rows.where(F.col(other) != F.col(variable))
                bound.append(variable)
        rows = rows.drop("__a", "__b")
    if delta is not None and len(pattern) == 1:
        rows = rows.where(F.col("e0") - F.col("s0") <= delta)
    return rows.select(*bound, *[c for k in range(len(pattern)) for c in (f"s{k}", f"e{k}")])


def two_hop_paths(graph: TemporalGraph, window: Window) -> DataFrame:
    """Adjacent edge pairs (a to b to c) with one flag for every ordering; an edge may meet itself if it is a loop."""
    edges = graph.restrict(window).walkable()
    one = edges.select(F.col("src").alias("a"), F.col("dst").alias("b"), F.col("t_start").alias("s0"), F.col("t_end").alias("e0"))
    two = edges.select(F.col("src").alias("__b"), F.col("dst").alias("c"), F.col("t_start").alias("s1"), F.col("t_end").alias("e1"))
    pairs = one.join(two, F.col("b") == F.col("__b")).drop("__b")
    return pairs.withColumns({kind.value: kind.column("s0", "e0", "s1", "e1") for kind in Ordering})


def two_hop_counts(graph: TemporalGraph, window: Window) -> DataFrame:
    pairs = two_hop_paths(graph, window)
    return pairs.agg(F.count("*").alias("pairs"), *[F.sum(F.col(k.value).cast("long")).alias(k.value) for k in Ordering])


def temporal_cycles(graph: TemporalGraph, length: int, delta: int, window: Window, predicate: Ordering = Ordering.STRICTLY_SUCCEEDS) -> DataFrame:
    """Cycles of `length` edges in time order within `delta`."""
    names = [f"v{k}" for k in range(length)]
    pattern = [(names[k], names[(k + 1) % length]) for k in range(length)]
    return match_pattern(graph, pattern, window, [(k, k + 1, predicate) for k in range(length - 1)], delta)
