"""Per-vertex choice between an index and a scan, inside one query.

A vertex without an index is scanned. For an indexed one the share of its edges that the query
should match is estimated from its histogram (or counted, or averaged, in the baselines); at or
below the threshold (or where a cost model says so) the index answers, above it the list is
scanned. All path methods take `access`: `lay` fetches a window's edges in the way named.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.predicates import Window
from ..plans import histogram as hist
from ..plans import index as idx
from ..session import settle, settle_sorted
from .edgemap import FrontierEdges, window_edges
from .graph import TemporalGraph

THETA = 0.20
MODES = ("scan", "index", "auto", "oracle", "uniform", "global_scan", "global_range")


@dataclass(frozen=True)
class AccessPlan:
    """Index and histogram of a graph's high-degree vertices, built once and used by many queries.

    `light` holds the edges of vertices without an index and `heavy` those of indexed ones, both
    in order of the axis that the heap is on; `inward` is the same for lookups by the other end.
    """

    index: idx.DualAxisIndex
    histogram: hist.Histogram
    theta: float = THETA
    mode: str = "threshold"  # or "cost"
    c: float = 1.0
    c_scan: float = 1.0
    light: DataFrame | None = None
    heavy: DataFrame | None = None
    inward: AccessPlan | None = None

    def side(self, direction: str) -> AccessPlan:
        if direction == "out":
            return self
        if self.inward is None:
            raise ValueError("plan_access(..., directions=('out', 'in')) builds the index of in-edges")
        return self.inward


def plan_access(graph: TemporalGraph, cutoff: int = idx.CUTOFF, theta: float = THETA, bins: int = hist.BINS, block_rows: int = idx.BLOCK_ROWS, directions: tuple[str, ...] = ("out",), **how) -> AccessPlan:
    """Out-edges have the largest start on top of the heap, in-edges the least end: what forward and backward paths bound."""
    edges = graph.walkable()
    made = {}
    for direction in directions:
        key, axis, mode = ("src", "t_start", "max") if direction == "out" else ("dst", "t_end", "min")
        index = idx.build_index(edges, cutoff, axis, mode, block_rows, direction)
        weight = F.col("weight") if "weight" in edges.columns else F.lit(1.0).alias("weight")
        rows = edges.select("src", "dst", "t_start", "t_end", weight)
        own = F.col(key) == F.col("v")
        parts = [settle_sorted(rows.join(index.catalog.select("v"), own, kind), axis) for kind in ("left_anti", "left_semi")]
        made[direction] = AccessPlan(index, hist.build_histogram(edges, index.catalog, bins, direction), theta, light=parts[0], heavy=parts[1], **how)
    return replace(made["out"], inward=made.get("in")) if "out" in made else AccessPlan(made["in"].index, made["in"].histogram, theta, inward=made["in"], **how)


def plan_choices(graph: TemporalGraph, cutoffs: list[int], theta: float = THETA, bins: int = hist.BINS, **how) -> dict[int, AccessPlan]:
    """Plans for each cutoff that decide but can't fetch: catalogs and histograms of out-edges, no index is built.

    Histograms don't depend on the cutoff, so those of the least one serve all.
    """
    edges = graph.walkable()
    sizes = settle(idx.select_indexed_vertices(edges, min(cutoffs)))
    histogram = hist.build_histogram(edges, sizes, bins)
    made = {}
    for cutoff in cutoffs:
        catalog = sizes.where(F.col("m") >= cutoff)
        made[cutoff] = AccessPlan(idx.DualAxisIndex(None, catalog, "out", "t_start", "max"), hist.restrict_histogram(histogram, catalog), theta, **how)
    return made


def index_cost(m: Column, k: Column, c: float = 1.0) -> Column:
    """Cost of reading k matches through an index of m edges."""
    return c * (F.log2(m.cast("double")) + k)


def scan_cost(m: Column, c: float = 1.0) -> Column:
    """Cost of reading a whole list of m edges."""
    return c * m.cast("double")


def true_matches(edges: DataFrame, asked: DataFrame, direction: str = "out") -> DataFrame:
    """(v, a, b, k): edges of v with start >= a and end <= b, counted."""
    pairs = asked.select("v", "a", "b").join(edges.select(F.col("src" if direction == "out" else "dst").alias("v"), "t_start", "t_end"), "v", "left")
    inside = (F.col("t_start") >= F.col("a")) & (F.col("t_end") <= F.col("b"))
    return pairs.groupBy("v", "a", "b").agg(F.sum(F.when(inside, 1).otherwise(0)).alias("k"))


def window_matches(edges: DataFrame, vertices: DataFrame, window: Window, direction: str = "out") -> DataFrame:
    """(v, k) of these vertices for one window: only partial counts move."""
    inside = edges.where(window.contains()).groupBy(F.col("src" if direction == "out" else "dst").alias("v")).agg(F.count("*").alias("k"))
    return vertices.select("v").join(inside, "v", "left").select("v", F.coalesce("k", F.lit(0)).alias("k"))


def _by_index(plan: AccessPlan) -> Column:
    """Does the index answer, by columns m, k_hat and beta?"""
    if plan.mode == "cost":
        return index_cost(F.col("m"), F.col("k_hat"), plan.c) < scan_cost(F.col("m"), plan.c_scan)
    return F.col("beta") <= plan.theta


def choose_access(asked: DataFrame, plan: AccessPlan, how: str = "auto", edges: DataFrame | None = None, direction: str = "out") -> DataFrame:
    """(v, a, b, m, k_hat, beta, access) of distinct asked (v, a, b); m is null where v has no index."""
    asked = asked.select("v", "a", "b").distinct()
    known = asked.join(plan.index.catalog, "v", "left")
    if how == "oracle":
        counts = true_matches(edges, asked.join(plan.index.catalog.select("v"), "v", "left_semi"), direction).withColumnRenamed("k", "k_hat")
    else:
        counts = hist.estimate(plan.histogram, asked).drop("m")
    out = known.join(counts, ["v", "a", "b"], "left").withColumn("k_hat", F.when(F.col("m").isNotNull(), F.coalesce("k_hat", F.lit(0.0)).cast("double")))
    beta = F.col("k_hat") / F.col("m")
    if how == "uniform":  # one decision for all vertices, from the average selectivity
        total = out.agg((F.sum("k_hat") / F.sum("m")).alias("__beta"))
        out = out.crossJoin(F.broadcast(total)).withColumn("beta", F.when(F.col("m").isNotNull(), F.col("__beta"))).drop("__beta")
    else:
        out = out.withColumn("beta", beta)
    use = F.lit(True) if how == "index" else _by_index(plan)
    return out.withColumn("access", F.when(F.col("m").isNotNull() & use, "index").otherwise("scan"))


@dataclass(frozen=True)
class WholeTable:
    """Time as a plain attribute: the edge table is read and filtered in every round."""

    edges: DataFrame
    key: str
    label: str | None = None  # narrow the whole table to starts (ends) from the frontier's least (to its largest) label

    def meet(self, frontier: DataFrame) -> DataFrame:
        own = self.edges
        if self.label is not None and "label" in frontier.columns:
            bound = frontier.agg((F.min if self.key == "src" else F.max)("label")).head()[0]
            if bound is not None:
                own = own.where(F.col("t_start") >= bound if self.key == "src" else F.col("t_end") <= bound)
        return frontier.join(own, F.col("v") == F.col(self.key))


def window_rows(graph: TemporalGraph, window: Window, how: str, plan: AccessPlan, direction: str = "out") -> DataFrame:
    """(src, dst, t_start, t_end, weight): the window's edges, each vertex's by index or by scan.

    The choice is made once for each indexed vertex, for the whole window: rounds then meet only
    what was fetched.
    """
    own, key = plan.side(direction), "src" if direction == "out" else "dst"
    inside = window.contains()
    if how == "index":
        by_index, others = own.index.catalog.select("v"), None
    else:
        if how == "auto":  # estimates of a whole window take no joins
            chosen = hist.estimate_window(own.histogram, window.start, window.end).withColumn("beta", F.col("k_hat") / F.col("m"))
            chosen = chosen.withColumn("access", F.when(_by_index(own), "index").otherwise("scan"))
        else:
            asked = own.index.catalog.select("v").withColumns({"a": F.lit(window.start).cast("long"), "b": F.lit(window.end).cast("long")})
            chosen = choose_access(asked, own, how, graph.walkable(), direction)
        chosen = settle(chosen.select("v", "access"))
        sizes = {r.access: r.n for r in chosen.groupBy("access").agg(F.count("*").alias("n")).collect()}
        by_index = chosen.where("access = 'index'").select("v") if sizes.get("index") else None
        others = chosen.where("access = 'scan'").select("v") if sizes.get("scan") else None
    rows = own.light.where(inside)
    if by_index is not None:
        found = idx.query_window(own.index, by_index, window.start, window.end)
        ends = (F.col("v").alias("src"), F.col("nbr").alias("dst")) if direction == "out" else (F.col("nbr").alias("src"), F.col("v").alias("dst"))
        rows = rows.unionByName(found.select(*ends, "t_start", "t_end", "weight"))
    if others is not None and by_index is None:
        rows = rows.unionByName(own.heavy.where(inside))
    elif others is not None:
        rows = rows.unionByName(own.heavy.where(inside).join(others, F.col(key) == F.col("v"), "left_semi"))
    return rows


def lay(graph: TemporalGraph, window: Window, direction: str = "out", access: str = "scan", plan: AccessPlan | None = None, columns: tuple[str, ...] = ("src", "dst", "t_start", "t_end")) -> FrontierEdges | WholeTable:
    """The window's edges for lookups by `src` (direction "out") or `dst`, fetched in the way named."""
    if access not in MODES:
        raise ValueError(f"access must be one of {MODES}")
    if access in ("global_scan", "global_range"):
        edges, key = graph.walkable().select(*columns).where(window.contains()), "src" if direction == "out" else "dst"
        if access == "global_scan":
            return WholeTable(edges, key)
        return WholeTable(settle_sorted(edges, "t_start" if direction == "out" else "t_end"), key, "label")
    if access == "scan":
        return window_edges(graph.restrict(window).walkable(), direction, columns)
    rows = window_rows(graph, window, access, plan or plan_access(graph, directions=("out", direction) if direction == "in" else ("out",)), direction)
    return window_edges(settle(rows.select(*columns)), direction, columns)


def explain_access(graph: TemporalGraph, plan: AccessPlan, window: Window, how: str = "auto") -> DataFrame:
    """The choice for every vertex, for a containment query over the window."""
    asked = graph.vertices.df.withColumns({"a": F.lit(window.start).cast("long"), "b": F.lit(window.end).cast("long")})
    return choose_access(asked, plan, how, graph.walkable())


def calibrate(graph: TemporalGraph, plan: AccessPlan, windows: list[Window]) -> tuple[float, float, float]:
    """(c, c_scan, theta*) in edges examined: what the index opens for each edge returned, one for a scan.

    theta* is the selectivity at which the two cost curves meet for the mean indexed degree.
    """
    ratios, mean_m = [], plan.index.catalog.agg(F.avg("m")).head()[0]
    for w in windows:
        asked = plan.index.catalog.select("v").withColumns({"a": F.lit(w.start).cast("long"), "b": F.lit(w.end).cast("long")})
        opened = idx.nodes_read(plan.index, asked, idx.ThreeSided(F.col("a"), F.col("a"), F.col("b"))).agg(F.sum("examined")).head()[0] or 0
        k, m = true_matches(graph.walkable(), asked).join(plan.index.catalog, "v").agg(F.sum("k"), F.sum(F.log2("m"))).head()
        if k:
            ratios.append(opened / (k + m))
    c = sum(ratios) / len(ratios) if ratios else 1.0
    theta = max(0.0, 1.0 / c - math.log2(mean_m) / mean_m) if mean_m else 0.0
    return c, 1.0, theta
