"""Statistics of graphs, and measures of cost and accuracy of the access choice."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.predicates import Window
from ..plans import histogram as hist
from ..plans import index as idx
from .access import AccessPlan, choose_access, index_cost, scan_cost, true_matches, window_matches
from .baselines import time_expanded
from .graph import TemporalEdgeSet, TemporalGraph, degrees


def graph_stats(edges: DataFrame) -> DataFrame:
    """One row: vertices, edges, largest degrees, and mean degree both as m/n and 2m/n."""
    n = TemporalEdgeSet(edges).endpoints().df.agg(F.count("*").alias("n"))
    out = degrees(edges, "out").agg(F.sum("m").alias("edges"), F.max("m").alias("max_out"))
    into = degrees(edges, "in").agg(F.max("m").alias("max_in"))
    row = n.crossJoin(out).crossJoin(into)
    return row.select("n", F.col("edges").alias("m"), "max_out", "max_in", (F.col("edges") / F.col("n")).alias("m_per_n"), (2 * F.col("edges") / F.col("n")).alias("degree_2m_per_n"))


def degree_profile(edges: DataFrame, cutoffs: list[int], orientation: str = "out") -> DataFrame:
    """(cutoff, vertices, edges, share): what an index at each cutoff would cover."""
    deg = degrees(edges, orientation)
    spark = edges.sparkSession
    cuts = spark.createDataFrame([(int(c),) for c in cutoffs], "cutoff long")
    total = deg.agg(F.sum("m").alias("all"))
    met = F.broadcast(cuts).join(deg, F.col("m") >= F.col("cutoff"), "left").groupBy("cutoff").agg(F.count("v").alias("vertices"), F.coalesce(F.sum("m"), F.lit(0)).alias("edges"))
    return met.crossJoin(F.broadcast(total)).select("cutoff", "vertices", "edges", (F.col("edges") / F.col("all")).alias("share"))


def time_profile(edges: DataFrame) -> DataFrame:
    """(v, m, mean_gap, sd_gap, burstiness): gaps between successive starts of a vertex's edges.

    Burstiness is (sd - mean) / (sd + mean): -1 for a regular series, towards 1 for bursts.
    """
    from pyspark.sql import Window as W

    gap = F.col("t_start") - F.lag("t_start").over(W.partitionBy("src").orderBy("t_start"))
    per = edges.select("src", "t_start", gap.alias("gap")).groupBy(F.col("src").alias("v")).agg(F.count("*").alias("m"), F.avg("gap").alias("mean_gap"), F.stddev_pop("gap").alias("sd_gap"))
    return per.withColumn("burstiness", F.when(F.col("sd_gap") + F.col("mean_gap") > 0, (F.col("sd_gap") - F.col("mean_gap")) / (F.col("sd_gap") + F.col("mean_gap"))))


def asked_over(plan_catalog: DataFrame, window: Window) -> DataFrame:
    return plan_catalog.select("v").withColumns({"a": F.lit(window.start).cast("long"), "b": F.lit(window.end).cast("long")})


def selectivity(graph: TemporalGraph, vertices: DataFrame, window: Window) -> DataFrame:
    """(v, m, k, beta): edges of each vertex and those inside the window."""
    edges = graph.walkable()
    k = true_matches(edges, asked_over(vertices, window)).select("v", "k")
    return degrees(edges).join(k, "v").select("v", "m", "k", (F.col("k") / F.col("m")).alias("beta"))


def decision_accuracy(graph: TemporalGraph, plan: AccessPlan, window: Window) -> DataFrame:
    """One row over the indexed vertices: tp, tn, fp, fn, accuracy, precision, recall.

    An index should be used where the true selectivity is at or below theta.
    """
    asked = asked_over(plan.index.catalog, window)
    truth = window_matches(graph.walkable(), plan.index.catalog, window)
    rows = choose_access(asked, plan).join(truth, "v")
    did, should = F.col("access") == "index", F.col("k") / F.col("m") <= plan.theta
    count = lambda c: F.coalesce(F.sum(c.cast("long")), F.lit(0).cast("long"))
    row = rows.agg(count(did & should).alias("tp"), count(~did & ~should).alias("tn"), count(did & ~should).alias("fp"), count(~did & should).alias("fn"))
    part = lambda a, b: F.when(F.expr(b) > 0, F.expr(a) / F.expr(b))
    return row.select("*", part("tp + tn", "tp + tn + fp + fn").alias("accuracy"), part("tp", "tp + fp").alias("precision"), part("tp", "tp + fn").alias("recall"))


def estimate_error(graph: TemporalGraph, plan: AccessPlan, window: Window) -> DataFrame:
    """(v, m, k, k_hat, error, q_error): error as a share of the list, and the larger ratio of the two counts (each at least one)."""
    asked = asked_over(plan.index.catalog, window)
    rows = hist.estimate(plan.histogram, asked).join(true_matches(graph.walkable(), asked), ["v", "a", "b"])
    one = lambda c: F.greatest(F.col(c).cast("double"), F.lit(1.0))
    return rows.select("v", "m", "k", "k_hat", (F.abs(F.col("k_hat") - F.col("k")) / F.col("m")).alias("error"), F.greatest(one("k") / one("k_hat"), one("k_hat") / one("k")).alias("q_error"))


def cost_table(graph: TemporalGraph, plan: AccessPlan, window: Window) -> DataFrame:
    """(v, m, k, index_cost, scan_cost, least): modelled costs of both accesses with the true number of matches."""
    rows = true_matches(graph.walkable(), asked_over(plan.index.catalog, window)).join(plan.index.catalog, "v")
    t, s = index_cost(F.col("m"), F.col("k"), plan.c), scan_cost(F.col("m"), plan.c_scan)
    return rows.select("v", "m", "k", t.alias("index_cost"), s.alias("scan_cost"), F.least(t, s).alias("least"))


def work(graph: TemporalGraph, plan: AccessPlan, window: Window) -> DataFrame:
    """(v, m, k, index_examined, nodes, scan_examined): edges that either access reads for a containment query."""
    asked = asked_over(plan.index.catalog, window)
    opened = idx.nodes_read(plan.index, asked, idx.ThreeSided(F.col("a"), F.col("a"), F.col("b")))
    rows = true_matches(graph.walkable(), asked).join(plan.index.catalog, "v").join(opened, "v", "left")
    return rows.select("v", "m", "k", F.coalesce("examined", F.lit(0)).alias("index_examined"), F.coalesce("nodes", F.lit(0)).alias("nodes"), F.col("m").alias("scan_examined"))


def space(graph: TemporalGraph, plan: AccessPlan, window: Window) -> DataFrame:
    """(part, rows): edges, index nodes and the edges they hold, histogram cells, and the time-expanded graph of the window."""
    nodes, arcs = time_expanded(graph, window)
    parts = {
        "edges": graph.walkable().agg(F.count("*").alias("rows")),
        "index_edges": plan.index.nodes.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("rows")),
        "index_nodes": plan.index.nodes.agg(F.count("*").alias("rows")),
        "histogram_cells": plan.histogram.cells.agg(F.count("*").alias("rows")),
        "window_edges": graph.restrict(window).walkable().agg(F.count("*").alias("rows")),
        "expanded_nodes": nodes.agg(F.count("*").alias("rows")),
        "expanded_arcs": arcs.agg(F.count("*").alias("rows")),
    }
    out = None
    for name, df in parts.items():
        row = df.select(F.lit(name).alias("part"), F.col("rows").cast("long"))
        out = row if out is None else out.unionByName(row)
    return out
