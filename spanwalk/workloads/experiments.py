"""The experiments on the given tables: python -m spanwalk.workloads.experiments NAME [--sf DIR] [--cores N].

Each prints one JSON object a row. Work counters (edges examined) are the primary evidence at
test sizes; wall times are printed beside them.
"""

from __future__ import annotations

import argparse
import json

from pyspark.sql import SparkSession
from pyspark.sql import functions as F


from ..functions.statistics import window_percentile, window_recent
from ..operators import access, baselines, components, metrics, paths, structure
from ..operators.graph import TemporalGraph, top_sources
from ..plans import index
from ..session import local_session, settle
from ..sources.graphs import TABLES, load_graph
from ..sources.synthetic import synthetic_edges
from .measures import normalized, thread_sweep, time_runs

SHARES = (0.001, 0.005, 0.01, 0.02, 0.03, 0.04, 0.05, 0.10, 0.20, 0.50, 1.0)


def _graph(spark: SparkSession, sf: str, name: str) -> TemporalGraph:
    edges = synthetic_edges(spark, 200, 100_000, sigma=1.5, burst=0.6) if name == "synthetic" else load_graph(spark, sf, name)
    return TemporalGraph(settle(edges))


def dataset_statistics(spark, sf):
    for name in TABLES:
        yield {"graph": name} | metrics.graph_stats(load_graph(spark, sf, name)).head().asDict()


def all_algorithms(spark, sf, sources: int = 100, runs: int = 3):
    """Nine algorithms on every graph, window from the 95th percentile of starts on; 100 sources in one job.

    Betweenness sums over the same sources (its states are sources times window edges) and over
    edges of positive duration, as its path counts need.
    """
    for name in TABLES:
        g = _graph(spark, sf, name)
        w, s = window_percentile(g.edges), top_sources(g.edges, sources)
        loops = TemporalGraph(settle(g.edges.where("src <> dst and t_end > t_start")))
        jobs = {
            "earliest_arrival": lambda: paths.earliest_arrival(g, s, w),
            "latest_departure": lambda: paths.latest_departure(g, s, w),
            "fastest": lambda: paths.fastest(g, s, w),
            "shortest_duration": lambda: paths.shortest_duration(g, s, w),
            "bfs": lambda: paths.temporal_bfs(g, s, w),
            "components": lambda: components.connected_components(g, w),
            "coreness": lambda: structure.coreness(g, w),
            "pagerank_100": lambda: structure.pagerank(g, w, max_iter=100),
            "betweenness": lambda: structure.betweenness(loops, w, paths.source_frame(spark, s)),
        }
        for algorithm, job in jobs.items():
            yield {"graph": name, "algorithm": algorithm, "seconds": round(time_runs(job, runs)["mean_s"], 3)}


def threads(spark, sf, cores: tuple[int, ...] = (1, 2, 4)):
    """Minimal paths against the number of cores."""
    yield from thread_sweep(["m01_ea_trade_strict", "m02_ld_trade", "m03_fastest_trade", "m04_short_trade"], list(cores), sf)


def window_sizes(spark, sf, cutoff: int = 1000, runs: int = 2):
    """Access modes against window size, minimal paths of 100 sources to the fixpoint: edges examined, and time relative to scan-only."""
    for name in ("nations", "hub", "synthetic"):
        g = _graph(spark, sf, name)
        plan = access.plan_access(g, cutoff, directions=("out", "in"))
        s = top_sources(g.edges, 100)
        for share in SHARES:
            w = window_recent(g.edges, share)
            work = metrics.work(g, plan, w).agg(F.sum("k").alias("k"), F.sum("m").alias("m"), F.sum("index_examined").alias("i")).head()
            for algorithm in (paths.earliest_arrival, paths.latest_departure):
                times = {m: time_runs(lambda m=m: algorithm(g, s, w, access=m, plan=plan), runs)["mean_s"] for m in ("scan", "index", "auto")}
                yield {"graph": name, "algorithm": algorithm.__name__, "share": share, "beta": round(work.k / work.m, 4), "index_examined_share": round(work.i / work.m, 4), "scan_seconds": round(times["scan"], 3)} | {f"{k}_relative": round(v, 3) for k, v in normalized(times).items()}


def index_micro(spark, sf, sizes: tuple[int, ...] = (10_000, 100_000, 1_000_000)):
    """One vertex: time and edges examined of a single index query against size and window."""
    for m in sizes:
        edges = settle(synthetic_edges(spark, 2, m, sigma=0.1).withColumn("src", F.lit(0).cast("long")))
        ix = index.build_index(edges, 1)
        for share in (0.01, 0.05, 0.1, 0.2):
            w = window_recent(edges, share)
            asked = settle(metrics.asked_over(ix.catalog, w))
            bounds = index.ThreeSided(F.col("a"), F.col("a"), F.col("b"))
            row = index.nodes_read(ix, asked, bounds).head()
            yield {"edges": m, "share": share, "nodes": row.nodes, "examined": row.examined, "seconds": round(time_runs(lambda: index.query_index(ix, asked, bounds), 3)["mean_s"], 4)}


def decision_accuracy(spark, sf, cutoffs: tuple[int, ...] = (1000, 2000, 4000, 8000)):
    """Accuracy of the access choice against cutoff and window, theta one fifth."""
    for name in ("nations", "synthetic"):
        g = _graph(spark, sf, name)
        for cutoff in cutoffs:
            plan = access.plan_access(g, cutoff)
            for share in SHARES[:-2]:
                row = metrics.decision_accuracy(g, plan, window_recent(g.edges, share)).head()
                yield {"graph": name, "cutoff": cutoff, "share": share, "vertices": row.tp + row.tn + row.fp + row.fn, "accuracy": row.accuracy}


def against_messages(spark, sf):
    """Edges looked at by supersteps that send along all edges, against the window's own."""
    for name in ("trade", "relay"):
        g = _graph(spark, sf, name)
        w, s = window_percentile(g.edges), top_sources(g.edges, 10)
        _, messages = baselines.message_passing_arrival(g, s, w)
        sent = messages.agg(F.sum("messages")).head()[0]
        ours = time_runs(lambda: paths.earliest_arrival(g, s, w), 2)["mean_s"]
        theirs = time_runs(lambda: baselines.message_passing_arrival(g, s, w)[0], 2)["mean_s"]
        yield {"graph": name, "messages": sent, "window_edges": g.restrict(w).edges.count(), "seconds": round(ours, 3), "messages_seconds": round(theirs, 3)}


def against_preprocessing(spark, sf):
    """The time-expanded graph's size and time, and one sequential pass, against the engine."""
    for name in ("trade", "relay"):
        g = _graph(spark, sf, name)
        w, s = window_percentile(g.edges), top_sources(g.edges, 100)
        nodes, arcs = baselines.time_expanded(g, w)
        inside = g.restrict(w)
        n, m = inside.vertices.size(), inside.edges.count()
        jobs = {"engine": lambda: paths.earliest_arrival(g, s, w), "expanded": lambda: baselines.time_expanded_arrival(g, s, w), "one_pass": lambda: baselines.one_pass_arrival(g, s, w)}
        yield {"graph": name, "blow_up": round((nodes.count() + arcs.count()) / (n + m), 2)} | {f"{k}_seconds": round(time_runs(j, 2)["mean_s"], 3) for k, j in jobs.items()}


def weak_scaling(spark, sf, sizes: tuple[int, ...] = (10_000, 100_000, 1_000_000)):
    """Earliest arrival as the synthetic graph grows."""
    for m in sizes:
        g = TemporalGraph(settle(synthetic_edges(spark, m // 100, m, sigma=1.5)))
        w, s = window_percentile(g.edges), top_sources(g.edges, 100)
        yield {"edges": m, "seconds": round(time_runs(lambda: paths.earliest_arrival(g, s, w), 2)["mean_s"], 3)}


EXPERIMENTS = {
    "statistics": dataset_statistics, "algorithms": all_algorithms, "threads": threads, "windows": window_sizes, "index": index_micro,
    "accuracy": decision_accuracy, "messages": against_messages, "preprocessing": against_preprocessing, "scaling": weak_scaling,
}


def main() -> None:
    p = argparse.ArgumentParser(description=__doc__)
    p.add_argument("name", choices=EXPERIMENTS)
    p.add_argument("--sf", default="/root/testdata/sf0.01")
    p.add_argument("--cores", type=int, default=8)
    a = p.parse_args()
    spark = local_session(a.cores, a.cores)
    spark.sparkContext.setLogLevel("ERROR")
    for row in EXPERIMENTS[a.name](spark, a.sf):
        print(json.dumps(row), flush=True)


if __name__ == "__main__":
    main()
