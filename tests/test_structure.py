"""Components, cores, ranks, patterns, sets and statistics against plain Python."""

import random

from pyspark.sql import functions as F

from spanwalk.functions.predicates import Ordering, Window
from spanwalk.functions.statistics import exact_percentile, window_recent
from spanwalk.operators import components, metrics, patterns, structure
from spanwalk.operators.graph import TemporalEdgeSet, TemporalGraph, VertexSet, top_sources, with_edge_ids
from spanwalk.operators.temporal_joins import asof_join, interval_join
from spanwalk.plans.fixpoint import pareto
from spanwalk.sources.graphs import TINY, edges_frame, tiny
from spanwalk.sources.synthetic import synthetic_edges


def plain_components(pairs):
    root = {}

    def find(x):
        while root.setdefault(x, x) != x:
            x = root[x]
        return x

    for a, b in pairs:
        x, y = find(a), find(b)
        root[max(x, y)] = min(x, y)
    return {v: find(v) for v in list(root)}


def test_components(spark):
    r = random.Random(4)
    rows = [(r.randrange(60), r.randrange(60), k, k) for k in range(45)] + [(100 + k, 101 + k, 1, 2) for k in range(40)]
    g, w = TemporalGraph(edges_frame(spark, rows)), Window(0, 100)
    want = plain_components([e[:2] for e in rows])
    for method in ("star", "propagate"):
        assert {x.v: x.component for x in components.connected_components(g, w, method=method).collect()} == want
    alone = {x.v: x.component for x in components.connected_components(g, Window(0, 0), include_isolated=True).collect()}
    assert set(alone) == set(want)


def test_cores(spark):
    r = random.Random(5)
    rows = [(r.randrange(12), r.randrange(12), 1, 2) for _ in range(40)]
    g, w = TemporalGraph(edges_frame(spark, rows)), Window(0, 9)
    live, core, k = {v for e in rows for v in e[:2]}, {}, 1
    while live:
        while True:
            deg = {v: sum((e[0] == v) + (e[1] == v) for e in rows if e[0] in live and e[1] in live) for v in live}
            weak = {v for v in live if deg[v] < k}
            if not weak:
                break
            for v in weak:
                core[v] = k - 1
            live -= weak
        k += 1
    assert {x.v: x.coreness for x in structure.coreness(g, w).collect()} == core
    for k in (2, 5):
        assert {x.v for x in structure.k_core(g, w, k).collect()} == {v for v, c in core.items() if c >= k}


def test_pagerank(spark):
    g, w = TemporalGraph(tiny(spark)), Window(0, 14)
    rank = {r.v: r.rank for r in structure.pagerank(g, w, max_iter=30, tol=1e-12).collect()}
    assert abs(sum(rank.values()) - 1) < 1e-9
    n, own = 7, {v: 1 / 7 for v in range(7)}
    for _ in range(30):
        new = {v: 0.15 / n for v in range(7)}
        for a, b, *_ in TINY:
            new[b] += 0.85 * own[a] / sum(e[0] == a for e in TINY)
        own = new
    assert all(abs(rank[v] - own[v]) < 1e-9 for v in own)


def test_two_hop_and_formula(spark):
    g, w = TemporalGraph(tiny(spark)), Window(0, 14)
    assert tuple(patterns.two_hop_counts(g, w).head()) == (28, 17, 11, 19, 2)
    # start(A) <= end(B) and end(A) <= start(B) says no more than end(A) <= start(B)
    pairs = patterns.two_hop_paths(g, w)
    assert pairs.where(((F.col("s0") <= F.col("e1")) & (F.col("e0") <= F.col("s1"))) != F.col("succeeds")).count() == 0


def test_patterns(spark):
    g, w = TemporalGraph(tiny(spark)), Window(0, 14)
    got = {(r.v0, r.v1, r.v2, r.s0) for r in patterns.temporal_cycles(g, 3, 20, w, Ordering.SUCCEEDS).collect()}
    want = set()
    for a in TINY:
        for b in TINY:
            for c in TINY:
                if a[1] == b[0] and b[1] == c[0] and c[1] == a[0] and a[3] <= b[2] and b[3] <= c[2] and len({a[0], b[0], c[0]}) == 3 and c[3] - a[2] <= 20:
                    want.add((a[0], b[0], c[0], a[2]))
    assert got == want


def test_mutual_reach_and_slices(spark):
    g, w = TemporalGraph(edges_frame(spark, [(0, 1, 1, 2), (1, 0, 3, 4), (1, 2, 3, 4), (3, 4, 11, 12)])), Window(0, 20)
    assert {tuple(r) for r in components.mutual_reachability(g, w).collect()} == {(0, 1)}
    assert {tuple(r) for r in components.reachability_components(g, w).collect()} == {(0, 0), (1, 0)}
    slices = {(r.slice, r.v, r.component) for r in components.components_over_time(g, w, 10).collect()}
    assert slices == {(0, 0, 0), (0, 1, 0), (0, 2, 0), (1, 3, 3), (1, 4, 3)}


def test_sets_and_ids(spark):
    a, b = VertexSet(spark.createDataFrame([(1,), (2,)], "v long")), VertexSet(spark.createDataFrame([(2,), (3,)], "v long"))
    assert (a.union(b).size(), a.intersect(b).size(), a.minus(b).size()) == (3, 1, 1)
    twice = edges_frame(spark, [(0, 1, 1, 2), (0, 1, 1, 2), (0, 1, 1, 3)])
    assert with_edge_ids(twice).select("edge_id").distinct().count() == 3
    assert TemporalEdgeSet(twice).minus(TemporalEdgeSet(twice.limit(1))).size() == 2


def test_statistics(spark):
    r = random.Random(2)
    values = sorted(r.choice([r.randint(0, 50), r.randint(0, 10**6), 13]) for _ in range(5000))
    df = spark.createDataFrame([(v,) for v in values], "x long")
    for p in (0.001, 0.2, 0.5, 0.95, 1.0):
        want = values[max(0, -(-int(round(p * 5000 * 1000)) // 1000) - 1)]
        assert exact_percentile(df, "x", p) == want == exact_percentile(df, "x", p, most=100)
    assert exact_percentile(df.limit(0), "x", 0.5) is None
    w = window_recent(edges_frame(spark, [(0, 1, t, t + 5) for t in range(100)]), 0.05)
    assert (w.start, w.end) == (94, 104)
    row = metrics.graph_stats(tiny(spark)).head()
    assert (row.n, row.m, row.max_out) == (7, 14, 3) and top_sources(tiny(spark), 1) == [0]


def test_pareto(spark):
    df = spark.createDataFrame([(1, 1, 1, 5), (1, 1, 2, 4), (1, 1, 2, 6), (1, 1, 3, 4)], "source long, v long, x long, y long")
    assert {(r.x, r.y) for r in pareto(df, ["source", "v"]).collect()} == {(1, 5), (2, 4)}


def test_time_joins(spark):
    left = spark.createDataFrame([(1, 10), (1, 5), (2, 7)], "k long, t long")
    right = spark.createDataFrame([(1, 5, 50), (1, 9, 90), (1, 10, 100)], "k long, t long, x long")
    assert {(r.k, r.t, r.prev_x) for r in asof_join(left, right, ["k"], "t", ["x"]).collect()} == {(1, 10, 90), (1, 5, None), (2, 7, None)}
    assert {(r.k, r.t, r.prev_x) for r in asof_join(left, right, ["k"], "t", ["x"], strict=False).collect()} == {(1, 10, 100), (1, 5, 50), (2, 7, None)}
    a = [(k, k * 3, k * 3 + k % 7) for k in range(40)]
    b = [(k, k * 4, k * 4 + k % 5) for k in range(30)]
    got = interval_join(spark.createDataFrame(a, "i long, a0 long, a1 long"), spark.createDataFrame(b, "j long, b0 long, b1 long"), 4, "a0", "a1", "b0", "b1")
    assert sorted((r.i, r.j) for r in got.collect()) == sorted((x[0], y[0]) for x in a for y in b if x[1] <= y[2] and y[1] <= x[2])


def test_synthetic_is_repeatable(spark):
    one = synthetic_edges(spark, 50, 2000, sigma=1.2, burst=0.5)
    assert one.count() == 2000
    key = F.sum(F.xxhash64("src", "dst", "t_start", "t_end").cast("decimal(38,0)"))
    assert one.agg(key).head()[0] == synthetic_edges(spark, 50, 2000, sigma=1.2, burst=0.5).repartition(3).agg(key).head()[0]
    degrees = sorted((r["count"] for r in one.groupBy("src").count().collect()), reverse=True)
    assert degrees[0] > 4 * degrees[len(degrees) // 2]


def test_coreness_along_a_path(spark, monkeypatch):
    """Values fall one edge a round along a path: one task finishes what some rounds leave; rounds alone agree."""
    rows = [(k, k + 1, k, k + 1) for k in range(60)] + [(0, 1, 5, 6), (5, 5, 1, 2), (7, 9, 3, 4)]
    rounds, keep = [], structure.settle_laid
    monkeypatch.setattr(structure, "settle_laid", lambda df: rounds.append(1) or keep(df))
    w = Window(0, 300)
    got = {x.v: x.coreness for x in structure.coreness(TemporalGraph(edges_frame(spark, rows)), w).collect()}
    assert got == {v: 2 if v <= 9 else 1 for v in range(61)} and len(rounds) < 20
    few = TemporalGraph(edges_frame(spark, [e for e in rows if e[1] <= 12]))
    assert {x.v: x.coreness for x in structure.coreness(few, w, task_pairs=0).collect()} == {v: 2 if v <= 9 else 1 for v in range(13)}
