"""Path methods against enumerated walks; many random graphs share one run on disjoint vertex ranges."""

import pytest
from pyspark.sql import functions as F

from spanwalk.functions.predicates import Ordering, Window
from spanwalk.operators import baselines, paths, structure
from spanwalk.operators.graph import InvalidEdges, TemporalGraph
from spanwalk.plans import fixpoint
from spanwalk.sources.graphs import TINY, edges_frame, tiny

from . import brute

SEEDS, OFFSET, WINDOW = range(24), 100, Window(1, 10)


def both(spark, zero=True):
    graphs = {k: brute.random_edges(k, zero) for k in SEEDS}
    rows = [(k * OFFSET + e[0], k * OFFSET + e[1], *e[2:]) for k, g in graphs.items() for e in g]
    return graphs, TemporalGraph(edges_frame(spark, rows).cache())


def expected(graphs, kind, value):
    return {(k * OFFSET, k * OFFSET + v): row[value] for k, g in graphs.items() for v, row in brute.answers(g, 0, WINDOW.start, WINDOW.end, kind).items()}


def got(df, value):
    return {(r["source"], r["v"]): r[value] for r in df.collect() if r["source"] != r["v"]}


@pytest.mark.parametrize("kind", list(Ordering))
def test_arrival_and_hops(spark, kind):
    graphs, g = both(spark)
    sources = [k * OFFSET for k in SEEDS]
    assert got(paths.earliest_arrival(g, sources, WINDOW, kind), "arrival") == expected(graphs, kind.value, 0)
    assert got(paths.temporal_bfs(g, sources, WINDOW, kind), "hops") == expected(graphs, kind.value, 4)
    assert got(paths.arrival_by_edges(g, sources, WINDOW, kind), "arrival") == expected(graphs, kind.value, 0)


@pytest.mark.parametrize("kind", [Ordering.SUCCEEDS, Ordering.STRICTLY_SUCCEEDS])
def test_minimal_paths(spark, kind):
    graphs, g = both(spark)
    sources = [k * OFFSET for k in SEEDS]
    fast = paths.fastest(g, sources, WINDOW, kind)
    assert got(fast, "duration") == expected(graphs, kind.value, 1)
    assert {tuple(r) for r in fast.collect()} == {tuple(r) for r in paths.fastest(g, sources, WINDOW, kind, "per_departure").collect()}
    assert got(paths.shortest_duration(g, sources, WINDOW, kind), "cost") == expected(graphs, kind.value, 2)
    assert got(paths.shortest_duration(g, sources, WINDOW, kind, cost="weight"), "cost") == expected(graphs, kind.value, 3)
    late = {(r.target, r.v): r.departure for r in paths.latest_departure(g, sources, WINDOW, kind).collect() if r.target != r.v}
    assert late == {(k * OFFSET, k * OFFSET + v): d for k, e in graphs.items() for v, d in brute.departures(e, 0, WINDOW.start, WINDOW.end, kind.value).items()}


@pytest.mark.parametrize("kind", [Ordering.SUCCEEDS, Ordering.STRICTLY_SUCCEEDS])
def test_path_output_is_valid(spark, kind):
    graphs, g = both(spark)
    sources = [k * OFFSET for k in SEEDS]
    rule, want = brute.RULES[kind.value], expected(graphs, kind.value, 0)
    found = {}
    for r in paths.arrival_paths(g, sources, WINDOW, kind).collect():
        steps = [(e.src, e.dst, e.t_start, e.t_end) for e in r.path]
        assert steps[0][0] == r.source and steps[-1][1] == r.v
        assert all(a[1] == b[0] and rule(a, b) for a, b in zip(steps, steps[1:]))
        found[r.source, r.v] = steps[-1][3]
    assert found == want


@pytest.mark.parametrize("kind", [Ordering.SUCCEEDS, Ordering.STRICTLY_SUCCEEDS])
def test_baselines_agree(spark, kind):
    graphs, g = both(spark)
    sources, want = [k * OFFSET for k in SEEDS], expected(graphs, kind.value, 0)
    assert got(baselines.message_passing_arrival(g, sources, WINDOW, kind)[0], "arrival") == want
    assert got(baselines.time_expanded_arrival(g, sources, WINDOW, kind), "arrival") == want
    assert got(baselines.one_pass_arrival(g, sources, WINDOW, kind), "arrival") == want


def test_betweenness(spark):
    graphs, g = both(spark, zero=False)
    score = {r.v: r.score for r in structure.betweenness(g, WINDOW).collect()}
    want = {k * OFFSET + v: s for k, e in graphs.items() for v, s in brute.betweenness(e, WINDOW.start, WINDOW.end, "strictly_succeeds").items()}
    assert score.keys() == want.keys() and all(abs(score[v] - want[v]) < 1e-9 for v in want)
    with pytest.raises(ValueError):
        structure.betweenness(TemporalGraph(tiny(spark)), Window(0, 14))


def test_worked_example(spark):
    g, w = TemporalGraph(tiny(spark)), Window(0, 14)
    cell = lambda kind, target: [got(f(g, [0], w, kind), c).get((0, target)) for f, c in ((paths.earliest_arrival, "arrival"), (paths.fastest, "duration"), (paths.shortest_duration, "cost"), (paths.temporal_bfs, "hops"))]
    assert cell(Ordering.STRICTLY_SUCCEEDS, 6) == [14, 9, 3, 2]
    assert cell(Ordering.SUCCEEDS, 5) == [10, 9, 5, 3]
    assert got(paths.earliest_arrival(g, [0], Window(3, 11), Ordering.SUCCEEDS), "arrival") == {(0, 1): 6}
    source = [r.arrival for r in paths.earliest_arrival(g, [0], w).collect() if r.v == 0]
    assert source == [0]


def test_reachability_and_exposure(spark):
    g, w = TemporalGraph(tiny(spark)), Window(0, 14)
    assert {r.v for r in paths.reachable(g, [0], w, max_hops=1).collect()} == {0, 1, 2}
    assert {r.v for r in paths.reachable(g, [0], w, targets=[1, 6]).collect()} == {1, 6}
    assert {(r.v, r.exposed) for r in paths.exposure(g, [0], w).collect()} == {(0, 0), (1, 3), (2, 5), (3, 6), (4, 6), (5, 11), (6, 14)}
    short = {r.v for r in paths.exposure(g, [0], w, infectious=3).collect()}
    seen, todo = {(0, -1)}, [(0, -1)]
    while todo:
        v, at = todo.pop()
        for e in TINY:
            if e[0] == v and at < e[2] <= max(at, 0) + 3 and (e[1], e[3]) not in seen:
                seen.add((e[1], e[3]))
                todo.append((e[1], e[3]))
    assert short == {v for v, _ in seen}


def test_edge_cases(spark):
    w = Window(0, 10)
    empty = TemporalGraph(spark.createDataFrame([], tiny(spark).schema))
    assert [tuple(r) for r in paths.earliest_arrival(empty, [5], w).collect()] == [(5, 5, 0)]
    loop = TemporalGraph(edges_frame(spark, [(1, 1, 2, 3), (1, 2, 3, 3), (1, 2, 3, 3)]))
    assert got(paths.earliest_arrival(loop, [1], w), "arrival") == {(1, 2): 3}
    big = 2**62 // 100
    far = TemporalGraph(edges_frame(spark, [(0, 1, big, big + 1), (1, 2, big + 2, big + 3)]))
    assert got(paths.earliest_arrival(far, [0], Window(big, big + 9)), "arrival") == {(0, 1): big + 1, (0, 2): big + 3}
    for bad in ([(0, 1, 5, 4)], [(0, 1, 1, 2, -1.0)]):
        with pytest.raises(InvalidEdges):
            TemporalGraph(edges_frame(spark, bad)).checked()
    assert TemporalGraph(edges_frame(spark, TINY)).checked().edges.where(F.col("src") == 0).count() == 3
    with pytest.raises(ValueError):
        paths.latest_departure(loop, [1], w, Ordering.OVERLAPS)


def test_undirected(spark):
    g = TemporalGraph(edges_frame(spark, [(1, 0, 1, 2), (2, 1, 3, 4)]), directed=False)
    assert got(paths.earliest_arrival(g, [0], Window(0, 9)), "arrival") == {(0, 1): 2, (0, 2): 4}


def test_expanded_search_along_a_chain(spark, monkeypatch):
    """150 touching edges, some of length zero, are hundreds of arcs deep: one task finishes what a dozen rounds leave; rounds alone agree."""
    rows = [(k, k + 1, k - k % 3, k + 1 - (k + 1) % 3) for k in range(150)] + [(0, 40, 500, 501), (200, 3, 30, 31), (300, 301, 9, 10)]
    g, w = TemporalGraph(edges_frame(spark, rows)), Window(0, 600)
    rounds, keep = [], fixpoint.settle
    monkeypatch.setattr(fixpoint, "settle", lambda df: rounds.append(1) or keep(df))
    found = baselines.time_expanded_arrival(g, [0, 200], w, Ordering.SUCCEEDS)
    best = {0: {}, 200: {}}
    for s, own in best.items():
        own[s], again = 0, True
        while again:
            again = False
            for u, v, x, y in rows:
                if own.get(u, 999) <= x and y < own.get(v, 999):
                    own[v] = y
                    again = True
    assert {(r.source, r.v): r.arrival for r in found.collect()} == {(s, v): t for s, own in best.items() for v, t in own.items()}
    assert set(range(151)) <= best[0].keys() and len(rounds) < 20
    short = TemporalGraph(edges_frame(spark, rows[:9]))
    assert {r.v: r.arrival for r in baselines.time_expanded_arrival(short, [0], w, Ordering.SUCCEEDS, task_arcs=0).collect()} == {k: k - k % 3 for k in range(10)}
