"""Index invariants, queries against filters, estimates against counts, and the access choice."""

import random

import pytest
from pyspark.sql import functions as F

from spanwalk.functions.predicates import Ordering, Window
from spanwalk.operators import access, metrics, paths
from spanwalk.operators.graph import TemporalGraph
from spanwalk.plans import histogram, index, layout
from spanwalk.sources.graphs import edges_frame


def some_edges(seed=1, vertices=5, m=900):
    r = random.Random(seed)
    out = []
    for _ in range(m):
        v = min(r.randrange(vertices), r.randrange(vertices))
        s = r.choice([r.randint(0, 1000), r.randint(0, 40), 7])
        out.append((v, r.randrange(vertices), s, s + r.choice([0, r.randint(0, 60)])))
    return out


@pytest.fixture(scope="module")
def edges(spark):
    return edges_frame(spark, some_edges()).cache()


@pytest.mark.parametrize("axis,mode,orientation", [(a, m, o) for a in ("t_start", "t_end") for m in ("min", "max") for o in ("out", "in")])
def test_query_is_the_filter(spark, edges, axis, mode, orientation):
    ix = index.build_index(edges, 60, axis, mode, 8, orientation, shard_rows=10**6 if mode == "min" else 150)
    tree = ix.tree_axis
    own, other = ("src", "dst") if orientation == "out" else ("dst", "src")
    for bound, lo, hi in ((30, 0, 500), (500, 100, 700), (-5, 0, 10**6), (10**6, 0, 10**6), (7, 7, 7)):
        got = sorted(map(tuple, index.query_index(ix, ix.catalog.select("v"), index.ThreeSided(F.lit(bound), F.lit(lo), F.lit(hi))).select("v", "nbr", "t_start", "t_end").collect()))
        rule = F.col(axis) >= bound if mode == "max" else F.col(axis) <= bound
        indexed = [r.v for r in ix.catalog.collect()]
        want = sorted(map(tuple, edges.where(F.col(own).isin(indexed) & rule & F.col(tree).between(lo, hi)).select(F.col(own), F.col(other), "t_start", "t_end").collect()))
        assert got == want


def test_invariants(spark, edges):
    ix = index.build_index(edges, 60, "t_start", "max", 8)
    rows = {(r.v, r.shard, r.node): r for r in ix.nodes.collect()}
    assert sum(r.n for r in rows.values()) == ix.catalog.agg(F.sum("m")).head()[0]
    for (v, shard, node), r in rows.items():
        assert r.n == len(r.edges)
        if node > 1:
            parent = rows[v, shard, node // 2]
            assert r.heap_best <= parent.heap_worst and parent.n >= 8
        sibling = rows.get((v, shard, node + 1))
        if node > 1 and node % 2 == 0 and sibling:
            assert r.tree_hi <= sibling.tree_hi
    asked = metrics.asked_over(ix.catalog, Window(20, 400))
    bounds = index.ThreeSided(F.col("a"), F.col("a"), F.col("b"))
    flat = {(r.v, r.nodes) for r in index.nodes_read(ix, asked, bounds).collect()}
    down = {(r.v, r.n) for r in index.descend(ix, asked, bounds).groupBy("v").agg(F.count("*").alias("n")).collect()}
    assert flat == down


def test_save_and_load(spark, edges, tmp_path):
    ix = index.build_index(edges, 60)
    ix.save(str(tmp_path / "ix"))
    again = index.load_index(spark, str(tmp_path / "ix"), "out", "t_start", "max")
    assert again.nodes.agg(F.sum("n")).head()[0] == ix.nodes.agg(F.sum("n")).head()[0]


def test_estimates_bracket_the_count(spark, edges):
    g = TemporalGraph(edges)
    catalog = index.select_indexed_vertices(edges, 60)
    h = histogram.build_histogram(edges, catalog, 10)
    assert h.cells.agg(F.sum("n")).head()[0] == catalog.agg(F.sum("m")).head()[0]
    for w in (Window(0, 2000), Window(100, 600), Window(7, 7), Window(900, 950), Window(5000, 6000)):
        asked = metrics.asked_over(catalog, w)
        count = {r.v: r.k for r in access.true_matches(edges, asked).collect()}
        low, mid, high = ({r.v: r.k_hat for r in histogram.estimate(h, asked, c).collect()} for c in ("none", "uniform", "full"))
        for v, k in count.items():
            assert low[v] - 1e-6 <= k <= high[v] + 1e-6 and low[v] - 1e-6 <= mid[v] <= high[v] + 1e-6
    assert {r.v: r.m for r in metrics.selectivity(g, catalog, Window(0, 2000)).collect()}
    whole = {r.v: r.whole for r in histogram.prefix_counts(h).groupBy("v").agg(F.max("upto").alias("whole")).collect()}
    assert whole == {r.v: r.m for r in catalog.collect()}


def test_point_mass(spark):
    """Half of the edges share the last start: the histogram may miss, the bounds still hold."""
    rows = [(0, 1, 1000, 1001)] * 500 + [(0, 1, k * 2, k * 2 + 1) for k in range(500)]
    edges = edges_frame(spark, rows)
    h = histogram.build_histogram(edges, index.select_indexed_vertices(edges, 100))
    asked = metrics.asked_over(index.select_indexed_vertices(edges, 100), Window(999, 1001))
    low, high = (histogram.estimate(h, asked, c).head().k_hat for c in ("none", "full"))
    assert low <= 500 <= high


@pytest.mark.parametrize("kind", [Ordering.SUCCEEDS, Ordering.STRICTLY_SUCCEEDS])
def test_all_accesses_agree(spark, edges, kind):
    g, w = TemporalGraph(edges), Window(100, 900)
    plan = access.plan_access(g, 60, bins=10, block_rows=8, directions=("out", "in"))
    want = sorted(map(tuple, paths.earliest_arrival(g, [0, 1], w, kind).collect()))
    for how in access.MODES:
        assert sorted(map(tuple, paths.earliest_arrival(g, [0, 1], w, kind, access=how, plan=plan).collect())) == want


@pytest.mark.parametrize("method", [paths.latest_departure, paths.fastest, paths.shortest_duration, paths.temporal_bfs, paths.reachable])
def test_all_paths_take_the_index(spark, edges, method):
    g, w = TemporalGraph(edges), Window(700, 900)
    plan = access.plan_access(g, 60, theta=0.25, bins=10, block_rows=8, directions=("out", "in"))
    want = sorted(map(tuple, method(g, [0, 1], w).collect()))
    for how in ("index", "auto", "global_range"):
        assert sorted(map(tuple, method(g, [0, 1], w, access=how, plan=plan).collect())) == want


def test_costs_decide_instead_of_the_threshold(spark, edges):
    g, w = TemporalGraph(edges), Window(300, 1100)
    free, dear = (access.plan_access(g, 60, mode="cost", c=c) for c in (0.0, 1e9))
    assert {r.access for r in access.explain_access(g, free, w).where("m is not null").collect()} == {"index"}
    assert {r.access for r in access.explain_access(g, dear, w).collect()} == {"scan"}
    assert sorted(map(tuple, paths.earliest_arrival(g, [0], w, access="auto", plan=free).collect())) == sorted(map(tuple, paths.earliest_arrival(g, [0], w, access="auto", plan=dear).collect()))


def test_bounds_reach_the_nodes(spark, edges):
    """Headers are filtered in the file scan, and only nodes that may hold results are unpacked."""
    ix = index.build_index(edges, 60, block_rows=8)
    spark.conf.set("spark.sql.maxMetadataStringLength", "1000")
    found = index.query_window(ix, ix.catalog.select("v"), 900, 2000)
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert "GreaterThanOrEqual(heap_best,900)" in plan and "GreaterThanOrEqual(tree_hi,900)" in plan and "LessThanOrEqual(tree_lo,2000)" in plan
    asked = ix.catalog.select("v").withColumns({"a": F.lit(900).cast("long"), "b": F.lit(2000).cast("long")})
    opened = index.nodes_read(ix, asked, index.ThreeSided(F.col("a"), F.col("a"), F.col("b"))).agg(F.sum("nodes")).head()[0]
    assert opened < 0.5 * ix.nodes.count()


def test_choice_at_worked_values(spark):
    """theta .3 and beta .2 choose the index; beta at theta does too; costs of 8 edges and 3 matches are 6 and 8."""
    rows = [(0, 1, t, t) for t in range(10)]
    edges = edges_frame(spark, rows)
    plan = access.plan_access(TemporalGraph(edges), 5, theta=0.3)
    choose = lambda a: access.choose_access(spark.createDataFrame([(0, a, 9)], "v long, a long, b long"), plan, "oracle", edges).head().access
    assert choose(8) == "index" and choose(7) == "index" and choose(6) == "scan"
    one = spark.range(1).select(access.index_cost(F.lit(8), F.lit(3)).alias("t"), access.scan_cost(F.lit(8)).alias("s")).head()
    assert (one.t, one.s) == (6.0, 8.0)


def test_accuracy_and_work(spark, edges):
    g = TemporalGraph(edges)
    plan = access.plan_access(g, 60, block_rows=8)
    row = metrics.decision_accuracy(g, plan, Window(0, 2000)).head()
    assert row.tp + row.tn + row.fp + row.fn == plan.index.catalog.count() and row.accuracy == 1.0
    work = metrics.work(g, plan, Window(900, 2000)).collect()
    assert all(r.k <= r.index_examined <= r.scan_examined for r in work)
    c, c_scan, theta = access.calibrate(g, plan, [Window(900, 2000), Window(500, 2000)])
    assert c >= 0.5 and c_scan == 1.0 and 0 <= theta <= 2
    assert metrics.decision_accuracy(g, access.plan_access(g, 10**9), Window(0, 1)).head().accuracy is None


def test_layout(spark, edges):
    whole, blocks = layout.adjacency_blocks(edges, block_rows=50), layout.adjacency_blocks(edges, block_rows=50, shard_rows=200)
    assert blocks.agg(F.max("n")).head()[0] <= 50 and blocks.agg(F.max("shard")).head()[0] > 0 == whole.agg(F.max("shard")).head()[0]
    assert sorted(map(tuple, layout.unpack_blocks(blocks).select("src", "dst", "t_start", "t_end").collect())) == sorted(map(tuple, edges.select("src", "dst", "t_start", "t_end").collect()))
    offsets = sorted((r.v, r.first, r.m) for r in layout.csr_offsets(edges, chunk=2).collect())
    at = 0
    for _, first, m in offsets:
        assert first == at
        at += m


def test_choices_take_no_index(edges, monkeypatch):
    """Decisions at several cutoffs come from one histogram, without an index, and are those of full plans."""
    g, w = TemporalGraph(edges), Window(10, 600)
    want = {c: metrics.decision_accuracy(g, access.plan_access(g, c), w).head() for c in (60, 200)}
    monkeypatch.setattr(index, "build_index", None)
    plans = access.plan_choices(g, [60, 200])
    assert {c: metrics.decision_accuracy(g, p, w).head() for c, p in plans.items()} == want
    assert want[60].tn + want[60].tp > want[200].tn + want[200].tp > 0
    counts = {r.v: r.k for r in access.window_matches(edges, plans[60].index.catalog, w).collect()}
    assert counts == {v: sum(e[0] == v and e[2] >= 10 and e[3] <= 600 for e in some_edges()) for v in counts}
