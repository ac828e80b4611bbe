"""Graph queries on the given tables with their DuckDB twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.predicates import Ordering, Window
from ..functions.statistics import window_percentile, window_recent
from ..operators import access, baselines, components, metrics, paths, patterns, structure
from ..operators.edgemap import expand_counted, window_edges
from ..operators.graph import TemporalEdgeSet, TemporalGraph, VertexSet, edge_map, edge_map_static, top_sources, vertex_map, with_edge_ids
from ..plans import histogram, index, layout
from ..session import settle, settle_columns
from ..sources.graphs import TABLES, graph_sql, load_graph
from ..sources.synthetic import synthetic_edges, with_uniform_end
from . import twins as t

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
TWINS: dict[str, str] = {}
STRICT, SUCCEEDS = Ordering.STRICTLY_SUCCEEDS, Ordering.SUCCEEDS


def query(name: str, twin: str | None = None) -> Callable[[Query], Query]:
    def keep(f: Query) -> Query:
        QUERIES[name] = f
        if twin is not None:
            TWINS[name] = twin
        return f

    return keep


def setting(spark: SparkSession, sf_dir: str, name: str, share: float = 0.05, sources: int = 1, where: str | None = None) -> tuple[TemporalGraph, Window, list[int]]:
    """A graph, its most recent window, and its sources of largest out-degree in the whole graph."""
    edges = load_graph(spark, sf_dir, name)
    edges = settle(edges if where is None else edges.where(where))
    return TemporalGraph(edges), window_percentile(edges, round(1 - share, 6)), top_sources(edges, sources)


# ---- graphs and their statistics ------------------------------------------------------------

for _name in TABLES:
    query(f"g_{_name}", f"SELECT src, dst, t_start, t_end, weight FROM ({graph_sql(_name, 'duckdb')}) AS g")(lambda spark, sf, name=_name: load_graph(spark, sf, name).select("src", "dst", "t_start", "t_end", "weight"))


def _stats_sql(name: str) -> str:
    return f"""SELECT '{name}' AS graph, n, m, max_out, max_in, m / n AS m_per_n, 2 * m / n AS degree_2m_per_n FROM
      (SELECT count(*) AS m FROM ({graph_sql(name, "duckdb")}) AS g), (SELECT count(*) AS n FROM (SELECT src FROM ({graph_sql(name, "duckdb")}) AS g UNION SELECT dst FROM ({graph_sql(name, "duckdb")}) AS g)),
      (SELECT max(c) AS max_out FROM (SELECT count(*) AS c FROM ({graph_sql(name, "duckdb")}) AS g GROUP BY src)), (SELECT max(c) AS max_in FROM (SELECT count(*) AS c FROM ({graph_sql(name, "duckdb")}) AS g GROUP BY dst))"""


@query("g_stats", " UNION ALL ".join(map(_stats_sql, TABLES)))
def g_stats(spark, sf):
    out = None
    for name in TABLES:
        row = metrics.graph_stats(load_graph(spark, sf, name)).select(F.lit(name).alias("graph"), "*")
        out = row if out is None else out.unionByName(row)
    return out


@query("g_synthetic")
def g_synthetic(spark, sf):
    """An edge for every event among its users, drawn anew."""
    e = spark.read.parquet(f"{sf}/events.parquet")
    return synthetic_edges(spark, e.select("user_id").where("user_id is not null").distinct(), e.select("event_id"), sigma=1.5, burst=0.3)


# ---- primitives -----------------------------------------------------------------------------

def _pairs_sql(name: str) -> str:
    rules = {"succeeds": "a.t_end <= b.t_start", "strictly_succeeds": "a.t_end < b.t_start", "overlaps": "a.t_start < b.t_start AND a.t_end < b.t_end", "overlaps_proper": "a.t_start < b.t_start AND a.t_end < b.t_end AND b.t_start < a.t_end"}
    sums = ", ".join(f"CAST(sum(CASE WHEN {r} THEN 1 ELSE 0 END) AS BIGINT) AS n_{k}" for k, r in rules.items())
    return f"WITH g AS ({graph_sql(name, 'duckdb')}) SELECT count(*) AS pairs, {sums} FROM g AS a JOIN g AS b ON a.dst = b.src"


for _name in ("relay", "basket"):
    query(f"p01_predicate_counts_{_name}", _pairs_sql(_name))(lambda spark, sf, name=_name: patterns.two_hop_counts(TemporalGraph(load_graph(spark, sf, name)), Window(-(2**62), 2**62)).withColumnsRenamed({k.value: f"n_{k.value}" for k in Ordering}))


@query("p02_vertex_set_ops", f"""WITH g AS ({graph_sql('relay', 'duckdb')}), a AS (SELECT DISTINCT src AS v FROM g WHERE weight > 150), b AS (SELECT DISTINCT dst AS v FROM g WHERE weight > 170)
  SELECT 'union' AS op, v FROM (SELECT v FROM a UNION SELECT v FROM b) UNION ALL SELECT 'intersect', v FROM (SELECT v FROM a INTERSECT SELECT v FROM b)
  UNION ALL SELECT 'minus', v FROM (SELECT v FROM a EXCEPT SELECT v FROM b) UNION ALL SELECT 'filter', v FROM a WHERE v % 2 = 0""")
def p02(spark, sf):
    g = load_graph(spark, sf, "relay")
    a, b = VertexSet.of(g.where("weight > 150"), "src"), VertexSet.of(g.where("weight > 170"), "dst")
    parts = {"union": a.union(b), "intersect": a.intersect(b), "minus": a.minus(b), "filter": a.filter(F.col("v") % 2 == 0)}
    out = None
    for op, vs in parts.items():
        row = vs.df.select(F.lit(op).alias("op"), "v")
        out = row if out is None else out.unionByName(row)
    return out


@query("p03_edge_set_ops", f"""WITH g AS ({graph_sql('relay', 'duckdb')}), a AS (SELECT src, dst, t_start, t_end FROM g WHERE weight > 120), b AS (SELECT src, dst, t_start, t_end FROM g WHERE weight < 180)
  SELECT 'intersect' AS op, count(*) AS n FROM (SELECT * FROM a INTERSECT ALL SELECT * FROM b) UNION ALL SELECT 'minus', count(*) FROM (SELECT * FROM a EXCEPT ALL SELECT * FROM b)
  UNION ALL SELECT 'union', count(*) FROM (SELECT * FROM a UNION ALL SELECT * FROM b)""")
def p03(spark, sf):
    g = load_graph(spark, sf, "relay")
    cols = ["src", "dst", "t_start", "t_end"]
    a, b = TemporalEdgeSet(g.where("weight > 120").select(cols)), TemporalEdgeSet(g.where("weight < 180").select(cols))
    out = None
    for op, es in {"intersect": a.intersect(b), "minus": a.minus(b), "union": a.union(b)}.items():
        row = es.df.agg(F.count("*").alias("n")).select(F.lit(op).alias("op"), "n")
        out = row if out is None else out.unionByName(row)
    return out


@query("p04_vertex_map", f"""WITH g AS ({graph_sql('relay', 'duckdb')}), d AS (SELECT src AS v, count(*) AS m FROM g GROUP BY src), u AS (SELECT DISTINCT dst AS v FROM g WHERE weight > 170)
  SELECT v, m + 1 AS m FROM d WHERE v IN (SELECT v FROM u) AND m + 1 > 60""")
def p04(spark, sf):
    g = load_graph(spark, sf, "relay")
    from ..operators.graph import degrees

    return vertex_map(VertexSet.of(g.where("weight > 170"), "dst"), degrees(g), F.col("m") > 60, {"m": F.col("m") + 1})


@query("p05_edge_map_static", f"WITH g AS ({graph_sql('trade', 'duckdb')}) SELECT src, dst, t_start, t_end FROM g WHERE src < 50 AND weight > 50000")
def p05(spark, sf):
    g = TemporalGraph(load_graph(spark, sf, "trade"))
    return edge_map_static(g, VertexSet(spark.range(50).select(F.col("id").alias("v"))), F.col("weight") > 50000).select("src", "dst", "t_start", "t_end")


@query("p06_edge_map_set", f"WITH g AS ({graph_sql('hub', 'duckdb')}) SELECT src, dst, t_start, t_end FROM g WHERE t_end - t_start > 3000000000")
def p06(spark, sf):
    return edge_map(TemporalEdgeSet(load_graph(spark, sf, "hub")), F.col("t_end") - F.col("t_start") > 3_000_000_000).df.select("src", "dst", "t_start", "t_end")


def _expand_once(kind: Ordering, direction: str):
    from ..operators.edgemap import expand_backward, expand_forward, window_edges

    def run(spark, sf):
        g, w, sources = setting(spark, sf, "nations", 0.05, 5)
        edges = window_edges(g.restrict(w).edges, direction)
        middle = (w.start + w.end) // 2
        frontier = paths._seeds(paths.source_frame(spark, sources), middle)
        hit = (expand_forward if direction == "out" else expand_backward)(frontier, edges, kind)
        return hit.groupBy("source", F.col("dst" if direction == "out" else "src").alias("v")).agg(F.count("*").alias("edges"), F.min("t_end").alias("first_end"), F.max("t_start").alias("last_start"))

    rule = {("out", STRICT): "t_start > mid", ("out", SUCCEEDS): "t_start >= mid", ("in", STRICT): "t_end < mid", ("in", SUCCEEDS): "t_end <= mid"}[direction, kind]
    own, other = ("src", "dst") if direction == "out" else ("dst", "src")
    query(f"p07_expand_{direction}_{kind.value}", f"""WITH {t.base('nations', 0.05, 5)}, m AS (SELECT (ta + tb) // 2 AS mid FROM w)
      SELECT source, {other} AS v, count(*) AS edges, min(t_end) AS first_end, max(t_start) AS last_start FROM s JOIN ew ON {own} = source, m WHERE {rule} GROUP BY source, {other}""")(run)


for _d in ("out", "in"):
    for _k in (STRICT, SUCCEEDS):
        _expand_once(_k, _d)


@query("p10_uniform_end", "SELECT event_id, epoch_us(ts) AS t_start, epoch_us(ts) + 5 + (event_id * 7919 + user_id) % 96 AS t_end FROM events")
def p10(spark, sf):
    e = spark.read.parquet(f"{sf}/events.parquet").selectExpr("event_id", "user_id", "timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', ts) AS t_start")
    return with_uniform_end(e, 5, 100, F.col("event_id") * 7919 + F.col("user_id")).select("event_id", "t_start", "t_end")


_SHARES = (0.001, 0.01, 0.05, 0.2, 0.5)


@query("p11_windows", f"WITH g AS ({graph_sql('nations', 'duckdb')}) " + " UNION ALL ".join(f"SELECT {f}::DOUBLE AS share, ta, tb, count(*) / (SELECT count(*) FROM g) AS achieved FROM g, (SELECT CAST(quantile_disc(t_start, {round(1 - f, 6)}) AS BIGINT) AS ta, max(t_end) AS tb FROM g) AS w WHERE t_start >= ta GROUP BY ta, tb" for f in _SHARES))
def p11(spark, sf):
    edges = settle(load_graph(spark, sf, "nations"))
    rows = []
    for f in _SHARES:
        w = window_recent(edges, f)
        rows.append((f, w.start, w.end))
    asked = spark.createDataFrame(rows, "share double, ta long, tb long")
    n = edges.agg(F.count("*").alias("n"))
    return edges.join(F.broadcast(asked), F.col("t_start") >= F.col("ta")).groupBy("share", "ta", "tb").agg(F.count("*").alias("k")).crossJoin(F.broadcast(n)).select("share", "ta", "tb", (F.col("k") / F.col("n")).alias("achieved"))


for _mode, _rule in (("contained", "t_start >= ta AND t_end <= tb"), ("intersects", "t_start <= tb AND t_end >= ta")):
    query(f"p12_restrict_{_mode}", f"WITH g AS ({graph_sql('trade', 'duckdb')}), w AS (SELECT CAST(quantile_disc(t_start, 0.4) AS BIGINT) AS ta, CAST(quantile_disc(t_start, 0.41) AS BIGINT) AS tb FROM g) SELECT src, dst, t_start, t_end FROM g, w WHERE {_rule}")(
        lambda spark, sf, mode=_mode: (lambda e: TemporalGraph(e).restrict(Window(window_percentile(e, 0.4).start, window_percentile(e, 0.41).start), mode).edges.select("src", "dst", "t_start", "t_end"))(settle(load_graph(spark, sf, "trade")))
    )


# ---- minimal paths --------------------------------------------------------------------------

def _paths(name: str, method, twin: str, graph: str, share: float = 0.05, sources: int = 1, **how):
    def run(spark, sf):
        g, w, s = setting(spark, sf, graph, share, sources)
        return method(g, s, w, **how)

    query(name, twin)(run)


for _g in ("relay", "trade", "nations", "hub"):
    for _k, _short in ((STRICT, "strict"), (SUCCEEDS, "succeeds")):
        _paths(f"m01_ea_{_g}_{_short}", paths.earliest_arrival, t.arrival(_g, _k.value), _g, predicate=_k)
_paths("m01_ea_multi_source", paths.earliest_arrival, t.arrival("relay", "strictly_succeeds", 0.05, 100), "relay", 0.05, 100)
_paths("m01_ea_overlaps", paths.earliest_arrival, t.overlap_arrival("relay", 0.02, False), "relay", 0.02, predicate=Ordering.OVERLAPS)
_paths("m01_ea_overlaps_proper", paths.earliest_arrival, t.overlap_arrival("trade", 0.01, True), "trade", 0.01, predicate=Ordering.OVERLAPS_PROPER)
for _g in ("relay", "trade", "nations"):
    _paths(f"m02_ld_{_g}", paths.latest_departure, t.departure(_g, "strictly_succeeds"), _g)
_paths("m02_ld_relay_succeeds", paths.latest_departure, t.departure("relay", "succeeds"), "relay", predicate=SUCCEEDS)
for _g in ("relay", "trade", "hub"):
    _paths(f"m03_fastest_{_g}", paths.fastest, t.fastest(_g, "strictly_succeeds"), _g)
_paths("m03_fastest_relay_succeeds", paths.fastest, t.fastest("relay", "succeeds"), "relay", predicate=SUCCEEDS)
_paths("m03a_per_departure", paths.fastest, t.fastest("relay", "strictly_succeeds"), "relay", strategy="per_departure")
for _g in ("relay", "trade", "basket"):
    _paths(f"m04_short_{_g}", paths.shortest_duration, t.shortest(_g, "strictly_succeeds"), _g)
_paths("m04a_weighted", paths.shortest_duration, t.shortest("basket", "strictly_succeeds", 0.05, "weight", "0.0::DOUBLE"), "basket", cost="weight")
for _g in ("relay", "trade"):
    _paths(f"m05_bfs_time_{_g}", paths.temporal_bfs, t.hops(_g, "strictly_succeeds"), _g)
    _paths(f"m05_bfs_window_{_g}", paths.temporal_bfs, t.window_hops(_g, 0.01), _g, 0.01, mode="window")

# ---- structure ------------------------------------------------------------------------------

for _g, _f in (("relay", 0.005), ("basket", 0.002), ("trade", 0.001)):
    for _m in ("star", "propagate"):
        def _cc(spark, sf, graph=_g, share=_f, method=_m):
            g, w, _ = setting(spark, sf, graph, share)
            return components.connected_components(g, w, method=method)

        query(f"m06_cc_{_g}" + ("" if _m == "star" else "_propagate"), t.components(_g, _f))(_cc)


@query("m06a_mutual_reach", f"""WITH RECURSIVE {t.base('relay', 0.02)},
  r(source, v, label) AS (SELECT DISTINCT src, src, ta - 1 FROM ew, w UNION SELECT r.source, ew.dst, ew.t_end FROM r JOIN ew ON ew.src = r.v AND ew.t_start > r.label),
  p AS (SELECT DISTINCT source, v FROM r WHERE source <> v) SELECT a.source AS u, a.v FROM p AS a JOIN p AS b ON a.source = b.v AND a.v = b.source WHERE a.source < a.v""")
def m06a(spark, sf):
    g, w, _ = setting(spark, sf, "relay", 0.02)
    return components.mutual_reachability(g, w)


@query("m06a_through_time_components", f"""WITH RECURSIVE {t.base('relay', 0.02)},
  r(source, v, label) AS (SELECT DISTINCT src, src, ta - 1 FROM ew, w UNION SELECT r.source, ew.dst, ew.t_end FROM r JOIN ew ON ew.src = r.v AND ew.t_start > r.label),
  p AS (SELECT DISTINCT source AS a, v AS b FROM r WHERE source <> v), n AS (SELECT x.a, x.b FROM p AS x JOIN p AS y ON x.a = y.b AND x.b = y.a),
  c(v, c) AS (SELECT DISTINCT a, a FROM n UNION SELECT n.b, c.c FROM c JOIN n ON n.a = c.v AND c.c < n.b) SELECT v, min(c) AS component FROM c GROUP BY v""")
def m06a_components(spark, sf):
    g, w, _ = setting(spark, sf, "relay", 0.02)
    return components.reachability_components(g, w)


for _g, _f, _n in (("relay", 0.02, 3), ("basket", 0.01, 3)):
    def _core(spark, sf, graph=_g, share=_f, k=_n):
        g, w, _ = setting(spark, sf, graph, share)
        return structure.k_core(g, w, k)

    query(f"m07_kcore_{_g}_k{_n}", t.core(_g, _f, _n))(_core)


@query("m07_coreness_relay", "SELECT v, max(k) AS coreness FROM (" + " UNION ALL ".join(f"SELECT v, {k}::BIGINT AS k FROM ({t.core('relay', 0.02, k)}) AS c{k}" for k in range(1, 9)) + ") AS a GROUP BY v")
def m07_coreness(spark, sf):
    g, w, _ = setting(spark, sf, "relay", 0.02)
    return structure.coreness(g, w)


@query("m08_bc_relay", t.betweenness("relay", 0.03, "src <> dst"))
def m08(spark, sf):
    g, w, _ = setting(spark, sf, "relay", 0.03, where="src <> dst")
    return structure.betweenness(g, w).select("v", F.round("score", 6).alias("score"))


@query("m08a_bc_given_sources", t.betweenness("relay", 0.03, "src <> dst", "src % 5 = 0"))
def m08a_given(spark, sf):
    g, w, _ = setting(spark, sf, "relay", 0.03, where="src <> dst")
    given = g.edges.where("src % 5 = 0").select(F.col("src").alias("source")).distinct()
    return structure.betweenness(g, w, given).select("v", F.round("score", 6).alias("score"))


@query("m08a_sampled_bc")
def m08a(spark, sf):
    g, w, _ = setting(spark, sf, "relay", 0.03, where="src <> dst")
    return structure.sampled_betweenness(g, w, 20).select("v", F.round("score", 6).alias("score"))


for _g in ("relay", "nations"):
    def _rank(spark, sf, graph=_g):
        g, w, _ = setting(spark, sf, graph)
        return structure.pagerank(g, w, max_iter=10).select("v", F.round("rank", 6).alias("rank"))

    query(f"m09_pagerank_{_g}_10", t.pagerank(_g, 0.05, 10))(_rank)


@query("m09_pagerank_nations_100", t.pagerank("nations", 0.05, 100))
def m09_100(spark, sf):
    """All 100 rounds."""
    g, w, _ = setting(spark, sf, "nations")
    return structure.pagerank(g, w, max_iter=100).select("v", F.round("rank", 6).alias("rank"))


# ---- queries and applications ---------------------------------------------------------------

@query("m10_reach", f"SELECT source, v FROM ({t.arrival('trade', 'succeeds', 0.05, 3)}) AS a")
def m10(spark, sf):
    g, w, s = setting(spark, sf, "trade", 0.05, 3)
    return paths.reachable(g, s, w, SUCCEEDS)


@query("m10_reach_pairs", f"SELECT source, v FROM ({t.arrival('relay', 'strictly_succeeds', 0.05, 5)}) AS a WHERE v IN (3, 7, 11)")
def m10_pairs(spark, sf):
    g, w, s = setting(spark, sf, "relay", 0.05, 5)
    return paths.reachable(g, s, w, targets=[3, 7, 11])


@query("m10_max_hops", f"SELECT source, v FROM ({t.hops('trade', 'strictly_succeeds', 0.05, 3)}) AS a")
def m10_hops(spark, sf):
    g, w, s = setting(spark, sf, "trade")
    return paths.reachable(g, s, w, max_hops=3)


@query("m11_two_hop", f"""WITH {t.base('relay', 0.05)} SELECT a.src AS a, a.dst AS b, b.dst AS c, a.t_start AS s0, a.t_end AS e0, b.t_start AS s1, b.t_end AS e1, a.t_end <= b.t_start AS is_succeeds,
  a.t_end < b.t_start AS is_strictly_succeeds, a.t_start < b.t_start AND a.t_end < b.t_end AS is_overlaps, a.t_start < b.t_start AND a.t_end < b.t_end AND b.t_start < a.t_end AS is_overlaps_proper FROM ew AS a JOIN ew AS b ON a.dst = b.src""")
def m11_two_hop(spark, sf):
    g, w, _ = setting(spark, sf, "relay")
    return patterns.two_hop_paths(g, w).withColumnsRenamed({k.value: f"is_{k.value}" for k in Ordering})


_HOUR = 3_600_000_000


@query("m11_triangle", f"""WITH {t.base('relay', 0.3)}, i AS (SELECT row_number() OVER () AS id, * FROM ew)
  SELECT a.src AS v0, b.src AS v1, c.src AS v2, a.t_start AS s0, a.t_end AS e0, b.t_start AS s1, b.t_end AS e1, c.t_start AS s2, c.t_end AS e2 FROM i AS a JOIN i AS b ON a.dst = b.src AND a.t_end < b.t_start JOIN i AS c ON b.dst = c.src AND c.dst = a.src AND b.t_end < c.t_start
  WHERE a.src <> b.src AND b.src <> c.src AND a.src <> c.src AND c.t_end - a.t_start <= {72 * _HOUR}""")
def m11_triangle(spark, sf):
    g, w, _ = setting(spark, sf, "relay", 0.3)
    return patterns.temporal_cycles(g, 3, 72 * _HOUR, w)


@query("m11_pattern_basket", f"""WITH {t.base('basket', 0.03)} SELECT a.src AS x, a.dst AS y, b.dst AS z, a.t_start AS s0, a.t_end AS e0, b.t_start AS s1, b.t_end AS e1
  FROM (SELECT * FROM ew WHERE t_end - t_start <= 40) AS a JOIN (SELECT * FROM ew WHERE t_end - t_start <= 40) AS b ON a.dst = b.src AND a.t_end < b.t_start WHERE a.src <> b.dst AND a.src <> a.dst AND b.src <> b.dst AND b.t_end - a.t_start <= 40""")
def m11_basket(spark, sf):
    g, w, _ = setting(spark, sf, "basket", 0.03)
    return patterns.match_pattern(g, [("x", "y"), ("y", "z")], w, [(0, 1, STRICT)], 40)


@query("m12_path_relay", f"SELECT source, v, arrival, TRUE AS valid FROM ({t.arrival('relay', 'strictly_succeeds', 0.05, 3)}) AS a WHERE v <> source")
def m12(spark, sf):
    """Paths themselves are not unique; each is checked to start at its source, end in time at v, and be ordered."""
    g, w, s = setting(spark, sf, "relay", 0.05, 3)
    p = F.col("path")
    steps = F.forall(F.sequence(F.lit(1), F.size(p) - 1), lambda i: (F.get(p, i)["t_start"] > F.get(p, i - 1)["t_end"]) & (F.get(p, i)["src"] == F.get(p, i - 1)["dst"]))
    ordered = F.when(F.size(p) > 1, steps).otherwise(F.lit(True))
    valid = ordered & (F.get(p, F.lit(0))["src"] == F.col("source")) & (F.element_at(p, -1)["dst"] == F.col("v")) & (F.element_at(p, -1)["t_end"] == F.col("arrival"))
    return paths.arrival_paths(g, s, w).select("source", "v", "arrival", valid.alias("valid"))


@query("m13_exposure", f"SELECT v, min(greatest(arrival, (SELECT ta FROM w))) AS exposed FROM (WITH RECURSIVE {t.base('relay', 0.05, 3)}, r(v, label) AS (SELECT source, ta - 1 FROM s, w UNION SELECT ew.dst, ew.t_end FROM r JOIN ew ON ew.src = r.v AND ew.t_start > r.label) SELECT v, label AS arrival, ta FROM r, w) AS a GROUP BY v".replace("(SELECT ta FROM w)", "ta"))
def m13(spark, sf):
    g, w, s = setting(spark, sf, "relay", 0.05, 3)
    return paths.exposure(g, s, w)


@query("m13_exposure_infectious", f"""WITH RECURSIVE {t.base('relay', 0.05, 3)}, r(v, label) AS (SELECT source, ta - 1 FROM s, w UNION SELECT ew.dst, ew.t_end FROM r JOIN ew ON ew.src = r.v AND ew.t_start > r.label AND ew.t_start <= greatest(r.label, (SELECT ta FROM w)) + {240 * _HOUR})
  SELECT v, greatest(min(label), any_value(ta)) AS exposed FROM r, w GROUP BY v""")
def m13_infectious(spark, sf):
    g, w, s = setting(spark, sf, "relay", 0.05, 3)
    return paths.exposure(g, s, w, infectious=240 * _HOUR)


@query("m14_top_central", f"SELECT v, round(score, 6) AS score FROM ({t.betweenness('relay', 0.03, 'src <> dst')}) AS b ORDER BY score DESC, v LIMIT 5")
def m14(spark, sf):
    g, w, _ = setting(spark, sf, "relay", 0.03, where="src <> dst")
    return structure.top_central(g, w, 5).select("v", F.round("score", 6).alias("score"))


@query("m15_components_over_time", f"""WITH RECURSIVE {t.base('relay', 0.02)}, d AS (SELECT (t_start - ta) // {_HOUR * 24} AS slice, src, dst FROM ew, w),
  n AS (SELECT slice, src AS a, dst AS b FROM d UNION SELECT slice, dst, src FROM d),
  r(slice, v, c) AS (SELECT DISTINCT slice, a, a FROM n UNION SELECT n.slice, n.b, r.c FROM r JOIN n ON n.slice = r.slice AND n.a = r.v AND r.c < n.b),
  f AS (SELECT slice, v, min(c) AS component FROM r GROUP BY slice, v), p AS (SELECT *, lag(component) OVER (PARTITION BY v ORDER BY slice) AS previous FROM f)
  SELECT CAST(slice AS BIGINT) AS slice, v, component, previous, coalesce(previous <> component, FALSE) AS changed FROM p""")
def m15(spark, sf):
    g, w, _ = setting(spark, sf, "relay", 0.02)
    return components.components_over_time(g, w, 24 * _HOUR)


@query("m16_filtered_route", t.arrival("trade", "strictly_succeeds", 0.05, 1, "weight > 20000"))
def m16(spark, sf):
    """Obstacles are edges filtered away before the search."""
    g, w, s = setting(spark, sf, "trade", where="weight > 20000")
    return paths.earliest_arrival(g, s, w)


# ---- storage, index, access -----------------------------------------------------------------

@query("x01_csr_offsets", f"WITH g AS ({graph_sql('trade', 'duckdb')}), d AS (SELECT src AS v, count(*) AS m FROM g GROUP BY src) SELECT v, CAST(coalesce(sum(m) OVER (ORDER BY v ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS first, m FROM d")
def x01(spark, sf):
    return layout.csr_offsets(load_graph(spark, sf, "trade"), chunk=100)


@query("x02_adjacency_blocks", f"WITH g AS ({graph_sql('nations', 'duckdb')}) SELECT src, dst, t_start, t_end, weight FROM g")
def x02(spark, sf):
    return layout.unpack_blocks(layout.adjacency_blocks(load_graph(spark, sf, "nations"), block_rows=512))


@query("x02_scan_neighbors", f"WITH {t.base('nations', 0.05, 3)} SELECT src, dst, t_start, t_end FROM ew WHERE src IN (SELECT source FROM s)")
def x02_scan(spark, sf):
    g, w, s = setting(spark, sf, "nations", 0.05, 3)
    return layout.scan_neighbors(g.edges, paths.source_frame(spark, s).withColumnRenamed("source", "v"), w.start, w.end).select("src", "dst", "t_start", "t_end")


for _g, _side in (("nations", "out"), ("nations", "in"), ("hub", "out")):
    query(f"x03_indexed_vertices_{_g}_{_side}", f"SELECT {'src' if _side == 'out' else 'dst'} AS v, count(*) AS m FROM ({graph_sql(_g, 'duckdb')}) AS g GROUP BY 1 HAVING count(*) >= 1000")(lambda spark, sf, g=_g, side=_side: index.select_indexed_vertices(load_graph(spark, sf, g), 1000, side))


def _three_sided(name: str, axis: str, mode: str, orientation: str, bounds, rule: str):
    own = "src" if orientation == "out" else "dst"
    other = "dst" if orientation == "out" else "src"

    def run(spark, sf):
        g, w, _ = setting(spark, sf, "nations")
        ix = index.build_index(g.edges, 1000, axis, mode, 64, orientation)
        asked = ix.catalog.select("v").withColumns({"ta": F.lit(w.start).cast("long"), "tb": F.lit(w.end).cast("long")})
        heap, lo, hi, extra = bounds
        return index.query_index(ix, asked, index.ThreeSided(F.expr(heap), F.expr(lo), F.expr(hi)), F.expr(extra) if extra else None).select("v", "nbr", "t_start", "t_end")

    query(name, f"WITH {t.base('nations')}, i AS (SELECT {own} AS v FROM edges GROUP BY {own} HAVING count(*) >= 1000) SELECT {own} AS v, {other} AS nbr, t_start, t_end FROM edges, w WHERE {own} IN (SELECT v FROM i) AND {rule}")(run)


_FAR = str(2**62)
_three_sided("x05_contained", "t_start", "max", "out", ("ta", "ta", "tb", None), "t_start >= ta AND t_end <= tb")
_three_sided("x05a_intersecting", "t_start", "min", "out", ("tb - 20", "ta", _FAR, None), "t_start <= tb - 20 AND t_end >= ta")
_three_sided("x05b_succeeds", "t_start", "max", "out", ("ta + 10", "ta + 10", "tb", None), "t_start >= ta + 10 AND t_end <= tb")
_three_sided("x05b_strictly", "t_start", "max", "out", ("ta + 11", "ta + 11", "tb", None), "t_start > ta + 10 AND t_end <= tb")
_three_sided("x05c_backward", "t_end", "min", "in", ("tb - 10", "ta", "tb - 10", None), "t_end <= tb - 10 AND t_start >= ta AND t_start <= tb - 10")
_three_sided("x05d_overlaps", "t_start", "max", "out", ("ta + 6", "ta + 21", "tb", None), "t_start > ta + 5 AND t_end > ta + 20 AND t_end <= tb")
_three_sided("x05d_overlaps_proper", "t_start", "max", "out", ("ta + 6", "ta + 21", "tb", "t_start < ta + 20"), "t_start > ta + 5 AND t_end > ta + 20 AND t_end <= tb AND t_start < ta + 20")


@query("x04a_descend", f"WITH {t.base('nations')}, i AS (SELECT src AS v FROM edges GROUP BY src HAVING count(*) >= 1000) SELECT src AS v, count(*) AS k, TRUE AS same_nodes FROM ew WHERE src IN (SELECT v FROM i) GROUP BY src")
def x04a(spark, sf):
    """Matches found, and whether a root-down descent opens exactly the nodes that the flat join picks."""
    g, w, _ = setting(spark, sf, "nations")
    ix = index.build_index(g.edges, 1000)
    asked = metrics.asked_over(ix.catalog, w)
    bounds = index.ThreeSided(F.col("a"), F.col("a"), F.col("b"))
    found = index.query_index(ix, asked, bounds).groupBy("v").agg(F.count("*").alias("k"))
    flat = index.nodes_read(ix, asked, bounds).select("v", "nodes")
    down = index.descend(ix, asked, bounds).groupBy("v").agg(F.count("*").alias("down"))
    return found.join(flat, "v").join(down, "v").select("v", "k", (F.col("nodes") == F.col("down")).alias("same_nodes"))


_HIST = f"""i AS (SELECT src AS v, count(*) AS m FROM edges GROUP BY src HAVING count(*) >= 1000),
  o AS (SELECT src AS v, t_start AS s, t_end - t_start AS d FROM edges WHERE src IN (SELECT v FROM i)),
  meta AS (SELECT v, count(*) AS m, min(s) AS s_lo, max(s) AS s_hi, min(d) AS d_lo, max(d) AS d_hi FROM o GROUP BY v),
  cells AS (SELECT o.v, CAST(CASE WHEN s_hi = s_lo THEN 0 ELSE least(99, ((s - s_lo) * 100) // (s_hi - s_lo)) END AS BIGINT) AS bx, CAST(CASE WHEN d_hi = d_lo THEN 0 ELSE least(99, ((d - d_lo) * 100) // (d_hi - d_lo)) END AS BIGINT) AS by_, count(*) AS n FROM o JOIN meta USING (v) GROUP BY 1, 2, 3)"""


@query("x06_costs", f"WITH {t.base('nations')}, k AS (SELECT src AS v, count(*) AS m, count(*) FILTER (WHERE t_start >= ta AND t_end <= tb) AS k FROM edges, w GROUP BY src HAVING count(*) >= 1000) SELECT v, m, k, round(log2(m) + k, 6) AS index_cost, round(m::DOUBLE, 6) AS scan_cost, round(least(log2(m) + k, m), 6) AS least FROM k")
def x06(spark, sf):
    g, w, _ = setting(spark, sf, "nations")
    plan = access.plan_access(g, 1000)
    return metrics.cost_table(g, plan, w).select("v", "m", "k", *[F.round(c, 6).alias(c) for c in ("index_cost", "scan_cost", "least")])


@query("x09_histogram", f"WITH {t.base('nations')}, {_HIST} SELECT v, bx, by_ AS by_cell, n FROM cells")
def x09(spark, sf):
    g, _, _ = setting(spark, sf, "nations")
    h = histogram.build_histogram(g.edges, index.select_indexed_vertices(g.edges, 1000))
    return h.cells.withColumnRenamed("by", "by_cell")


def _corner(x: str) -> str:
    """Area of the triangle that the line start + duration = b cuts off above a corner at distance x before it."""
    return f"power(greatest({x}, 0.0), 2) / 2"


#: Expected share of a cell inside [a, b] from areas: the triangle at the lower left corner less those beyond the right and upper sides.
_SHARE = f"""CASE WHEN s1 = s0 AND d1 = d0 THEN CASE WHEN s0 >= a AND s0 + d0 <= b THEN 1.0 ELSE 0.0 END
  WHEN s1 = s0 THEN CASE WHEN s0 >= a THEN greatest(0.0, least(1.0, (b - s0 - d0) / (d1 - d0))) ELSE 0.0 END
  WHEN d1 = d0 THEN greatest(0.0, least(s1, b - d0) - greatest(s0, a)) / (s1 - s0)
  WHEN s1 <= a THEN 0.0 ELSE ({_corner('b - greatest(s0, a) - d0')} - ({_corner('b - s1 - d0')}) - ({_corner('b - greatest(s0, a) - d1')}) + {_corner('b - s1 - d1')}) / ((s1 - s0) * (d1 - d0)) END"""


def _estimate_sql(share: str, digits: int = 4, window: float = 0.05, cutoff: int = 1000) -> str:
    return f"""WITH {t.base('nations', window)}, {_HIST.replace(">= 1000", f">= {cutoff}")},
      c AS (SELECT v, m, n, ta AS a, tb AS b, s_lo + (s_hi - s_lo) * CAST(bx AS DOUBLE) / 100 AS s0, s_lo + (s_hi - s_lo) * CAST(bx + 1 AS DOUBLE) / 100 AS s1, d_lo + (d_hi - d_lo) * CAST(by_ AS DOUBLE) / 100 AS d0, d_lo + (d_hi - d_lo) * CAST(by_ + 1 AS DOUBLE) / 100 AS d1 FROM cells JOIN meta USING (v), w),
      q AS (SELECT v, m, n, CAST(a AS DOUBLE) AS a, CAST(b AS DOUBLE) AS b, s0, s1, d0, d1 FROM c)
      SELECT v, CAST(a AS BIGINT) AS a, CAST(b AS BIGINT) AS b, m, round(sum(n * CAST({share} AS DOUBLE)), {digits}) AS k_hat FROM q GROUP BY v, a, b, m"""


for _cell, _share in (("uniform", _SHARE), ("full", "CASE WHEN s1 >= a AND s0 + d0 <= b THEN 1.0 ELSE 0.0 END"), ("none", "CASE WHEN s0 >= a AND s1 + d1 <= b THEN 1.0 ELSE 0.0 END")):
    def _estimate(spark, sf, cell=_cell):
        g, w, _ = setting(spark, sf, "nations")
        indexed = index.select_indexed_vertices(g.edges, 1000)
        h = histogram.build_histogram(g.edges, indexed)
        return histogram.estimate(h, metrics.asked_over(indexed, w), cell).select("v", "a", "b", "m", F.round("k_hat", 4).alias("k_hat"))

    query(f"x09a_estimate_{_cell}", _estimate_sql(_share))(_estimate)


@query("x09b_prefix_counts", f"""WITH {t.base('nations')}, {_HIST}, grid AS (SELECT * FROM (SELECT DISTINCT v, bx FROM cells) AS r JOIN (SELECT DISTINCT v, by_ FROM cells) AS c USING (v)),
  filled AS (SELECT grid.v, grid.bx, grid.by_, coalesce(n, 0) AS n FROM grid LEFT JOIN cells ON cells.v = grid.v AND cells.bx = grid.bx AND cells.by_ = grid.by_),
  down AS (SELECT v, bx, by_, sum(n) OVER (PARTITION BY v, by_ ORDER BY bx ROWS UNBOUNDED PRECEDING) AS n FROM filled)
  SELECT v, bx, by_ AS by_cell, CAST(sum(n) OVER (PARTITION BY v, bx ORDER BY by_ ROWS UNBOUNDED PRECEDING) AS BIGINT) AS upto FROM down""")
def x09b(spark, sf):
    g, _, _ = setting(spark, sf, "nations")
    h = histogram.build_histogram(g.edges, index.select_indexed_vertices(g.edges, 1000))
    return histogram.prefix_counts(h).withColumnRenamed("by", "by_cell")


@query("x08_access_choice", f"""WITH {t.base('nations', 0.1)}, k AS (SELECT src AS v, count(*) AS m, count(*) FILTER (WHERE t_start >= ta AND t_end <= tb) AS k FROM edges, w GROUP BY src)
  SELECT v, CASE WHEN m >= 2000 AND k::DOUBLE / m <= 0.2 THEN 'index' ELSE 'scan' END AS access FROM k""")
def x08(spark, sf):
    g, w, _ = setting(spark, sf, "nations", 0.1)
    return access.explain_access(g, access.plan_access(g, 2000), w).select("v", "access")


@query("x08_cost_choice", f"""WITH {t.base('nations', 0.1)}, k AS (SELECT src AS v, count(*) AS m, count(*) FILTER (WHERE t_start >= ta AND t_end <= tb) AS k FROM edges, w GROUP BY src)
  SELECT v, CASE WHEN m >= 1000 AND 9 * (log2(m) + k) < m THEN 'index' ELSE 'scan' END AS access FROM k""")
def x08_cost(spark, sf):
    g, w, _ = setting(spark, sf, "nations", 0.1)
    return access.explain_access(g, access.plan_access(g, 1000, mode="cost", c=9.0), w, "oracle").select("v", "access")


_CUTS = [500, 1000, 2000, 4000]


@query("x11_degree_profile", f"WITH d AS (SELECT src, count(*) AS m FROM ({graph_sql('nations', 'duckdb')}) AS g GROUP BY src), c AS (SELECT unnest({_CUTS})::BIGINT AS cutoff) SELECT cutoff, count(src) AS vertices, CAST(coalesce(sum(m), 0) AS BIGINT) AS edges, coalesce(sum(m), 0) / (SELECT sum(m) FROM d) AS share FROM c LEFT JOIN d ON m >= cutoff GROUP BY cutoff")
def x11(spark, sf):
    return metrics.degree_profile(load_graph(spark, sf, "nations"), _CUTS)


@query("x12_time_profile", f"""WITH g AS ({graph_sql('relay', 'duckdb')}), l AS (SELECT src, t_start - lag(t_start) OVER (PARTITION BY src ORDER BY t_start) AS gap FROM g), a AS (SELECT src AS v, count(*) AS m, avg(gap) AS mean_gap, stddev_pop(gap) AS sd_gap FROM l GROUP BY src)
  SELECT v, m, round(mean_gap, 2) AS mean_gap, round(CASE WHEN sd_gap + mean_gap > 0 THEN (sd_gap - mean_gap) / (sd_gap + mean_gap) END, 6) AS burstiness FROM a""")
def x12(spark, sf):
    return metrics.time_profile(load_graph(spark, sf, "relay")).select("v", "m", F.round("mean_gap", 2).alias("mean_gap"), F.round("burstiness", 6).alias("burstiness"))


# ---- baselines and measures -----------------------------------------------------------------

for _n, _mode in (("b01_scan", "scan"), ("b02_index", "index"), ("b03_oracle", "oracle"), ("b04_uniform", "uniform"), ("b05_global_scan", "global_scan"), ("b05_global_range", "global_range"), ("x10_selective_index", "auto")):
    def _access(spark, sf, mode=_mode):
        g, w, s = setting(spark, sf, "nations")
        plan = access.plan_access(g, 1000) if mode in ("index", "oracle", "uniform", "auto") else None
        return paths.earliest_arrival(g, s, w, access=mode, plan=plan)

    query(_n, t.arrival("nations", "strictly_succeeds"))(_access)

_paths("b06_messages", lambda g, s, w: baselines.message_passing_arrival(g, s, w)[0], t.arrival("relay", "strictly_succeeds"), "relay")
_paths("b06_message_counts", lambda g, s, w: baselines.message_passing_arrival(g, s, w)[1], f"""WITH RECURSIVE {t.base('relay')}, o AS (SELECT src AS v, count(*) AS m FROM edges GROUP BY src),
  vs AS (SELECT src AS v FROM edges UNION SELECT dst FROM edges),
  st(it, v, label, fresh) AS (SELECT 0, v, CASE WHEN v IN (SELECT source FROM s) THEN ta - 1 END, v IN (SELECT source FROM s) FROM vs, w
    UNION ALL (WITH c AS (SELECT ew.dst AS v, min(ew.t_end) AS label FROM st JOIN ew ON ew.src = st.v AND ew.t_start > st.label WHERE st.fresh GROUP BY ew.dst)
      SELECT st.it + 1, st.v, least(st.label, c.label), coalesce(c.label < coalesce(st.label, c.label + 1), FALSE) FROM st LEFT JOIN c ON c.v = st.v WHERE EXISTS (SELECT 1 FROM st AS f WHERE f.fresh)))
  SELECT it + 1 AS round, CAST(coalesce(sum(m), 0) AS BIGINT) AS messages FROM st LEFT JOIN o USING (v) WHERE fresh GROUP BY it""", "relay")
for _n, _method, _twin in (
    ("m02_ld_trade_auto", paths.latest_departure, t.departure("trade", "strictly_succeeds")), ("m03_fastest_trade_auto", paths.fastest, t.fastest("trade", "strictly_succeeds")),
    ("m04_short_trade_auto", paths.shortest_duration, t.shortest("trade", "strictly_succeeds")), ("m05_bfs_trade_auto", paths.temporal_bfs, t.hops("trade", "strictly_succeeds")),
):
    def _by_choice(spark, sf, method=_method):
        """Vertices of 80 edges and more are indexed; a theta between their selectivities sends some to the index and some to a scan."""
        g, w, s = setting(spark, sf, "trade")
        return method(g, s, w, access="auto", plan=access.plan_access(g, 80, theta=0.02, directions=("out", "in") if method is paths.latest_departure else ("out",)))

    query(_n, _twin)(_by_choice)
for _k, _short in ((STRICT, "strict"), (SUCCEEDS, "succeeds")):
    _paths(f"b07_time_expanded_{_short}", baselines.time_expanded_arrival, t.arrival("relay", _k.value), "relay", predicate=_k)
    _paths(f"b08_one_pass_{_short}", baselines.one_pass_arrival, t.arrival("trade", _k.value, 0.05, 10), "trade", 0.05, 10, predicate=_k)


@query("c06_accuracy", f"""WITH {t.base('nations', 0.05)}, k AS (SELECT src AS v, count(*) AS m, count(*) FILTER (WHERE t_start >= ta AND t_end <= tb) AS k FROM edges, w GROUP BY src HAVING count(*) >= 1000)
  SELECT count(*) FILTER (WHERE k::DOUBLE / m <= 0.2) AS should_use FROM k""")
def c06(spark, sf):
    g, w, _ = setting(spark, sf, "nations", 0.05)
    return metrics.decision_accuracy(g, access.plan_access(g, 1000), w).select((F.col("tp") + F.col("fn")).alias("should_use"))


def _accuracy_sql(cutoff: int, share: float) -> str:
    """Decisions from independent estimates against counts."""
    return f"""SELECT {cutoff} AS cutoff, {share}::DOUBLE AS share, count(*) FILTER (WHERE did AND should) AS tp, count(*) FILTER (WHERE NOT did AND NOT should) AS tn, count(*) FILTER (WHERE did AND NOT should) AS fp, count(*) FILTER (WHERE NOT did AND should) AS fn,
      round(avg(CASE WHEN did = should THEN 1.0 ELSE 0.0 END), 6) AS accuracy FROM (SELECT e.k_hat / e.m <= 0.2 AS did, k.k::DOUBLE / e.m <= 0.2 AS should FROM ({_estimate_sql(_SHARE, 9, share, cutoff)}) AS e
      JOIN (WITH {t.base('nations', share)} SELECT src AS v, count(*) FILTER (WHERE t_start >= ta AND t_end <= tb) AS k FROM edges, w GROUP BY src) AS k ON k.v = e.v) AS z"""


_SWEEP = [(c, x) for c in (1000, 2000, 4000) for x in (0.005, 0.05, 0.2)]


@query("c06_accuracy_sweep", " UNION ALL ".join(f"({_accuracy_sql(c, x)})" for c, x in _SWEEP))
def c06_sweep(spark, sf):
    """(cutoff, share, accuracy...) over cutoffs and windows."""
    edges = settle_columns(load_graph(spark, sf, "nations").select("src", "dst", "t_start", "t_end"))
    g, out = TemporalGraph(edges), None
    windows = {share: window_recent(edges, share) for share in (0.005, 0.05, 0.2)}
    for cutoff, plan in access.plan_choices(g, [1000, 2000, 4000]).items():
        for share, w in windows.items():
            row = metrics.decision_accuracy(g, plan, w).select(F.lit(cutoff).alias("cutoff"), F.lit(share).alias("share"), "tp", "tn", "fp", "fn", F.round("accuracy", 6).alias("accuracy"))
            out = row if out is None else out.unionByName(row)
    return out


@query("c07_estimate_error", f"""WITH {t.base('nations')}, k AS (SELECT src AS v, count(*) FILTER (WHERE t_start >= ta AND t_end <= tb) AS k FROM edges, w GROUP BY src)
  SELECT e.v, e.m, k.k, round(e.k_hat, 3) AS k_hat, round(abs(e.k_hat - k.k) / e.m, 5) AS error, round(greatest(greatest(k.k, 1) / greatest(e.k_hat, 1), greatest(e.k_hat, 1) / greatest(k.k, 1)), 4) AS q_error FROM ({_estimate_sql(_SHARE, 12)}) AS e JOIN k ON k.v = e.v""")
def c07(spark, sf):
    g, w, _ = setting(spark, sf, "nations", 0.05)
    rows = metrics.estimate_error(g, access.plan_access(g, 1000), w)
    return rows.select("v", "m", "k", *[F.round(c, n).alias(c) for c, n in (("k_hat", 3), ("error", 5), ("q_error", 4))])


@query("c08_edges_examined", f"WITH {t.base('nations', 0.02)}, k AS (SELECT src AS v, count(*) AS m, count(*) FILTER (WHERE t_start >= ta AND t_end <= tb) AS k FROM edges, w GROUP BY src HAVING count(*) >= 1000) SELECT v, m, k, TRUE AS at_least_matches, TRUE AS below_scan FROM k")
def c08(spark, sf):
    g, w, _ = setting(spark, sf, "nations", 0.02)
    return metrics.work(g, access.plan_access(g, 1000), w).select("v", "m", "k", (F.col("index_examined") >= F.col("k")).alias("at_least_matches"), (F.col("index_examined") < F.col("scan_examined")).alias("below_scan"))


@query("c10_selectivity", f"WITH {t.base('hub', 0.05)} SELECT src AS v, count(*) AS m, count(*) FILTER (WHERE t_start >= ta AND t_end <= tb) AS k, count(*) FILTER (WHERE t_start >= ta AND t_end <= tb) / count(*) AS beta FROM edges, w GROUP BY src")
def c10(spark, sf):
    g, w, _ = setting(spark, sf, "hub", 0.05)
    return metrics.selectivity(g, g.edges.select(F.col("src").alias("v")).distinct(), w)


@query("c12_space", f"""WITH {t.base('relay', 0.05)}, o AS (SELECT DISTINCT src AS v, t_start AS t FROM ew), i AS (SELECT DISTINCT dst AS v, t_end AS t FROM ew)
  SELECT 'edges' AS part, count(*) AS rows FROM edges UNION ALL SELECT 'window_edges', count(*) FROM ew UNION ALL SELECT 'expanded_nodes', (SELECT count(*) FROM o) + (SELECT count(*) FROM i)
  UNION ALL SELECT 'expanded_arcs', (SELECT count(*) FROM (SELECT DISTINCT src, dst, t_start, t_end FROM ew)) + (SELECT count(*) FROM i WHERE EXISTS (SELECT 1 FROM o WHERE o.v = i.v AND o.t > i.t)) + (SELECT count(*) FROM o AS x WHERE EXISTS (SELECT 1 FROM o WHERE o.v = x.v AND o.t > x.t))
  UNION ALL SELECT 'index_edges', coalesce(sum(m), 0)::BIGINT FROM (SELECT count(*) AS m FROM edges GROUP BY src HAVING count(*) >= 70)
  UNION ALL SELECT 'histogram_cells', (SELECT count(*) FROM (WITH {_HIST.replace('>= 1000', '>= 70')} SELECT * FROM cells))""")
def c12(spark, sf):
    g, w, _ = setting(spark, sf, "relay", 0.05)
    return metrics.space(g, access.plan_access(g, 70), w).where("part <> 'index_nodes'")


@query("c12_space_all")
def c12_all(spark, sf):
    """With the number of index nodes, which only the engine's own layout decides."""
    g, w, _ = setting(spark, sf, "relay", 0.05)
    return metrics.space(g, access.plan_access(g, 70), w)


@query("c08_counters", f"""WITH {t.base('relay', 0.3, 5)} SELECT count(*) AS examined, count(*) FILTER (WHERE t_start > (ta + tb) // 2) AS admitted FROM ew, w WHERE src IN (SELECT source FROM s)""")
def c08_counters(spark, sf):
    """Counters that the job of one edge map leaves behind, frontier labels in the middle of the window."""
    g, w, s = setting(spark, sf, "relay", 0.3, 5)
    frontier = paths.source_frame(spark, s).select("source", F.col("source").alias("v"), F.lit((w.start + w.end) // 2).cast("long").alias("label"))
    found, seen = expand_counted(frontier, window_edges(g.restrict(w).edges), STRICT)
    found.write.format("noop").mode("overwrite").save()
    return spark.createDataFrame([(seen.get["examined"], seen.get["admitted"])], "examined long, admitted long")
