"""Building blocks of the DuckDB twins: graphs, windows, sources and label recursions."""

from __future__ import annotations

from ..sources.graphs import graph_sql


def base(graph: str, share: float = 0.05, sources: int = 1, where: str = "TRUE") -> str:
    """CTEs: edges, w (window), ew (edges inside it), s (top sources of the whole graph), vertices."""
    return f"""
    edges AS (SELECT * FROM ({graph_sql(graph, "duckdb")}) AS g WHERE {where}),
    w AS (SELECT CAST(quantile_disc(t_start, {round(1 - share, 6)}) AS BIGINT) AS ta, max(t_end) AS tb FROM edges),
    ew AS (SELECT edges.* FROM edges, w WHERE t_start >= ta AND t_end <= tb),
    s AS (SELECT src AS source FROM edges GROUP BY src ORDER BY count(*) DESC, src LIMIT {sources})"""


def follows(kind: str) -> str:
    return ">" if kind == "strictly_succeeds" else ">="


def arrival(graph: str, kind: str, share: float = 0.05, sources: int = 1, where: str = "TRUE", value: str = "arrival") -> str:
    seed = "ta - 1" if kind == "strictly_succeeds" else "ta"
    return f"""WITH RECURSIVE {base(graph, share, sources, where)},
    r(source, v, label) AS (SELECT source, source, {seed} FROM s, w
      UNION SELECT r.source, ew.dst, ew.t_end FROM r JOIN ew ON ew.src = r.v AND ew.t_start {follows(kind)} r.label)
    SELECT source, v, CASE WHEN v = source THEN any_value(ta) ELSE min(label) END AS {value} FROM r, w GROUP BY source, v"""


def departure(graph: str, kind: str, share: float = 0.05) -> str:
    seed, sign = ("tb + 1", "<") if kind == "strictly_succeeds" else ("tb", "<=")
    return f"""WITH RECURSIVE {base(graph, share)},
    r(target, v, label) AS (SELECT source, source, {seed} FROM s, w
      UNION SELECT r.target, ew.src, ew.t_start FROM r JOIN ew ON ew.dst = r.v AND ew.t_end {sign} r.label)
    SELECT target, v, CASE WHEN v = target THEN any_value(tb) ELSE max(label) END AS departure FROM r, w GROUP BY target, v"""


def fastest(graph: str, kind: str, share: float = 0.05) -> str:
    return f"""WITH RECURSIVE {base(graph, share)},
    r(source, v, dep, arr) AS (SELECT source, dst, t_start, t_end FROM s JOIN ew ON src = source
      UNION SELECT r.source, ew.dst, r.dep, ew.t_end FROM r JOIN ew ON ew.src = r.v AND ew.t_start {follows(kind)} r.arr),
    b AS (SELECT source, v, min(arr - dep) AS duration FROM r WHERE v <> source GROUP BY source, v)
    SELECT b.source, b.v, b.duration, max(r.dep) AS departure, max(r.dep) + b.duration AS arrival FROM b JOIN r ON r.source = b.source AND r.v = b.v AND r.arr - r.dep = b.duration
    GROUP BY b.source, b.v, b.duration UNION ALL SELECT source, source, 0, ta, ta FROM s, w"""


def shortest(graph: str, kind: str, share: float = 0.05, price: str = "t_end - t_start", zero: str = "0") -> str:
    return f"""WITH RECURSIVE {base(graph, share)},
    r(source, v, arr, cost) AS (SELECT source, dst, t_end, {price} FROM s JOIN ew ON src = source
      UNION SELECT r.source, ew.dst, ew.t_end, r.cost + ({price}) FROM r JOIN ew ON ew.src = r.v AND ew.t_start {follows(kind)} r.arr)
    SELECT source, v, min(cost) AS cost FROM r WHERE v <> source GROUP BY source, v UNION ALL SELECT source, source, {zero} FROM s"""


def hops(graph: str, kind: str, share: float = 0.05, most: int = 40) -> str:
    seed = "ta - 1" if kind == "strictly_succeeds" else "ta"
    return f"""WITH RECURSIVE {base(graph, share)},
    r(source, v, label, hop) AS (SELECT source, source, {seed}, 0 FROM s, w
      UNION SELECT r.source, ew.dst, ew.t_end, r.hop + 1 FROM r JOIN ew ON ew.src = r.v AND ew.t_start {follows(kind)} r.label WHERE r.hop < {most})
    SELECT source, v, CAST(min(hop) AS BIGINT) AS hops FROM r GROUP BY source, v"""


def window_hops(graph: str, share: float = 0.05, most: int = 25) -> str:
    return f"""WITH RECURSIVE {base(graph, share)}, e AS (SELECT DISTINCT src, dst FROM ew),
    r(source, v, hop) AS (SELECT source, source, 0 FROM s UNION SELECT r.source, e.dst, r.hop + 1 FROM r JOIN e ON e.src = r.v WHERE r.hop < {most})
    SELECT source, v, CAST(min(hop) AS BIGINT) AS hops FROM r GROUP BY source, v"""


def overlap_arrival(graph: str, share: float, proper: bool) -> str:
    rule = "ew.t_start > r.ps AND ew.t_end > r.pe" + (" AND ew.t_start < r.pe" if proper else "")
    return f"""WITH RECURSIVE {base(graph, share)},
    r(source, v, ps, pe) AS (SELECT source, dst, t_start, t_end FROM s JOIN ew ON src = source
      UNION SELECT r.source, ew.dst, ew.t_start, ew.t_end FROM r JOIN ew ON ew.src = r.v AND {rule})
    SELECT source, v, min(pe) AS arrival FROM r WHERE v <> source GROUP BY source, v UNION ALL SELECT source, source, ta FROM s, w"""


def components(graph: str, share: float) -> str:
    return f"""WITH RECURSIVE {base(graph, share)},
    n AS (SELECT src AS a, dst AS b FROM ew UNION SELECT dst, src FROM ew),
    r(v, c) AS (SELECT DISTINCT a, a FROM n UNION SELECT n.b, r.c FROM r JOIN n ON n.a = r.v AND r.c < n.b)
    SELECT v, min(c) AS component FROM r GROUP BY v"""


def core(graph: str, share: float, k: int, rounds: int = 40) -> str:
    """A SELECT of the vertices of the k-core, from CTE `ids` (id, src, dst) of the window's edges."""
    return f"""WITH RECURSIVE {base(graph, share)}, ids AS (SELECT row_number() OVER () AS id, src, dst FROM ew),
    r(it, id, src, dst) AS (SELECT 0, id, src, dst FROM ids
      UNION ALL (WITH d AS (SELECT v FROM (SELECT src AS v FROM r UNION ALL SELECT dst FROM r) AS x GROUP BY v HAVING count(*) >= {k})
        SELECT it + 1, id, src, dst FROM r WHERE it < {rounds} AND src IN (SELECT v FROM d) AND dst IN (SELECT v FROM d)))
    SELECT DISTINCT v FROM (SELECT src AS v FROM r WHERE it = {rounds} UNION SELECT dst FROM r WHERE it = {rounds}) AS y"""


def pagerank(graph: str, share: float, rounds: int) -> str:
    return f"""WITH RECURSIVE {base(graph, share)},
    o AS (SELECT src, count(*) AS n FROM ew GROUP BY src),
    p AS (SELECT ew.src, ew.dst, count(*)::DOUBLE / any_value(o.n) AS p FROM ew JOIN o USING (src) GROUP BY ew.src, ew.dst),
    v AS (SELECT src AS v FROM ew UNION SELECT dst FROM ew), c AS (SELECT count(*) AS n FROM v),
    r(it, v, rank) AS (SELECT 0, v, 1.0::DOUBLE / n FROM v, c
      UNION ALL (WITH f AS (SELECT p.dst AS v, sum(r.rank * p.p) AS inflow FROM r JOIN p ON p.src = r.v GROUP BY p.dst),
        l AS (SELECT coalesce(sum(rank), 0) AS loose FROM r WHERE v NOT IN (SELECT src FROM o))
        SELECT r.it + 1, r.v, 0.15 / c.n + 0.85 * (coalesce(f.inflow, 0) + l.loose / c.n) FROM r LEFT JOIN f ON f.v = r.v, c, l WHERE r.it < {rounds}))
    SELECT v, round(rank, 6) AS rank FROM r WHERE it = {rounds}"""


def betweenness(graph: str, share: float, where: str, from_where: str = "TRUE") -> str:
    return f"""WITH RECURSIVE {base(graph, share, 1, where)}, ids AS (SELECT row_number() OVER () AS id, * FROM ew),
    r(s, v, t_end, cost, inner_vs) AS (SELECT src, dst, t_end, t_end - t_start, CAST([] AS BIGINT[]) FROM ids WHERE {from_where}
      UNION ALL SELECT r.s, i.dst, i.t_end, r.cost + i.t_end - i.t_start, list_append(r.inner_vs, r.v) FROM r JOIN ids AS i ON i.src = r.v AND i.t_start > r.t_end WHERE i.dst <> r.s AND r.v <> r.s),
    b AS (SELECT s, v, min(cost) AS cost FROM r WHERE s <> v GROUP BY s, v),
    t AS (SELECT r.s, r.v, r.inner_vs, count(*) OVER (PARTITION BY r.s, r.v) AS n FROM r JOIN b ON r.s = b.s AND r.v = b.v AND r.cost = b.cost),
    sc AS (SELECT x AS v, sum(1.0 / n) AS score FROM (SELECT unnest(inner_vs) AS x, n FROM t) AS u GROUP BY x),
    vs AS (SELECT src AS v FROM ew UNION SELECT dst FROM ew)
    SELECT vs.v, round(coalesce(score, 0), 6) AS score FROM vs LEFT JOIN sc ON sc.v = vs.v"""
