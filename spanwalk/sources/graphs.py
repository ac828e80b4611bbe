"""Temporal graphs over the given tables.

One recipe in SQL serves both engines; only the calls that turn times into integers differ.
Vertices are numbered from zero. Edges: (src, dst, t_start, t_end, weight).
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession

TABLES = {"trade": ("lineitem", "orders", "customer"), "relay": ("events",), "nations": ("lineitem", "orders", "customer", "supplier"), "hub": ("events",), "basket": ("lineitem",)}

_RECIPES = {
    "trade": """
        SELECT o_custkey AS src, nc + l_suppkey AS dst, DAY(o_orderdate) AS t_start,
               DAY(o_orderdate) + 1 + (l_partkey * 31 + l_linenumber) % 30 AS t_end, l_extendedprice AS weight
        FROM lineitem JOIN orders ON l_orderkey = o_orderkey CROSS JOIN (SELECT count(*) AS nc FROM customer) AS c
        UNION ALL
        SELECT nc + l_suppkey, o_custkey, DAY(l_shipdate),
               DAY(l_shipdate) + 1 + (l_partkey * 17 + CAST(l_quantity AS BIGINT)) % 30, l_extendedprice
        FROM lineitem JOIN orders ON l_orderkey = o_orderkey CROSS JOIN (SELECT count(*) AS nc FROM customer) AS c""",
    "relay": """
        SELECT user_id AS src, dst, t_start, t_end, value AS weight FROM (
          SELECT user_id, value, US(ts) AS t_start,
                 lead(user_id) OVER (PARTITION BY event_type ORDER BY ts, event_id) AS dst,
                 lead(US(ts)) OVER (PARTITION BY event_type ORDER BY ts, event_id) AS t_end
          FROM events) AS e
        WHERE dst IS NOT NULL""",
    "nations": """
        SELECT CAST(s_nationkey AS BIGINT) AS src, CAST(c_nationkey AS BIGINT) AS dst, DAY(l_shipdate) AS t_start,
               DAY(l_shipdate) + 1 + (l_partkey * 17 + CAST(l_quantity AS BIGINT)) % 30 AS t_end, l_extendedprice AS weight
        FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey""",
    "hub": """
        SELECT user_id + 5 AS src, kind AS dst, US(ts) AS t_start,
               US(ts) + 1000000 * (1 + (event_id * 7919 + user_id * 31) % 3600) AS t_end, value AS weight
        FROM (SELECT *, CAST(CASE event_type WHEN 'click' THEN 0 WHEN 'error' THEN 1 WHEN 'purchase' THEN 2 WHEN 'signup' THEN 3 ELSE 4 END AS BIGINT) AS kind FROM events) AS e
        UNION ALL
        SELECT kind, (user_id + CAST(regexp_extract(props, '(-?[0-9]+)', 1) AS BIGINT)) % nu + 5, US(ts),
               US(ts) + 1000000 * (1 + (event_id * 104729 + user_id * 17) % 3600), value
        FROM (SELECT *, CAST(CASE event_type WHEN 'click' THEN 0 WHEN 'error' THEN 1 WHEN 'purchase' THEN 2 WHEN 'signup' THEN 3 ELSE 4 END AS BIGINT) AS kind FROM events) AS e
        CROSS JOIN (SELECT max(user_id) + 1 AS nu FROM events) AS u""",
    "basket": """
        SELECT a.l_partkey AS src, b.l_partkey AS dst, DAY(least(a.l_shipdate, b.l_shipdate)) AS t_start,
               DAY(greatest(a.l_shipdate, b.l_shipdate)) AS t_end, a.l_quantity + b.l_quantity AS weight
        FROM lineitem AS a JOIN lineitem AS b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey""",
}
_CALLS = {
    "spark": {"DAY": "CAST(unix_date(CAST({} AS DATE)) AS BIGINT)", "US": "timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', {})"},
    "duckdb": {"DAY": "CAST(datediff('day', DATE '1970-01-01', CAST({} AS DATE)) AS BIGINT)", "US": "epoch_us({})"},
}


def graph_sql(name: str, dialect: str) -> str:
    """The recipe in the given dialect; tables stand by their names."""
    text = _RECIPES[name]
    for call, form in _CALLS[dialect].items():
        text = re.sub(rf"\b{call}\(((?:[^()]|\([^()]*\))*)\)", lambda m, form=form: form.format(m.group(1)), text)
    return text


def load_graph(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Edges of a named graph; scans read only the columns that the recipe names."""
    text = graph_sql(name, "spark")
    frames = {t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in TABLES[name]}
    for t in frames:
        text = re.sub(rf"\b(FROM|JOIN) {t}\b", rf"\1 {{{t}}}", text)
    return spark.sql(text, **frames)


#: A seven-vertex example (a..g are 0..6) with parallel and zero-length edges, cycles and touching intervals.
TINY = (
    (0, 1, 1, 3), (0, 2, 2, 5), (1, 2, 3, 4), (1, 3, 4, 6), (2, 3, 5, 7), (2, 4, 6, 6), (3, 4, 7, 9),
    (3, 5, 6, 10), (4, 5, 9, 11), (4, 0, 8, 10), (5, 6, 11, 12), (1, 6, 12, 14), (0, 1, 5, 6), (6, 0, 13, 13),
)


def edges_frame(spark: SparkSession, rows) -> DataFrame:
    """Edges from (src, dst, start, end[, weight]) tuples."""
    return spark.createDataFrame([(*map(int, r[:4]), float(r[4]) if len(r) > 4 else 1.0) for r in rows], "src long, dst long, t_start long, t_end long, weight double")


def tiny(spark: SparkSession) -> DataFrame:
    return edges_frame(spark, TINY)
