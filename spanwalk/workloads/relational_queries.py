"""Queries for the operators around the graph methods: sources, joins, aggregation, windows, functions, streams."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..functions import user_defined
from ..functions.statistics import exact_percentile
from ..operators.graph import TemporalGraph
from ..operators.temporal_joins import asof_join, interval_join, sessions, top_per_key
from ..session import settle, shared_dir, ship
from ..sources.files import read_edges, write_bucketed, write_edges
from ..sources.graphs import graph_sql, load_graph
from ..streaming import contacts, histograms
from .graph_queries import query

_RELAY = graph_sql("relay", "duckdb")
_TRADE = graph_sql("trade", "duckdb")
_DAY = 86_400_000_000
_US = "timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', ts)"


def _table(spark, sf, name):
    return spark.read.parquet(f"{sf}/{name}.parquet")


def _scratch(spark) -> str:
    return f"{shared_dir(spark)}/files-{uuid.uuid4().hex}"


# ---- sources and sinks ----------------------------------------------------------------------

for _kind in ("parquet", "orc", "csv", "json", "text"):
    def _round_trip(spark, sf, kind=_kind):
        edges, path = load_graph(spark, sf, "relay").select("src", "dst", "t_start", "t_end", "weight"), _scratch(spark)
        if kind == "text":
            edges.select(F.concat_ws(" ", "src", "dst", "t_start", "t_end", "weight")).write.text(path)
        else:
            write_edges(edges, path, kind=kind)
        return read_edges(spark, path, kind).groupBy("src").agg(F.count("*").alias("m"), F.sum("t_end").alias("ends"))

    query(f"o_source_{_kind}", f"SELECT src, count(*) AS m, CAST(sum(t_end) AS BIGINT) AS ends FROM ({_RELAY}) AS g GROUP BY src")(_round_trip)


@query("o_sink_slices", f"SELECT src, dst, t_start, t_end FROM ({_TRADE}) AS g WHERE t_start >= 9900 AND t_start < 10000")
def o_sink_slices(spark, sf):
    path = _scratch(spark)
    write_edges(load_graph(spark, sf, "trade"), path, slice_width=100)
    return spark.read.parquet(path).where("slice = 99 and t_start >= 9900 and t_start < 10000").select("src", "dst", "t_start", "t_end")


@query("o_sink_bucketed", f"SELECT src, count(*) AS m FROM ({_TRADE}) AS g GROUP BY src")
def o_sink_bucketed(spark, sf):
    name = f"edges_{uuid.uuid4().hex}"
    write_bucketed(load_graph(spark, sf, "trade"), name, 8)
    out = settle(spark.table(name).groupBy("src").agg(F.count("*").alias("m")))
    spark.sql(f"DROP TABLE {name}")
    return out


# ---- filters, joins -------------------------------------------------------------------------

@query("o_filters", f"SELECT src AS tail, dst AS head, t_end - t_start AS span, CAST(weight AS BIGINT) AS w FROM ({_TRADE}) AS g WHERE t_start BETWEEN 9000 AND 9200 AND src IN (1, 2, 3, 5, 8, 13) AND weight IS NOT NULL")
def o_filters(spark, sf):
    e = load_graph(spark, sf, "trade").where(F.col("t_start").between(9000, 9200) & F.col("src").isin(1, 2, 3, 5, 8, 13) & F.col("weight").isNotNull())
    return e.select(F.col("src").alias("tail"), F.col("dst").alias("head"), (F.col("t_end") - F.col("t_start")).alias("span"), F.round("weight").cast("long").alias("w"))


for _hint in ("broadcast", "merge", "shuffle_hash"):
    query(f"o_equi_join_{_hint}", f"SELECT c_mktsegment, count(*) AS n FROM ({_TRADE}) AS g JOIN customer ON c_custkey = src GROUP BY c_mktsegment")(
        lambda spark, sf, hint=_hint: load_graph(spark, sf, "trade").join(_table(spark, sf, "customer").select("c_custkey", "c_mktsegment").hint(hint), F.col("src") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"))
    )


@query("o_interval_join", f"WITH g AS ({_TRADE}), a AS (SELECT src AS s1, dst AS d1, t_start AS a0, t_end AS a1 FROM g WHERE src < 20), b AS (SELECT src AS s2, dst AS d2, t_start AS b0, t_end AS b1 FROM g WHERE src BETWEEN 20 AND 39) SELECT s1, s2, count(*) AS n FROM a JOIN b ON a0 <= b1 AND b0 <= a1 GROUP BY s1, s2")
def o_interval_join(spark, sf):
    g = load_graph(spark, sf, "trade")
    a = g.where("src < 20").select(F.col("src").alias("s1"), F.col("dst").alias("d1"), F.col("t_start").alias("a0"), F.col("t_end").alias("a1"))
    b = g.where("src between 20 and 39").select(F.col("src").alias("s2"), F.col("dst").alias("d2"), F.col("t_start").alias("b0"), F.col("t_end").alias("b1"))
    return interval_join(a, b, 15, "a0", "a1", "b0", "b1").groupBy("s1", "s2").agg(F.count("*").alias("n"))


@query("o_asof_join", "SELECT e.event_id, p.value AS prev_value FROM (SELECT * FROM events WHERE event_type = 'error') AS e ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'purchase') AS p ON e.user_id = p.user_id AND e.ts > p.ts")
def o_asof_join(spark, sf):
    e = _table(spark, sf, "events")
    left = e.where("event_type = 'error'").select("event_id", "user_id", "ts")
    right = e.where("event_type = 'purchase'").select("user_id", "ts", "value")
    return asof_join(left, right, ["user_id"], "ts", ["value"]).select("event_id", "prev_value")


@query("o_semi_anti_outer", f"WITH g AS ({_RELAY}), a AS (SELECT src AS v, count(*) AS o FROM g WHERE weight > 170 GROUP BY src), b AS (SELECT dst AS v, count(*) AS i FROM g WHERE weight > 170 GROUP BY dst) SELECT coalesce(a.v, b.v) AS v, coalesce(o, 0) AS outs, coalesce(i, 0) AS ins, a.v IS NOT NULL AND b.v IS NOT NULL AS both_ways FROM a FULL JOIN b ON a.v = b.v")
def o_semi_anti_outer(spark, sf):
    g = load_graph(spark, sf, "relay").where("weight > 170")
    a = g.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("o"))
    b = g.groupBy(F.col("dst").alias("v")).agg(F.count("*").alias("i"))
    return a.join(b, "v", "full").select("v", F.coalesce("o", F.lit(0)).alias("outs"), F.coalesce("i", F.lit(0)).alias("ins"), (F.col("o").isNotNull() & F.col("i").isNotNull()).alias("both_ways"))


@query("o_isolated", f"SELECT DISTINCT user_id AS v FROM events WHERE user_id NOT IN (SELECT src FROM ({_RELAY}) AS g WHERE weight > 150)")
def o_isolated(spark, sf):
    users = _table(spark, sf, "events").select(F.col("user_id").alias("v")).distinct()
    return users.join(load_graph(spark, sf, "relay").where("weight > 150").select(F.col("src").alias("v")), "v", "left_anti")


# ---- aggregation ----------------------------------------------------------------------------

@query("o_aggregates", f"SELECT src, count(*) AS m, count(DISTINCT dst) AS neighbours, min(t_start) AS first, max(t_end) AS last, arg_max(dst, t_start) AS latest, CAST(sum(CAST(round(weight * 100) AS BIGINT)) AS BIGINT) AS cents, round(CAST(sum(CAST(round(weight * 100) AS BIGINT)) AS BIGINT) / (count(*) * 100), 4) AS mean_weight FROM ({_RELAY}) AS g GROUP BY src")
def o_aggregates(spark, sf):
    return load_graph(spark, sf, "relay").groupBy("src").agg(F.count("*").alias("m"), F.countDistinct("dst").alias("neighbours"), F.min("t_start").alias("first"), F.max("t_end").alias("last"), F.max_by("dst", "t_start").alias("latest"), F.sum(F.round(F.col("weight") * 100).cast("long")).alias("cents"), F.round(F.sum(F.round(F.col("weight") * 100).cast("long")) / (F.count("*") * 100), 4).alias("mean_weight"))


@query("o_approx_distinct")
def o_approx_distinct(spark, sf):
    return load_graph(spark, sf, "relay").groupBy("src").agg(F.approx_count_distinct("dst", 0.02).alias("neighbours"))


@query("o_percentile", f"SELECT CAST(quantile_disc(t_end - t_start, 0.5) AS BIGINT) AS p50, CAST(quantile_disc(t_end - t_start, 0.99) AS BIGINT) AS p99 FROM ({_RELAY}) AS g")
def o_percentile(spark, sf):
    spans = settle(load_graph(spark, sf, "relay").select((F.col("t_end") - F.col("t_start")).alias("span")))
    return spark.createDataFrame([(exact_percentile(spans, "span", 0.5), exact_percentile(spans, "span", 0.99))], "p50 long, p99 long")


_MONTHLY = "SELECT n_name, r_name, EXTRACT(YEAR FROM o_orderdate)::BIGINT AS y, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def _orders_by_place(spark, sf):
    o, c, n, r = (_table(spark, sf, x) for x in ("orders", "customer", "nation", "region"))
    joined = o.join(c, o.o_custkey == c.c_custkey).join(F.broadcast(n), c.c_nationkey == n.n_nationkey).join(F.broadcast(r), n.n_regionkey == r.r_regionkey)
    return joined.select("n_name", "r_name", F.year("o_orderdate").cast("long").alias("y"))


query("o_rollup", _MONTHLY + " GROUP BY ROLLUP (r_name, n_name, y)")(lambda spark, sf: _orders_by_place(spark, sf).rollup("r_name", "n_name", "y").agg(F.count("*").alias("n")))
query("o_cube", _MONTHLY.replace("n_name, r_name,", "r_name,") + " GROUP BY CUBE (r_name, y)")(lambda spark, sf: _orders_by_place(spark, sf).cube("r_name", "y").agg(F.count("*").alias("n")))


@query("o_grouping_sets", _MONTHLY + " GROUP BY GROUPING SETS ((r_name, n_name), (y), ())")
def o_grouping_sets(spark, sf):
    return spark.sql("SELECT n_name, r_name, y, count(*) AS n FROM {d} GROUP BY GROUPING SETS ((r_name, n_name), (y), ())", d=_orders_by_place(spark, sf))


_KINDS = ["click", "error", "purchase", "signup", "view"]


@query("o_pivot", "SELECT user_id, " + ", ".join(f"count(*) FILTER (WHERE event_type = '{k}') AS n_{k}" for k in _KINDS) + " FROM events GROUP BY user_id")
def o_pivot(spark, sf):
    p = _table(spark, sf, "events").groupBy("user_id").pivot("event_type", _KINDS).agg(F.count(F.lit(1)))
    return p.select("user_id", *[F.coalesce(k, F.lit(0)).alias(f"n_{k}") for k in _KINDS])


# ---- windows, order, sets -------------------------------------------------------------------

@query("o_window_functions", f"""SELECT event_id, row_number() OVER w AS rn, rank() OVER (PARTITION BY user_id ORDER BY event_type) AS rk, dense_rank() OVER (PARTITION BY user_id ORDER BY event_type) AS dr,
  ntile(4) OVER w AS quarter, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS last3, min(value) OVER w AS least FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)""")
def o_window_functions(spark, sf):
    w, k = W.partitionBy("user_id").orderBy("ts"), W.partitionBy("user_id").orderBy("event_type")
    return _table(spark, sf, "events").select(
        "event_id", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(k).cast("long").alias("rk"), F.dense_rank().over(k).cast("long").alias("dr"), F.ntile(4).over(w).cast("long").alias("quarter"),
        F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.round(F.sum("value").over(w.rowsBetween(-2, 0)), 4).alias("last3"), F.min("value").over(w).alias("least"),
    )


@query("o_range_frame", f"SELECT src, dst, t_start, count(*) OVER (PARTITION BY src ORDER BY t_start RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS day_before FROM ({_RELAY}) AS g")
def o_range_frame(spark, sf):
    w = W.partitionBy("src").orderBy("t_start").rangeBetween(-86_400_000_000, 0)
    return load_graph(spark, sf, "relay").select("src", "dst", "t_start", F.count("*").over(w).alias("day_before"))


@query("o_sessions", "WITH e AS (SELECT user_id, epoch_us(ts) AS t FROM events), m AS (SELECT *, CASE WHEN t - lag(t) OVER (PARTITION BY user_id ORDER BY t) <= 86400000000 THEN 0 ELSE 1 END AS fresh FROM e), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY t ROWS UNBOUNDED PRECEDING) AS session FROM m) SELECT user_id, CAST(session AS BIGINT) AS session, min(t) AS start_us, max(t) AS end_us, count(*) AS n FROM s GROUP BY user_id, session")
def o_sessions(spark, sf):
    e = _table(spark, sf, "events").selectExpr("user_id", f"{_US} AS t")
    return sessions(e, "user_id", "t", 86_400_000_000).withColumnsRenamed({"start": "start_us", "end": "end_us"})


@query("o_top_sources", f"SELECT src AS v, count(*) AS m FROM ({_TRADE}) AS g GROUP BY src ORDER BY m DESC, v LIMIT 100")
def o_top_sources(spark, sf):
    return load_graph(spark, sf, "trade").groupBy(F.col("src").alias("v")).agg(F.count("*").alias("m")).orderBy(F.desc("m"), "v").limit(100)


@query("o_top_per_key", "SELECT user_id, event_id, value FROM events QUALIFY row_number() OVER (PARTITION BY user_id ORDER BY value DESC, event_id) <= 3")
def o_top_per_key(spark, sf):
    return top_per_key(_table(spark, sf, "events"), ["user_id"], [F.desc("value"), F.col("event_id")], 3).select("user_id", "event_id", "value")


@query("o_set_ops", f"WITH g AS ({_TRADE}) SELECT 'union' AS op, count(*) AS n FROM (SELECT src FROM g UNION SELECT dst FROM g) UNION ALL SELECT 'intersect', count(*) FROM (SELECT src FROM g WHERE weight > 60000 INTERSECT SELECT dst FROM g WHERE weight > 60000) UNION ALL SELECT 'except', count(*) FROM (SELECT src FROM g EXCEPT SELECT dst FROM g WHERE weight > 60000)")
def o_set_ops(spark, sf):
    g = load_graph(spark, sf, "trade")
    src, dst, big = g.select("src"), g.select(F.col("dst").alias("src")), g.where("weight > 60000")
    parts = {"union": src.union(dst).distinct(), "intersect": big.select("src").intersect(big.select(F.col("dst").alias("src"))), "except": src.subtract(big.select(F.col("dst").alias("src")))}
    out = None
    for op, df in parts.items():
        row = df.agg(F.count("*").alias("n")).select(F.lit(op).alias("op"), "n")
        out = row if out is None else out.unionByName(row)
    return out


_EXISTS = "SELECT c_custkey, (SELECT max(o_totalprice) FROM {orders} AS o WHERE o.o_custkey = c.c_custkey) AS dearest FROM {customer} AS c WHERE EXISTS (SELECT 1 FROM {orders} AS o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > (SELECT avg(o_totalprice) FROM {orders}))"
query("o_subqueries", _EXISTS.format(orders="orders", customer="customer"))(lambda spark, sf: spark.sql(_EXISTS, orders=_table(spark, sf, "orders"), customer=_table(spark, sf, "customer")))
_BY_QUANTITY = "SELECT CAST(l_quantity AS BIGINT) AS k, count(*) AS c FROM {lineitem} GROUP BY 1"
_RECURSIVE = "WITH RECURSIVE r(n, s) AS (SELECT k, c FROM {q} AS a WHERE k = 1 UNION ALL SELECT k, s + c * k * k FROM r JOIN {q} AS b ON k = n + 1) SELECT n, s FROM r"


@query("o_recursive_cte", _RECURSIVE.format(q=f"({_BY_QUANTITY.format(lineitem='lineitem')})"))
def o_recursive_cte(spark, sf):
    """Running sums of squared quantities, one quantity a level; the table is counted once, not at every level."""
    return spark.sql(_RECURSIVE, q=settle(spark.sql(_BY_QUANTITY, lineitem=_table(spark, sf, "lineitem"))))


# ---- functions ------------------------------------------------------------------------------

@query("o_date_functions", "SELECT o_orderkey, datediff('day', DATE '1970-01-01', o_orderdate::DATE)::BIGINT AS day_no, strftime(o_orderdate, '%Y-%m') AS month, (o_orderdate::DATE + 30)::VARCHAR AS later, dayofyear(o_orderdate)::BIGINT AS doy FROM orders")
def o_date_functions(spark, sf):
    d = F.col("o_orderdate").cast("date")
    return _table(spark, sf, "orders").select("o_orderkey", F.unix_date(d).cast("long").alias("day_no"), F.date_format("o_orderdate", "yyyy-MM").alias("month"), F.date_add(d, 30).cast("string").alias("later"), F.dayofyear(d).cast("long").alias("doy"))


@query("o_math_functions", "SELECT event_id, (user_id % 7 + 7) % 7 AS r, CAST(floor(value / 10) AS BIGINT) AS f, greatest(value, 100.0) AS g, least(value, 100.0) AS l, round(log2(value + 1), 6) AS b, round(exp(-value / 100), 6) AS e FROM events")
def o_math_functions(spark, sf):
    v = F.col("value")
    return _table(spark, sf, "events").select("event_id", F.pmod("user_id", F.lit(7)).alias("r"), F.floor(v / 10).alias("f"), F.greatest(v, F.lit(100.0)).alias("g"), F.least(v, F.lit(100.0)).alias("l"), F.round(F.log2(v + 1), 6).alias("b"), F.round(F.exp(-v / 100), 6).alias("e"))


@query("o_string_functions", "SELECT c_custkey, concat_ws('/', c_mktsegment, c_name) AS label, split_part(c_name, '#', 2) AS tail, regexp_extract(c_name, '0*([0-9]+)$', 1) AS number, lpad(CAST(c_custkey AS VARCHAR), 8, '0') AS padded, upper(substring(c_mktsegment, 1, 3)) AS short FROM customer")
def o_string_functions(spark, sf):
    c = _table(spark, sf, "customer")
    return c.select("c_custkey", F.concat_ws("/", "c_mktsegment", "c_name").alias("label"), F.split_part("c_name", F.lit("#"), F.lit(2)).alias("tail"), F.regexp_extract("c_name", "0*([0-9]+)$", 1).alias("number"), F.lpad(F.col("c_custkey").cast("string"), 8, "0").alias("padded"), F.upper(F.substring("c_mktsegment", 1, 3)).alias("short"))


@query("o_arrays_json", "SELECT user_id, count(*) AS n, CAST(sum(CAST(json_extract(props, '$.k') AS BIGINT)) AS BIGINT) AS k_sum, max(CAST(json_extract(props, '$.k') AS BIGINT)) AS k_max FROM events GROUP BY user_id")
def o_arrays_json(spark, sf):
    k = F.from_json("props", "k long")["k"]
    packed = _table(spark, sf, "events").groupBy("user_id").agg(F.collect_list(k).alias("ks"))
    return packed.select("user_id", F.size("ks").cast("long").alias("n"), F.aggregate("ks", F.lit(0).cast("long"), lambda a, x: a + x).alias("k_sum"), F.array_max(F.array_sort("ks")).alias("k_max"))


@query("o_sampling_by_id", f"SELECT src, dst, t_start, t_end FROM ({_TRADE}) AS g WHERE src % 10 = 3")
def o_sampling_by_id(spark, sf):
    return load_graph(spark, sf, "trade").where("src % 10 = 3").select("src", "dst", "t_start", "t_end")


@query("o_sampling")
def o_sampling(spark, sf):
    """The same tenth of the vertices on every run, and all their edges."""
    return load_graph(spark, sf, "trade").where(F.pmod(F.xxhash64("src", F.lit(3)), F.lit(10)) == 0).select("src", "dst", "t_start", "t_end")


@query("o_udf_scalar", "SELECT event_id, round(ln(1 + greatest(value, 0)), 6) AS l FROM events")
def o_udf_scalar(spark, sf):
    ship(spark)
    return _table(spark, sf, "events").select("event_id", F.round(user_defined.log_scale("value"), 6).alias("l"))


@query("o_udaf_burstiness", f"WITH g AS ({_RELAY}), l AS (SELECT src, t_start - lag(t_start) OVER (PARTITION BY src ORDER BY t_start) AS gap FROM g) SELECT src AS v, round((stddev_pop(gap) - avg(gap)) / (stddev_pop(gap) + avg(gap)), 6) AS b FROM l GROUP BY src HAVING stddev_pop(gap) + avg(gap) > 0")
def o_udaf_burstiness(spark, sf):
    ship(spark)
    return load_graph(spark, sf, "relay").groupBy(F.col("src").alias("v")).agg(F.round(user_defined.burstiness("t_start"), 6).alias("b")).where("b is not null")


@query("o_udtf_windows", "SELECT user_id, k::INTEGER AS k, upto - (k + 1) * 3600000000 AS from_t, upto - k * 3600000000 AS to_t FROM (SELECT user_id, epoch_us(max(ts)) AS upto FROM events GROUP BY user_id) AS u, (SELECT unnest(range(5)) AS k) AS r")
def o_udtf_windows(spark, sf):
    ship(spark)
    user_defined.register(spark)
    last = _table(spark, sf, "events").selectExpr("user_id", f"{_US} AS t").groupBy("user_id").agg(F.max("t").alias("upto"))
    return spark.sql("SELECT user_id, k, `start` AS from_t, `end` AS to_t FROM {u} AS u, LATERAL recent_windows(u.upto, 3600000000L, 5)", u=last)


@query("o_sql_views", f"WITH g AS ({_RELAY}), v AS (SELECT src AS v FROM g UNION SELECT dst FROM g) SELECT v, count(t_end) AS m FROM v LEFT JOIN g ON src = v AND weight > 150 GROUP BY v")
def o_sql_views(spark, sf):
    TemporalGraph(load_graph(spark, sf, "relay")).create_views("relay")
    return spark.sql("SELECT v, count(t_end) AS m FROM relay_vertices LEFT JOIN relay_edges ON src = v AND weight > 150 GROUP BY v")


# ---- streams --------------------------------------------------------------------------------

def _stream(spark, sf, files_per_trigger=1):
    return contacts.event_stream(spark, f"{sf}/events.parque[t]", files_per_trigger)  # a pattern, so that a single file is a source as well as a folder


@query("o_stream_tumbling", "SELECT epoch_us(time_bucket(INTERVAL 1 DAY, ts)) AS start_us, event_type, count(*) AS n FROM events GROUP BY ALL")
def o_stream_tumbling(spark, sf):
    done = contacts.run_to_end(contacts.tumbling_counts(_stream(spark, sf)), "complete")
    return done.select(F.unix_micros("w.start").alias("start_us"), "event_type", "n")


@query("o_stream_sliding", "SELECT epoch_us(time_bucket(INTERVAL 6 HOUR, ts) - k * INTERVAL 6 HOUR) AS start_us, event_type, count(*) AS n FROM events, (SELECT unnest(range(4)) AS k) AS s GROUP BY ALL")
def o_stream_sliding(spark, sf):
    done = contacts.run_to_end(contacts.tumbling_counts(_stream(spark, sf), "1 day", slide="6 hours"), "complete")
    return done.select(F.unix_micros("w.start").alias("start_us"), "event_type", "n")


@query("o_stream_sessions", "WITH m AS (SELECT user_id, ts, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) < 1800000000 THEN 0 ELSE 1 END AS fresh FROM events), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM m) SELECT user_id, epoch_us(min(ts)) AS start_us, count(*) AS n FROM s GROUP BY user_id, k")
def o_stream_sessions(spark, sf):
    done = contacts.run_to_end(contacts.session_counts(_stream(spark, sf)), "complete")
    return done.select("user_id", F.unix_micros("w.start").alias("start_us"), "n")


@query("o_stream_dedup", "SELECT DISTINCT user_id, event_type FROM events")
def o_stream_dedup(spark, sf):
    """Without a watermark: files needn't be in order of time, no row is late, and a batch may hold many files."""
    kinds = ["user_id", "event_type"]
    return contacts.run_to_end(contacts.without_repeats(_stream(spark, sf, 16).select(*kinds), kinds, late=None))


@query("o_stream_join", "SELECT a.event_id AS id0, b.event_id AS id1 FROM events AS a JOIN events AS b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 DAY")
def o_stream_join(spark, sf):
    a, b = _stream(spark, sf).where("event_type = 'click'"), _stream(spark, sf).where("event_type = 'purchase'")
    return contacts.run_to_end(contacts.two_hop_contacts(a, b, "1 DAY", "2 days")).select("id0", "id1")


@query("o_stream_static_join", "SELECT event_type, count(*) AS n FROM events JOIN customer ON c_custkey = user_id WHERE c_acctbal > 0 GROUP BY event_type")
def o_stream_static_join(spark, sf):
    rich = _table(spark, sf, "customer").where("c_acctbal > 0").select(F.col("c_custkey").alias("user_id"))
    return contacts.run_to_end(_stream(spark, sf).join(rich, "user_id").groupBy("event_type").agg(F.count("*").alias("n")), "complete")


@query("o_stream_degrees", "SELECT user_id, count(*) AS m, max(value) AS largest FROM events GROUP BY user_id")
def o_stream_degrees(spark, sf):
    """Degrees of contact kept up to date by a stream."""
    return contacts.run_to_end(_stream(spark, sf).groupBy("user_id").agg(F.count("*").alias("m"), F.max("value").alias("largest")), "complete")


@query("o_stream_stateful", "SELECT user_id, max(gap) AS longest_gap FROM (SELECT user_id, epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) AS gap FROM events) AS g GROUP BY user_id HAVING max(gap) IS NOT NULL")
def o_stream_stateful(spark, sf):
    """Longest silence of every user, from a custom state kept per key."""
    ship(spark)
    found = contacts.run_to_end(contacts.longest_gaps(_stream(spark, sf)), "update")
    return found.groupBy("user_id").agg(F.max("longest_gap").alias("longest_gap"))


@query("o_stream_late", f"""WITH t AS (SELECT *, epoch_us(ts) AS u FROM events), c AS (SELECT (min(u) + max(u)) // 2 AS cut, max(u) AS hi FROM t)
  SELECT epoch_us(time_bucket(INTERVAL 1 DAY, ts)) AS start_us, event_type, count(*) AS n FROM t, c WHERE (event_id % 2 = 0 OR u >= cut - 2 * {_DAY}) AND epoch_us(time_bucket(INTERVAL 1 DAY, ts)) + {_DAY} <= hi - 3600000000 GROUP BY ALL""")
def o_stream_late(spark, sf):
    """Events of odd ids of the first half of the time, but for its last two days, arrive when their windows are closed: they count nowhere."""
    path = _scratch(spark)
    timed = _table(spark, sf, "events").withColumn("u", F.expr(_US))
    ends = timed.agg(F.min("u").alias("lo"), F.max("u").alias("hi")).head()
    cut = (ends.lo + ends.hi) // 2
    late = (F.col("event_id") % 2 == 1) & (F.col("u") < cut - 2 * _DAY)
    for k, part in enumerate(((F.col("u") < cut) & ~late, F.col("u") >= cut, late)):
        timed.where(part).drop("u").coalesce(1).write.parquet(f"{path}/{k}")
    done = contacts.run_to_end(contacts.tumbling_counts(contacts.event_stream(spark, f"{path}/*")))
    return done.select(F.unix_micros("w.start").alias("start_us"), "event_type", "n")


@query("o_stream_histogram", f"""WITH g AS ({graph_sql('nations', 'duckdb')}), r AS (SELECT src AS v, min(t_start) AS s_lo, max(t_start) AS s_hi, min(t_end - t_start) AS d_lo, max(t_end - t_start) AS d_hi FROM g GROUP BY src HAVING count(*) >= 1000),
  k AS (SELECT v, min(i) FILTER (WHERE (s_hi >> i) - (s_lo >> i) < 100) AS x, min(i) FILTER (WHERE (d_hi >> i) - (d_lo >> i) < 100) AS y FROM r, (SELECT unnest(range(63)) AS i) AS p GROUP BY v)
  SELECT v, CAST(x AS INTEGER) AS kx, CAST(y AS INTEGER) AS ky, CAST(t_start >> x AS BIGINT) AS bx, CAST((t_end - t_start) >> y AS BIGINT) AS by_cell, count(*) AS n FROM g JOIN k ON v = src GROUP BY ALL""")
def o_stream_histogram(spark, sf):
    """Histograms of vertices of 1000 edges and more, after a stream of edges in three batches."""
    path, upkeep = _scratch(spark), histograms.HistogramUpkeep(spark)
    edges = load_graph(spark, sf, "nations").select("src", "dst", "t_start", "t_end")
    edges.repartition(3).write.parquet(path)
    stream = spark.readStream.schema(edges.schema).option("maxFilesPerTrigger", 1).parquet(path)
    stream.writeStream.foreachBatch(upkeep).option("checkpointLocation", f"{path}-progress").trigger(availableNow=True).start().awaitTermination()
    return upkeep.current().at_least(1000).cells.withColumnRenamed("by", "by_cell")
