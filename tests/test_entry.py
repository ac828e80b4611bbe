"""Queries and their twins on the smallest tables; the driver compares all of them at the next size."""

import os

import pytest

import __spark_entry__ as entry
from spanwalk.streaming.contacts import OnlineArrival
from spanwalk.sources.graphs import TINY, edges_frame

DATA = "/root/testdata/sf0.001"
SOME = ("m01_ea_relay_strict", "m02_ld_relay", "p02_vertex_set_ops", "x05_contained", "m07_kcore_relay_k3", "o_asof_join", "o_rollup", "o_stream_tumbling")


def test_every_twin_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.skipif(not os.path.isdir(DATA), reason="needs the given tables")
@pytest.mark.parametrize("name", SOME)
def test_twins(spark, name):
    import duckdb

    con = duckdb.connect()
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{DATA}/{t}.parquet'")
    df = entry.queries()[name](spark, DATA)
    columns = sorted(df.columns)
    ours = sorted(map(str, map(tuple, df.select(*columns).collect())))
    theirs = sorted(map(str, con.execute(f"SELECT {', '.join(columns)} FROM ({entry.oracle_sql()[name]}) AS x").fetchall()))
    assert ours == theirs


@pytest.mark.skipif(not os.path.isdir(DATA), reason="needs the given tables")
def test_entry(spark):
    assert entry.entry(spark).count() > 0


def test_online_arrival(spark, tmp_path):
    """A stream of edges in any order gives the batch answer after its last batch."""
    for k, part in enumerate((TINY[7:], TINY[:7])):
        edges_frame(spark, part).coalesce(1).write.parquet(str(tmp_path / "in" / f"k={k}"))
    online = OnlineArrival(spark, 0, 0)
    stream = spark.readStream.schema("src long, dst long, t_start long, t_end long, weight double, k int").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    q = stream.writeStream.foreachBatch(online).option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start()
    q.awaitTermination()
    assert {(r.v, r.arrival) for r in online.arrivals().collect()} == {(0, 0), (1, 3), (2, 5), (3, 6), (4, 6), (5, 11), (6, 14)}


@pytest.mark.skipif(not os.path.isdir(DATA), reason="needs the given tables")
def test_synthetic_edges_of_given_events(spark):
    """One edge for every event, among the users of the table."""
    events = spark.read.parquet(f"{DATA}/events.parquet")
    found = entry.queries()["g_synthetic"](spark, DATA).cache()
    users = {r[0] for r in events.select("user_id").distinct().collect()}
    assert found.count() == events.count()
    assert {r.src for r in found.collect()} | {r.dst for r in found.collect()} <= users


@pytest.mark.skipif(not os.path.isdir(DATA), reason="needs the given tables")
def test_recursion_over_a_given_table(spark):
    """The last level holds what the table gives in one sum."""
    total = spark.read.parquet(f"{DATA}/lineitem.parquet").selectExpr("cast(sum(l_quantity * l_quantity) as bigint)").head()[0]
    rows = {r.n: r.s for r in entry.queries()["o_recursive_cte"](spark, DATA).collect()}
    assert rows[max(rows)] == total
    test_twins(spark, "o_recursive_cte")


@pytest.mark.skipif(not os.path.isdir(DATA), reason="needs the given tables")
def test_table_function_over_a_given_table(spark):
    """Five windows for every user, back from the last event."""
    users = spark.read.parquet(f"{DATA}/events.parquet").select("user_id").distinct().count()
    assert entry.queries()["o_udtf_windows"](spark, DATA).count() == 5 * users
    test_twins(spark, "o_udtf_windows")
