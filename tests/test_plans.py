"""Physical plans: what is pushed down, pruned and moved."""

from pyspark.sql import functions as F

from spanwalk.functions.predicates import Ordering, Window
from spanwalk.operators.edgemap import expand_forward, window_edges
from spanwalk.operators.graph import TemporalGraph
from spanwalk.session import release, settle_partitioned
from spanwalk.sources.files import read_edges, write_edges
from spanwalk.sources.graphs import edges_frame


def plan_of(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_window_reaches_the_scan(spark, tmp_path):
    path = str(tmp_path / "edges")
    write_edges(edges_frame(spark, [(k % 9, k % 7, k, k + 3) for k in range(500)]), path, slice_width=100)
    g = TemporalGraph(read_edges(spark, path))
    plan = plan_of(g.restrict(Window(100, 200)).edges.select("src", "dst"))
    assert "GreaterThanOrEqual(t_start,100)" in plan and "LessThanOrEqual(t_end,200)" in plan
    assert "weight" not in plan.split("ReadSchema:")[1]
    pruned = plan_of(spark.read.parquet(path).where("slice = 3").select("src"))
    assert "PartitionFilters: [isnotnull(slice" in pruned


def test_only_the_frontier_moves(spark):
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        edges = window_edges(edges_frame(spark, [(k % 9, k % 7, k, k + 3) for k in range(500)]))
        frontier = spark.range(5).select(F.lit(0).alias("source"), F.col("id").alias("v"), F.lit(10).cast("long").alias("label"))
        df = expand_forward(frontier, edges, Ordering.STRICTLY_SUCCEEDS)
        df.collect()
        plan = plan_of(df)
        moved = [line for line in plan.split("Initial Plan")[0].splitlines() if "Exchange hashpartitioning" in line]
        assert len(moved) == 1 and "v#" in moved[0], plan
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def test_ranks_and_shares_lie_together(spark):
    """What PageRank joins in every round is laid out alike: neither side moves."""
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        shares = window_edges(edges_frame(spark, [(k % 9, k % 7, k, k + 3) for k in range(500)]), columns=("src", "dst"), partitions=parts)
        rank = settle_partitioned(spark.range(9).select(F.col("id").alias("v"), F.lit(0.5).alias("rank")), parts, "v")
        plan = plan_of(shares.meet(rank))
        assert "Join" in plan and "Exchange" not in plan, plan
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def test_released_frames_leave_no_files(spark):
    import os

    frame = settle_partitioned(spark.range(50).toDF("v"), 2, "v")
    path = frame._jdf.queryExecution().analyzed().collectLeaves().apply(0).rdd().getCheckpointFile().get().replace("file:", "")
    assert os.path.isdir(path)
    release(frame.select("v"))
    assert not os.path.exists(path)


def test_hubs_are_dealt_out(spark):
    rows = edges_frame(spark, [(0 if k % 3 else k % 11, k % 7, k, k + 3) for k in range(600)])
    plain, dealt = window_edges(rows), window_edges(rows, hub_rows=50)
    assert plain.hubs is None and dealt.hubs.where("v = 0 and salts > 5").count() == 1
    frontier = spark.range(11).select(F.lit(0).alias("source"), F.col("id").alias("v"), F.lit(10).cast("long").alias("label"))
    both = [sorted(map(tuple, expand_forward(frontier, e, Ordering.STRICTLY_SUCCEEDS).select("v", "label", "src", "dst", "t_start", "t_end").collect())) for e in (plain, dealt)]
    assert both[0] == both[1] and len(both[0]) > 500
