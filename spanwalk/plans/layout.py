"""Adjacency layouts: offsets of a sorted edge array, and packed neighbour blocks."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..operators.graph import degrees
from .shards import SHARD_ROWS, with_shards


def csr_offsets(edges: DataFrame, orientation: str = "out", chunk: int = 100_000) -> DataFrame:
    """(v, first, m): where v's edges begin in the edge array sorted by v, and how many there are.

    Prefix sums in two passes: within chunks of vertices, then over the totals of the chunks.
    """
    deg = degrees(edges, orientation).withColumn("chunk", F.floor(F.col("v") / chunk))
    totals = deg.groupBy("chunk").agg(F.sum("m").alias("total"))
    before = totals.withColumn("before", F.coalesce(F.sum("total").over(W.partitionBy(F.lit(0)).orderBy("chunk").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
    within = F.coalesce(F.sum("m").over(W.partitionBy("chunk").orderBy("v").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    return deg.withColumn("within", within).join(before.select("chunk", "before"), "chunk").select("v", (F.col("before") + F.col("within")).cast("long").alias("first"), "m")


def adjacency_blocks(edges: DataFrame, orientation: str = "out", block_rows: int = 4096, shard_rows: int = SHARD_ROWS) -> DataFrame:
    """(v, shard, block, n, t_start_min, t_end_max, nbr, t_start, t_end, weight): neighbours in start order.

    The arrays hold the same edge in the same position. A hub is many rows of bounded length,
    and is numbered within ranges of start times rather than by one task.
    """
    v, nbr = ("src", "dst") if orientation == "out" else ("dst", "src")
    own = edges.select(F.col(v).alias("v"), F.col(nbr).alias("nbr"), "t_start", "t_end", "weight").join(degrees(edges, orientation), "v")
    order = W.partitionBy("v", "shard").orderBy("t_start", "t_end", "nbr", "weight")
    numbered = with_shards(own, "t_start", shard_rows).withColumn("block", F.floor((F.row_number().over(order) - 1) / block_rows).cast("long"))
    packed = numbered.groupBy("v", "shard", "block").agg(F.array_sort(F.collect_list(F.struct("t_start", "t_end", "nbr", "weight"))).alias("e"))
    return packed.select("v", "shard", "block", F.size("e").alias("n"), F.array_min("e.t_start").alias("t_start_min"), F.array_max("e.t_end").alias("t_end_max"), F.col("e.nbr").alias("nbr"), F.col("e.t_start").alias("t_start"), F.col("e.t_end").alias("t_end"), F.col("e.weight").alias("weight"))


def unpack_blocks(blocks: DataFrame, orientation: str = "out") -> DataFrame:
    """Edges from packed blocks."""
    v, nbr = ("src", "dst") if orientation == "out" else ("dst", "src")
    rows = blocks.select("v", F.explode(F.arrays_zip("nbr", "t_start", "t_end", "weight")).alias("e"))
    return rows.select(F.col("v").alias(v), F.col("e.nbr").alias(nbr), "e.t_start", "e.t_end", "e.weight")


def scan_neighbors(edges: DataFrame, vertices: DataFrame, lo_start: int, hi_end: int) -> DataFrame:
    """Edges of the given vertices inside [lo_start, hi_end], by reading their whole lists."""
    return edges.join(vertices.select(F.col("v").alias("src")), "src", "left_semi").where((F.col("t_start") >= lo_start) & (F.col("t_end") <= hi_end))
