"""Dividing the edges of very large vertices, so that no task has to hold one."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SHARD_ROWS, SHARDS = 1_000_000, 64


def with_shards(rows: DataFrame, axis: str, shard_rows: int = SHARD_ROWS) -> DataFrame:
    """`rows` (v, m, ...) with a `shard`: zero, or for vertices of more than `shard_rows` edges the quantile range of `axis`.

    Quantiles come from mergeable sketches; shards are in order of the axis and don't overlap in it.
    """
    hubs = rows.where(F.col("m") > shard_rows).groupBy("v").agg(F.percentile_approx(axis, [k / SHARDS for k in range(1, SHARDS)], 1000).alias("cuts"))
    number = F.coalesce(F.size(F.filter("cuts", lambda c: c < F.col(axis))), F.lit(0))
    return rows.join(hubs, "v", "left").withColumn("shard", number).drop("cuts")
