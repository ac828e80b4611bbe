"""Joins on time that Spark has no operator for."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W


def asof_join(left: DataFrame, right: DataFrame, on: list[str], time: str, values: list[str], strict: bool = True) -> DataFrame:
    """Each left row with the values of the last right row of its key at an earlier time (or the same, if not strict).

    Both sides go through one shuffle by key and one sort, instead of a range join. Of right rows
    at one time the largest by value is taken.
    """
    tag = 0 if strict else 2  # left rows come before or after right rows of the same time
    a = left.withColumns({"__side": F.lit(tag), "__value": F.lit(None).cast(right.select(F.struct(time, *values)).schema[0].dataType)}).withColumn("__row", F.struct(*left.columns))
    b = right.select(*on, F.col(time), F.lit(1).alias("__side"), F.struct(time, *values).alias("__value"))
    both = a.select(*on, time, "__side", "__value", "__row").unionByName(b.withColumn("__row", F.lit(None).cast(a.schema["__row"].dataType)))
    order = W.partitionBy(*on).orderBy(time, "__side", "__value").rowsBetween(W.unboundedPreceding, 0)
    found = both.withColumn("__last", F.last("__value", ignorenulls=True).over(order)).where(F.col("__side") == tag)
    return found.select("__row.*", *[F.col(f"__last.{v}").alias(f"prev_{v}") for v in values], F.col(f"__last.{time}").alias(f"prev_{time}"))


def interval_join(left: DataFrame, right: DataFrame, width: int, l_start: str, l_end: str, r_start: str, r_end: str, on: list[str] = ()) -> DataFrame:
    """Pairs of rows whose closed integer intervals meet, columns of both sides (names must differ).

    Both sides are spread over the time buckets that they touch and joined on the bucket; a pair
    is kept only in the first bucket that both touch, so no pair appears twice and no cross join
    is needed. `width` should be near the typical length.
    """
    bucket = lambda s, e: F.explode(F.sequence(F.floor(F.col(s) / width), F.floor(F.col(e) / width)))
    a, b = left.withColumn("__bucket", bucket(l_start, l_end)), right.withColumn("__bucket", bucket(r_start, r_end))
    met = a.join(b, ["__bucket", *on])
    first = F.col("__bucket") == F.floor(F.greatest(l_start, r_start) / width)
    return met.where((F.col(l_start) <= F.col(r_end)) & (F.col(r_start) <= F.col(l_end)) & first).drop("__bucket")


def top_per_key(df: DataFrame, keys: list[str], order: list, k: int) -> DataFrame:
    """The first k rows of every key in the given order."""
    return df.withColumn("__place", F.row_number().over(W.partitionBy(*keys).orderBy(*order))).where(F.col("__place") <= k).drop("__place")


def sessions(events: DataFrame, key: str, time: str, gap: int) -> DataFrame:
    """(key, session, start, end, n): runs of events no more than `gap` apart, integer times."""
    order = W.partitionBy(key).orderBy(time)
    new = F.when(F.col(time) - F.lag(time).over(order) <= gap, 0).otherwise(1)
    marked = events.select(key, time, new.alias("__new")).withColumn("session", F.sum("__new").over(order.rowsBetween(W.unboundedPreceding, 0)))
    return marked.groupBy(key, "session").agg(F.min(time).alias("start"), F.max(time).alias("end"), F.count("*").alias("n"))
