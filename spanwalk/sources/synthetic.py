"""Synthetic temporal graphs: log-normal vertex popularity, Poisson arrivals, uniform durations."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..session import settle


def uniform(seed: int, tag: str, key: str = "id") -> Column:
    """A repeatable draw from (0, 1) for each row, whatever the partitions."""
    return (F.pmod(F.xxhash64(F.col(key), F.lit(seed), F.lit(tag)), F.lit(1 << 52)) + F.lit(0.5)) / float(1 << 52)


def normal(seed: int, tag: str, key: str = "id") -> Column:
    return F.sqrt(-2.0 * F.log(uniform(seed, tag + "-r", key))) * F.cos(2 * 3.141592653589793 * uniform(seed, tag + "-a", key))


def running_sum(df: DataFrame, value: str, order: str, out: str, chunk: int = 100_000) -> DataFrame:
    """Inclusive prefix sums in two passes: within chunks of `order`, then over the few chunk totals."""
    df = df.withColumn("__chunk", F.floor(F.col(order) / chunk))
    within = W.partitionBy("__chunk").orderBy(order)
    totals = df.groupBy("__chunk").agg(F.sum(value).alias("__total"))
    before = totals.withColumn("__before", F.coalesce(F.sum("__total").over(W.partitionBy(F.lit(0)).orderBy("__chunk").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
    return df.withColumn(out, F.sum(value).over(within)).join(before.select("__chunk", "__before"), "__chunk").withColumn(out, F.col(out) + F.col("__before")).drop("__chunk", "__before")


def synthetic_edges(spark: SparkSession, n: int | DataFrame, m: int | DataFrame, sigma: float = 1.0, mean_gap: float = 10.0, durations: tuple[int, int] = (1, 1000), seed: int = 1, burst: float = 0.0, buckets: int = 4096) -> DataFrame:
    """`m` edges among `n` vertices, or one for each row of a frame of ids among the vertices of another.

    A vertex's share of the edges is proportional to exp(sigma * normal). Shares are laid end to
    end on [0, 1) and cut into `buckets`, so that a draw finds its vertex by an equi-join on its
    bucket. With `burst`, that share of the vertices has its edges within a slice of time of its own.
    """
    named = lambda ids: spark.range(ids) if isinstance(ids, int) else ids.select(F.col(ids.columns[0]).cast("long").alias("id"))
    weights = named(n).select(F.col("id").alias("v"), F.exp(sigma * normal(seed, "weight")).alias("w"))
    laid = running_sum(settle(weights), "w", "v", "upto")
    count, top, total = laid.agg(F.count("*"), F.max("v"), F.coalesce(F.max("upto"), F.lit(1.0))).head()
    buckets = max(buckets, 1 << count.bit_length())  # a bucket meets a few vertices, however many there are
    bands = laid.select("v", ((F.col("upto") - F.col("w")) / total).alias("lo"), (F.col("upto") / total).alias("hi"))
    bands = settle(bands.withColumn("b", F.explode(F.sequence(F.floor(F.col("lo") * buckets), F.least(F.floor(F.col("hi") * buckets), F.lit(buckets - 1))))))
    draws = running_sum(named(m).withColumn("gap", F.ceil(-mean_gap * F.log(uniform(seed, "gap")))), "gap", "id", "t_start")
    draws = draws.withColumns({"u": uniform(seed, "src"), "w": uniform(seed, "dst")})

    def pick(df: DataFrame, draw: str, out: str) -> DataFrame:
        side = bands.select(F.col("v").alias(out), "lo", "hi", F.col("b").alias("__b"))
        hit = (F.floor(F.col(draw) * buckets) == F.col("__b")) & (F.col(draw) >= F.col("lo")) & ((F.col(draw) < F.col("hi")) | (F.col(out) == top))
        return df.join(side, hit).drop("lo", "hi", "__b", draw)

    edges = pick(pick(draws, "u", "src"), "w", "dst")
    span = F.lit(float(mean_gap * (m if isinstance(m, int) else m.count())))
    if burst:
        slow = uniform(seed, "burst", "src") < burst
        slot = F.floor(uniform(seed, "slice", "src") * span * 0.95) + F.floor(F.col("t_start") * 0.05)
        edges = edges.withColumn("t_start", F.when(slow, slot).otherwise(F.col("t_start")))
    lo, hi = durations
    length = lo + F.pmod(F.xxhash64("id", F.lit(seed), F.lit("duration")), F.lit(hi - lo + 1))
    return edges.select("src", "dst", F.col("t_start").cast("long"), (F.col("t_start") + length).cast("long").alias("t_end"), F.lit(1.0).alias("weight"))


def with_uniform_end(df: DataFrame, lo: int, hi: int, key: Column) -> DataFrame:
    """Ends for edges that only have a start: a length in [lo, hi] taken from integer arithmetic on `key`."""
    return df.withColumn("t_end", F.col("t_start") + lo + F.pmod(key, F.lit(hi - lo + 1)))
