"""Two-dimensional histograms (start, duration) of every vertex, kept up to date over a stream of edges.

Widths of cells are powers of two and cells are counted from zero on, so where a vertex's range
outgrows `bins` cells on an axis, neighbouring cells are joined and no edge is read again. What
is kept therefore depends on the edges alone, not on their order or their batches.
"""

from __future__ import annotations

import uuid
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.histogram import BINS, clipped, covered
from ..session import shared_dir

_RANGES = "v long, m long, s_lo long, s_hi long, d_lo long, d_hi long"
_CELLS = "v long, kx int, ky int, bx long, by long, n long"


@dataclass(frozen=True)
class DyadicHistogram:
    ranges: DataFrame  # v, m, s_lo, s_hi, d_lo, d_hi
    cells: DataFrame  # v, kx, ky, bx, by, n: 2^kx starts and 2^ky durations a cell

    def at_least(self, cutoff: int) -> DyadicHistogram:
        """That of vertices with so many edges and more, those that are worth an index."""
        kept = self.ranges.where(F.col("m") >= cutoff)
        return DyadicHistogram(kept, self.cells.join(kept.select("v"), "v", "left_semi"))

    def estimate(self, asked: DataFrame) -> DataFrame:
        """(v, a, b, m, k_hat): edges of v expected inside [a, b], mass spread evenly over the values that a cell can hold of the vertex."""
        side = lambda b, k, lo, hi: [f"greatest({lo}, shiftleft({b}, {k}))", f"least({hi}, shiftleft({b} + 1, {k}) - 1)"]
        (s0, s1), (d0, d1) = side("bx", "kx", "s_lo", "s_hi"), side("by", "ky", "d_lo", "d_hi")
        rows = self.cells.join(self.ranges, "v").join(asked.select("v", "a", "b"), "v")
        wide = rows.selectExpr("v", "m", "n", "a", "b", *[f"CAST({x} AS DOUBLE) AS {name}" for x, name in ((s0, "s0"), (s1, "s1"), (d0, "d0"), (d1, "d1"))])
        share = wide.selectExpr("v", "m", "n", *clipped()).selectExpr("v", "a", "b", "m", f"n * CAST({covered()} AS DOUBLE) AS k")
        return share.groupBy("v", "a", "b", "m").agg(F.sum("k").alias("k_hat"))


def _level(lo: str, hi: str, bins: int) -> Column:
    """The least power of two at which the range takes no more than `bins` cells."""
    return F.expr(f"filter(sequence(0, 63), k -> shiftright({hi}, k) - shiftright({lo}, k) < {bins})[0]")


def empty_histogram(spark: SparkSession) -> DyadicHistogram:
    return DyadicHistogram(spark.createDataFrame([], _RANGES), spark.createDataFrame([], _CELLS))


def absorb(old: DyadicHistogram, edges: DataFrame, bins: int = BINS, orientation: str = "out") -> DyadicHistogram:
    """`old` with these edges added. Equal (v, start, duration) are counted before rows move to their cells."""
    v = "src" if orientation == "out" else "dst"
    fresh = edges.select(F.col(v).alias("v"), F.col("t_start").alias("bx"), (F.col("t_end") - F.col("t_start")).alias("by")).groupBy("v", "bx", "by").agg(F.count("*").alias("n"))
    spans = fresh.groupBy("v").agg(F.sum("n").alias("m"), F.min("bx").alias("s_lo"), F.max("bx").alias("s_hi"), F.min("by").alias("d_lo"), F.max("by").alias("d_hi"))
    ranges = old.ranges.unionByName(spans).groupBy("v").agg(F.sum("m").alias("m"), F.min("s_lo").alias("s_lo"), F.max("s_hi").alias("s_hi"), F.min("d_lo").alias("d_lo"), F.max("d_hi").alias("d_hi"))
    levels = ranges.select("v", _level("s_lo", "s_hi", bins).alias("x"), _level("d_lo", "d_hi", bins).alias("y"))
    exact = fresh.withColumns({"kx": F.lit(0), "ky": F.lit(0)})
    moved = old.cells.unionByName(exact).join(levels, "v").selectExpr("v", "x AS kx", "y AS ky", "shiftright(bx, x - kx) AS bx", "shiftright(by, y - ky) AS by", "n")
    return DyadicHistogram(ranges, moved.groupBy("v", "kx", "ky", "bx", "by").agg(F.sum("n").alias("n")))


class HistogramUpkeep:
    """A foreachBatch sink. State is a Parquet version for each batch in the shared folder; a batch
    that is retried reads the version before it again and overwrites its own, and versions that
    no retry can need are deleted."""

    def __init__(self, spark: SparkSession, bins: int = BINS, orientation: str = "out", root: str | None = None):
        self.spark, self.bins, self.orientation = spark, bins, orientation
        self.root = root or f"{shared_dir(spark)}/histogram-{uuid.uuid4().hex}"
        self.version = -1

    def current(self, version: int | None = None) -> DyadicHistogram:
        version = self.version if version is None else version
        if version < 0:
            return empty_histogram(self.spark)
        read = lambda part, schema: self.spark.read.schema(schema).parquet(f"{self.root}/{part}-{version}")
        return DyadicHistogram(read("ranges", _RANGES), read("cells", _CELLS))

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        done = absorb(self.current(batch_id - 1), batch, self.bins, self.orientation)
        done.ranges.write.mode("overwrite").parquet(f"{self.root}/ranges-{batch_id}")
        done.cells.write.mode("overwrite").parquet(f"{self.root}/cells-{batch_id}")
        self.version = batch_id
        for part in ("ranges", "cells"):
            path = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.root}/{part}-{batch_id - 2}")
            path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)
