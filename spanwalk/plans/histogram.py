"""Two-dimensional histograms over (start, duration) of indexed vertices, and estimates from them.

The coverage formulas are SQL text that Spark and other engines read alike.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..session import settle, settle_partitioned

BINS = 100
#: Vertices whose ranges are sent to all tasks rather than having edges moved to them.
NEAR_ROWS = 200_000


@dataclass(frozen=True)
class Histogram:
    columns: DataFrame  # v, bx, total, cells (array of by, n), and v's meta: the filled cells of a column of equal starts, laid out by v
    meta: DataFrame  # v, m, s_lo, s_hi, d_lo, d_hi
    bins: int

    @property
    def cells(self) -> DataFrame:
        """(v, bx, by, n) of the filled cells."""
        return self.columns.select("v", "bx", F.explode("cells").alias("p")).select("v", "bx", "p.by", "p.n")


def build_histogram(edges: DataFrame, indexed: DataFrame, bins: int = BINS, orientation: str = "out") -> Histogram:
    """Equal-width cells in integer arithmetic; a range of width zero is one cell."""
    v = "src" if orientation == "out" else "dst"
    own = edges.select(F.col(v).alias("v"), F.col("t_start").alias("s"), (F.col("t_end") - F.col("t_start")).alias("d"))
    # ranges of all vertices from partial sums, then those asked for: edges don't move
    spans = own.groupBy("v").agg(F.count("*").alias("m"), F.min("s").alias("s_lo"), F.max("s").alias("s_hi"), F.min("d").alias("d_lo"), F.max("d").alias("d_hi"))
    meta = settle(spans.join(indexed.select("v"), "v", "left_semi"))
    cell = lambda x, lo, hi: F.expr(f"CASE WHEN {hi} = {lo} THEN 0 ELSE least({bins - 1}, ({x} - {lo}) * {bins} DIV ({hi} - {lo})) END").cast("long")
    ranges = F.broadcast(meta) if meta.count() <= NEAR_ROWS else meta
    cells = own.join(ranges, "v").select("v", cell("s", "s_lo", "s_hi").alias("bx"), cell("d", "d_lo", "d_hi").alias("by")).groupBy("v", "bx", "by").agg(F.count("*").alias("n"))
    columns = cells.groupBy("v", "bx").agg(F.sum("n").alias("total"), F.array_sort(F.collect_list(F.struct("by", "n"))).alias("cells"))
    return Histogram(settle_partitioned(columns.join(meta, "v"), int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions")), "v"), meta, bins)


def restrict_histogram(histogram: Histogram, indexed: DataFrame) -> Histogram:
    """The part of these vertices: cells depend on a vertex's own edges alone."""
    own = indexed.select("v")
    return Histogram(histogram.columns.join(own, "v", "left_semi"), histogram.meta.join(own, "v", "left_semi"), histogram.bins)


def corners(bins: int) -> list[str]:
    """Corners of a cell."""
    edge = lambda lo, hi, at: f"{lo} + ({hi} - {lo}) * CAST({at} AS DOUBLE) / {bins}"
    return [f"{edge('s_lo', 's_hi', 'bx')} AS s0", f"{edge('s_lo', 's_hi', 'bx + 1')} AS s1", f"{edge('d_lo', 'd_hi', 'by')} AS d0", f"{edge('d_lo', 'd_hi', 'by + 1')} AS d1"]


def clipped() -> list[str]:
    """Where the line start + duration = b enters and leaves the cell, clipped to starts of a and later."""
    left = "greatest(s0, least(s1, CAST(a AS DOUBLE)))"
    return ["s0", "s1", "d0", "d1", "a", "b", f"{left} AS l", "d1 - d0 AS h", f"greatest({left}, least(s1, b - d1)) AS u1", f"greatest({left}, least(s1, b - d0)) AS u2"]


def covered() -> str:
    """Share of a cell with start >= a and start + duration <= b, mass spread evenly over it."""
    return (
        "CASE WHEN s1 = s0 AND d1 = d0 THEN CASE WHEN s0 >= a AND s0 + d0 <= b THEN 1.0 ELSE 0.0 END "
        "WHEN s1 = s0 THEN CASE WHEN s0 < a THEN 0.0 ELSE greatest(0.0, least(h, b - d0 - s0)) / h END "
        "WHEN d1 = d0 THEN greatest(0.0, u2 - l) / (s1 - s0) "
        "ELSE ((u1 - l) * h + (u2 - u1) * ((b - d0 - u1) + (b - d0 - u2)) / 2.0) / ((s1 - s0) * h) END"
    )


def _expected(columns: DataFrame, bins: int, cell: str) -> DataFrame:
    """(v, a, b, m, k_hat) of rows of `Histogram.columns` with their (a, b)."""
    first = F.expr(f"CASE WHEN s_hi = s_lo THEN 0 ELSE least({bins - 1}, (a - s_lo) * {bins} DIV (s_hi - s_lo)) - 1 END")
    start, stop = corners(bins)[:2]
    inside = columns.selectExpr("*", start, stop).withColumn("whole", (F.col("s0") < F.col("s1")) & (F.col("s0") >= F.col("a")) & (F.col("s1") + F.col("d_hi") <= F.col("b")))
    taken = F.when(F.col("bx") < first, F.array().cast("array<struct<by:bigint,n:bigint>>")).when(F.col("whole"), F.array(F.struct(F.lit(0).cast("long").alias("by"), F.col("total").alias("n")))).otherwise(F.col("cells"))
    parts = inside.withColumn("p", F.explode_outer(taken))
    wide = parts.select("v", "m", "whole", "a", "b", "bx", "s_lo", "s_hi", "d_lo", "d_hi", "p.by", "p.n").selectExpr("v", "m", "n", "whole", "a", "b", *corners(bins))
    share = wide.selectExpr("v", "m", "n", "whole", *clipped()).selectExpr("v", "m", "n", "whole", "a", "b", "s0", "s1", "d0", "d1", f"CAST({covered()} AS DOUBLE) AS share")
    if cell == "full":
        share = share.withColumn("share", F.when((F.col("s1") >= F.col("a")) & (F.col("s0") + F.col("d0") <= F.col("b")), 1.0).otherwise(0.0))
    elif cell == "none":
        share = share.withColumn("share", F.when((F.col("s0") >= F.col("a")) & (F.col("s1") + F.col("d1") <= F.col("b")), 1.0).otherwise(0.0))
    counted = F.sum(F.when(F.col("n").isNull(), 0.0).otherwise(F.col("n") * F.when(F.col("whole"), 1.0).otherwise(F.col("share"))))
    return share.groupBy("v", "a", "b", "m").agg(counted.alias("k_hat"))


def estimate(histogram: Histogram, asked: DataFrame, cell: str = "uniform") -> DataFrame:
    """(v, a, b, m, k_hat): edges of v expected inside [a, b].

    `cell` says how a partly covered cell counts: by its share, wholly ("full", an upper bound)
    or not at all ("none", a lower bound). Columns of cells that start before `a` are left out by
    number, a column that lies inside the range as a whole counts by its total, and only the
    others are taken apart.
    """
    return _expected(asked.select("v", "a", "b").join(histogram.columns, "v"), histogram.bins, cell)


def estimate_window(histogram: Histogram, start: int, end: int) -> DataFrame:
    """The same for one range and all vertices: no join, and no move, columns lie by vertex."""
    return _expected(histogram.columns.withColumns({"a": F.lit(start).cast("long"), "b": F.lit(end).cast("long")}), histogram.bins, "uniform")


def prefix_counts(histogram: Histogram) -> DataFrame:
    """(v, bx, by, upto): edges in cells at or before (bx, by) on both axes, for cells that hold edges' rows and columns."""
    rows = histogram.cells.select("v", "bx").distinct()
    cols = histogram.cells.select("v", "by").distinct()
    grid = rows.join(cols, "v").join(histogram.cells, ["v", "bx", "by"], "left").na.fill(0, ["n"])
    along = grid.withColumn("run", F.sum("n").over(W.partitionBy("v", "bx").orderBy("by")))
    return along.withColumn("upto", F.sum("run").over(W.partitionBy("v", "by").orderBy("bx"))).select("v", "bx", "by", "upto")
