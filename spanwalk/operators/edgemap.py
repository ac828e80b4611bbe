"""The temporal edge map: from a labelled frontier to the edges that may go on from it."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from ..functions.predicates import Ordering
from ..plans.inspection import counted
from ..session import settle, settle_partitioned

#: Edges of one vertex that one task may hold, and the usual number in a partition of a large window.
HUB_ROWS, PARTITION_ROWS, SMALL_ROWS = 500_000, 2_000_000, 100_000


@dataclass(frozen=True)
class FrontierEdges:
    """A window's edges, laid out once by the end they are looked up by; only frontiers move later.

    Edges of hubs are dealt out over several salts, and a frontier row at a hub is repeated for
    each of them, so that no vertex is one task however many edges it has.
    """

    df: DataFrame
    key: str
    hubs: DataFrame | None  # v, salts

    def meet(self, frontier: DataFrame) -> DataFrame:
        """Frontier rows (with column v) joined with all edges at their vertex."""
        if self.hubs is None:
            return frontier.join(self.df, F.col("v") == F.col(self.key))
        spread = frontier.join(self.hubs.withColumnRenamed("v", "__hub"), F.col("v") == F.col("__hub"), "left")
        salted = spread.select(*frontier.columns, F.explode(F.sequence(F.lit(0), F.coalesce("salts", F.lit(1)) - 1)).alias("__salt"))
        return salted.join(self.df, (F.col("v") == F.col(self.key)) & (F.col("__salt") == F.col("__own"))).drop("__salt", "__own")


def window_edges(edges: DataFrame, direction: str = "out", columns: tuple[str, ...] = ("src", "dst", "t_start", "t_end"), hub_rows: int = HUB_ROWS, partitions: int | None = None) -> FrontierEdges:
    """Lay the edges out for lookups by `src` (direction "out") or `dst` ("in"); `partitions` fixes their number."""
    key = "src" if direction == "out" else "dst"
    rows = edges.select(*columns)
    sizes = rows.groupBy(F.col(key).alias("v")).agg(F.count("*").alias("m"))
    total, most = sizes.agg(F.coalesce(F.sum("m"), F.lit(0)), F.coalesce(F.max("m"), F.lit(0))).head()
    usual = int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    partitions = partitions or min(math.ceil(total / SMALL_ROWS), max(usual, math.ceil(total / PARTITION_ROWS)))
    if most <= hub_rows:
        return FrontierEdges(settle_partitioned(rows, partitions, key), key, None)
    hubs = settle(sizes.where(F.col("m") > hub_rows).select("v", F.ceil(F.col("m") / hub_rows).cast("int").alias("salts")))
    dealt = rows.join(hubs.withColumnRenamed("v", "__hub"), F.col(key) == F.col("__hub"), "left")
    own = F.when(F.col("salts").isNull(), 0).otherwise(F.pmod(F.xxhash64(*columns), F.col("salts")).cast("int"))
    return FrontierEdges(settle_partitioned(dealt.select(*columns, own.alias("__own")), partitions, key, "__own"), key, hubs)


def expand_forward(frontier: DataFrame, edges: FrontierEdges, predicate: Ordering) -> DataFrame:
    """Frontier (source, v, label) joined with the out-edges that may follow its labels."""
    return edges.meet(frontier).where(predicate.follows_label(F.col("label"), F.col("t_start")))


def expand_counted(frontier: DataFrame, edges: FrontierEdges, predicate: Ordering) -> tuple[DataFrame, Observation]:
    """`expand_forward`, and counters of the job that runs it: edges `examined` and `admitted`."""
    follows = predicate.follows_label(F.col("label"), F.col("t_start"))
    met, seen = counted(edges.meet(frontier), examined=F.count(F.lit(1)), admitted=F.count_if(follows))
    return met.where(follows), seen


def expand_backward(frontier: DataFrame, edges: FrontierEdges, predicate: Ordering) -> DataFrame:
    """Frontier (source, v, label) joined with the in-edges that may come before its labels."""
    return edges.meet(frontier).where(predicate.precedes_label(F.col("label"), F.col("t_end")))


def expand_states(states: DataFrame, edges: FrontierEdges, predicate: Ordering) -> DataFrame:
    """Last edges (source, v, p_start, p_end, ...) joined with the next edges that the predicate admits."""
    return edges.meet(states).where(predicate.column("p_start", "p_end", "t_start", "t_end"))
