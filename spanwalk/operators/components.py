"""Connected components of a window, over time, and through time."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..functions.predicates import Ordering, Window
from ..session import settle
from .graph import TemporalGraph
from .paths import earliest_arrival


def label_components(pairs: DataFrame, keys: list[str] = (), method: str = "star") -> DataFrame:
    """(keys, v, component) for pairs (keys, a, b); component is the least vertex reached.

    `star` alternates contractions in which every vertex points its larger, then its smaller
    neighbours at the least one: rounds grow with the logarithm of the longest chain. `propagate`
    floods least labels: rounds grow with the diameter. Hubs are only met by a partially
    aggregated minimum.
    """
    keys = list(keys)
    everyone = pairs.select(*keys, F.explode(F.array("a", "b")).alias("v")).distinct()
    links = settle(pairs.where("a <> b").select(*keys, F.greatest("a", "b").alias("u"), F.least("a", "b").alias("w")).distinct())
    seen = None
    if method == "propagate":
        both = settle(links.select(*keys, "u", "w").union(links.select(*keys, "w", "u")).toDF(*keys, "u", "w"))
        state = settle(everyone.withColumn("component", F.col("v")))
        while True:
            found = both.join(state.withColumnRenamed("v", "w"), [*keys, "w"]).groupBy(*keys, F.col("u").alias("v")).agg(F.min("component").alias("other"))
            new = settle(state.join(found, [*keys, "v"], "left").select(*keys, "v", F.least("component", "other").alias("component"), (F.col("other") < F.col("component")).alias("moved")))
            state = new.drop("moved")
            if new.where("moved").isEmpty():
                return state
    while True:
        both = links.unionByName(links.select(*keys, F.col("w").alias("u"), F.col("u").alias("w")))
        least = both.groupBy(*keys, "u").agg(F.min("w").alias("m")).withColumn("m", F.least("u", "m"))
        large = both.join(least, [*keys, "u"]).where("w > u").select(*keys, F.col("w").alias("u"), F.col("m").alias("w")).distinct()
        least = large.groupBy(*keys, "u").agg(F.min("w").alias("m"))
        small = large.join(least, [*keys, "u"]).select(*keys, F.explode(F.array(F.struct(F.col("u").alias("u"), F.col("m").alias("w")), F.struct(F.col("w").alias("u"), F.col("m").alias("w")))).alias("x")).select(*keys, "x.u", "x.w").where("u <> w").distinct()
        links = settle(small)
        now = tuple(links.agg(F.count("*"), F.sum(F.xxhash64(*keys, "u", "w").cast("decimal(38,0)"))).head())
        if now == seen:
            break
        seen = now
    return everyone.join(links.withColumnRenamed("u", "v"), [*keys, "v"], "left").select(*keys, "v", F.coalesce("w", "v").alias("component"))


def connected_components(graph: TemporalGraph, window: Window, include_isolated: bool = False, method: str = "star") -> DataFrame:
    """(v, component) of the window's edges taken as undirected."""
    inside = graph.restrict(window).edges.select(F.col("src").alias("a"), F.col("dst").alias("b"))
    found = label_components(inside, method=method)
    if include_isolated:
        found = graph.vertices.df.join(found, "v", "left").select("v", F.coalesce("component", "v").alias("component"))
    return found


def mutual_reachability(graph: TemporalGraph, window: Window, predicate: Ordering | None = None) -> DataFrame:
    """(u, v), u < v: pairs that reach each other by valid paths. Not transitive in general."""
    inside = graph.restrict(window)
    reach = settle(earliest_arrival(graph, inside.vertices.df, window, predicate).where("source <> v").select("source", "v"))
    back = reach.select(F.col("v").alias("source"), F.col("source").alias("v"))
    return reach.where("source < v").join(back, ["source", "v"], "left_semi").select(F.col("source").alias("u"), "v")


def reachability_components(graph: TemporalGraph, window: Window, predicate: Ordering | None = None) -> DataFrame:
    """(v, component) of the graph of mutually reachable pairs."""
    pairs = mutual_reachability(graph, window, predicate)
    return label_components(pairs.select(F.col("u").alias("a"), F.col("v").alias("b")))


def components_over_time(graph: TemporalGraph, window: Window, slice_width: int) -> DataFrame:
    """(slice, v, component, previous, changed): components of each slice of time, in one job for all slices."""
    inside = graph.restrict(window).edges.select(F.floor((F.col("t_start") - window.start) / slice_width).alias("slice"), F.col("src").alias("a"), F.col("dst").alias("b"))
    found = label_components(inside, ["slice"])
    before = F.lag("component").over(W.partitionBy("v").orderBy("slice"))
    return found.withColumn("previous", before).withColumn("changed", F.coalesce(F.col("previous") != F.col("component"), F.lit(False)))
