"""Minimal temporal paths, time-respecting search and reachability.

A valid path takes distinct edges inside the window, each ordered after the one before it by the
predicate; the empty path belongs to its source alone. Methods take many sources at once and
carry `source` as a key. Vertices that no valid path reaches are absent. `access` and `plan` say how
the window's edges are fetched (see `access.lay`); results don't depend on them.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.predicates import Ordering, Window
from ..plans.fixpoint import pareto_fixpoint, reach_fixpoint, scalar_fixpoint
from ..session import settle
from .access import lay
from .edgemap import FrontierEdges, expand_backward, expand_forward, expand_states, window_edges
from .graph import TemporalGraph, with_edge_ids


def source_frame(spark: SparkSession, sources: list[int] | DataFrame) -> DataFrame:
    if isinstance(sources, DataFrame):
        return sources.select(F.col(sources.columns[0]).cast("long").alias("source")).distinct()
    return spark.createDataFrame([(int(s),) for s in sorted(set(sources))], "source long")


def _seeds(sources: DataFrame, label: int) -> DataFrame:
    return sources.select("source", F.col("source").alias("v"), F.lit(label).cast("long").alias("label"))


def _forward_labels(graph: TemporalGraph, sources, window: Window, predicate: Ordering, access: str, max_hops: int | None, targets: list[int] | None = None, plan=None) -> DataFrame:
    spark = graph.edges.sparkSession
    seeds = _seeds(source_frame(spark, sources), predicate.seed(window.start))
    edges = lay(graph, window, "out", access, plan)
    stop = None
    if targets is not None:
        pairs = seeds.select("source").distinct().count() * len(set(targets))
        stop = lambda state: state.where(F.col("v").isin(*targets)).select("source", "v").distinct().count() == pairs
    return scalar_fixpoint(seeds, lambda d: expand_forward(d, edges, predicate).select("source", F.col("dst").alias("v"), F.col("t_end").alias("label")), max_rounds=max_hops, stop=stop)


def earliest_arrival(graph: TemporalGraph, sources, window: Window, predicate: Ordering | None = None, access: str = "scan", max_hops: int | None = None, plan=None) -> DataFrame:
    """(source, v, arrival): least end of a valid path; the source itself has the window's start."""
    predicate = predicate or graph.predicate
    if predicate is Ordering.OVERLAPS:
        return _arrival_pareto(graph, sources, window, predicate)
    if predicate is Ordering.OVERLAPS_PROPER:
        return arrival_by_edges(graph, sources, window, predicate)
    found = _forward_labels(graph, sources, window, predicate, access, max_hops, plan=plan)
    return found.select("source", "v", F.when(F.col("v") == F.col("source"), F.lit(window.start).cast("long")).otherwise(F.col("label")).alias("arrival"))


def _with_source(found: DataFrame, spark: SparkSession, sources, own: dict) -> DataFrame:
    """Replace what was found for the source itself by the value of the empty path."""
    rest = found.where(F.col("v") != F.col("source"))
    empty = source_frame(spark, sources).select("source", F.col("source").alias("v"), *[F.lit(x).cast("long").alias(c) for c, x in own.items()])
    return rest.unionByName(empty.select(*rest.columns))


def _first_edges(graph: TemporalGraph, sources, edges: FrontierEdges) -> DataFrame:
    """(source, v, edge): the edges that leave the sources; v is the source."""
    return edges.meet(source_frame(graph.edges.sparkSession, sources).withColumn("v", F.col("source"))).drop("v")


def _arrival_pareto(graph: TemporalGraph, sources, window: Window, predicate: Ordering) -> DataFrame:
    """Overlaps in prose form: smaller start and smaller end of the last edge both help."""
    edges = window_edges(graph.restrict(window).walkable())
    seed = _first_edges(graph, sources, edges).select("source", F.col("dst").alias("v"), F.col("t_start").alias("x"), F.col("t_end").alias("y"))
    step = lambda d: expand_states(d.select("source", "v", F.col("x").alias("p_start"), F.col("y").alias("p_end")), edges, predicate).select("source", F.col("dst").alias("v"), F.col("t_start").alias("x"), F.col("t_end").alias("y"))
    found = pareto_fixpoint(seed, step).groupBy("source", "v").agg(F.min("y").alias("arrival"))
    return _with_source(found, graph.edges.sparkSession, sources, {"arrival": window.start})


def edge_states(graph: TemporalGraph, sources, window: Window, predicate: Ordering, max_hops: int | None = None) -> tuple[DataFrame, DataFrame]:
    """States (source, edge_id, round) of all edges that end a valid path, and the window's edges with ids."""
    rows = settle(with_edge_ids(graph.restrict(window).walkable().select("src", "dst", "t_start", "t_end")))
    laid = window_edges(rows, columns=("src", "dst", "t_start", "t_end", "edge_id"))
    edges = laid.df.select("src", "dst", "t_start", "t_end", "edge_id")
    seed = _first_edges(graph, sources, laid).select("source", "edge_id")
    ends = edges.select(F.col("edge_id").alias("last"), F.col("dst").alias("v"), F.col("t_start").alias("p_start"), F.col("t_end").alias("p_end"))
    step = lambda d: expand_states(d.select("source", F.col("edge_id").alias("last")).join(ends, "last"), laid, predicate).select("source", "edge_id")
    return reach_fixpoint(seed, step, ["source", "edge_id"], max_hops), edges


def arrival_by_edges(graph: TemporalGraph, sources, window: Window, predicate: Ordering) -> DataFrame:
    """The exact form for any predicate: every edge is visited at most once a source."""
    states, edges = edge_states(graph, sources, window, predicate)
    found = states.join(edges, "edge_id").groupBy("source", F.col("dst").alias("v")).agg(F.min("t_end").alias("arrival"))
    return _with_source(found, graph.edges.sparkSession, sources, {"arrival": window.start})


def latest_departure(graph: TemporalGraph, targets, window: Window, predicate: Ordering | None = None, access: str = "scan", plan=None) -> DataFrame:
    """(target, v, departure): largest start of a valid path from v; the target itself has the window's end."""
    predicate = predicate or graph.predicate
    if not predicate.one_sided:
        raise ValueError("latest departure has scalar labels for one-sided predicates only")
    edges = lay(graph, window, "in", access, plan)
    label = window.end + 1 if predicate is Ordering.STRICTLY_SUCCEEDS else window.end
    seeds = _seeds(source_frame(graph.edges.sparkSession, targets), label)
    step = lambda d: expand_backward(d, edges, predicate).select("source", F.col("src").alias("v"), F.col("t_start").alias("label"))
    found = scalar_fixpoint(seeds, step, largest=True)
    return found.select(F.col("source").alias("target"), "v", F.when(F.col("v") == F.col("source"), F.lit(window.end).cast("long")).otherwise(F.col("label")).alias("departure"))


def fastest(graph: TemporalGraph, sources, window: Window, predicate: Ordering | None = None, strategy: str = "pareto", access: str = "scan", plan=None) -> DataFrame:
    """(source, v, duration, departure, arrival): least time from first start to last end, latest departure on ties.

    `pareto` keeps for each vertex the departures and arrivals that none dominates;
    `per_departure` solves earliest arrival once for each departure time of the source.
    """
    predicate = predicate or graph.predicate
    if not predicate.one_sided:
        raise ValueError("fastest paths take one-sided predicates")
    edges = lay(graph, window, "out", access, plan)
    first = _first_edges(graph, sources, edges)
    if strategy == "pareto":
        seed = first.select("source", F.col("dst").alias("v"), (-F.col("t_start")).alias("x"), F.col("t_end").alias("y"))
        step = lambda d: expand_forward(d.withColumnRenamed("y", "label"), edges, predicate).select("source", F.col("dst").alias("v"), "x", F.col("t_end").alias("y"))
        pairs = pareto_fixpoint(seed, step).select("source", "v", (-F.col("x")).alias("departure"), F.col("y").alias("arrival"))
    else:
        # the departure rides along in the key: (source, departure) plays the part of the source
        seed = first.select(F.struct("source", F.col("t_start").alias("departure")).alias("source"), F.col("dst").alias("v"), F.col("t_end").alias("label")).groupBy("source", "v").agg(F.min("label").alias("label"))
        step = lambda d: expand_forward(d, edges, predicate).select("source", F.col("dst").alias("v"), F.col("t_end").alias("label"))
        pairs = scalar_fixpoint(seed, step).select("source.source", "v", "source.departure", F.col("label").alias("arrival"))
    best = pairs.groupBy("source", "v").agg(F.min(F.struct((F.col("arrival") - F.col("departure")).alias("duration"), (-F.col("departure")).alias("late"))).alias("b"))
    found = best.select("source", "v", "b.duration", (-F.col("b.late")).alias("departure"), (F.col("b.duration") - F.col("b.late")).alias("arrival"))
    return _with_source(found, graph.edges.sparkSession, sources, {"duration": 0, "departure": window.start, "arrival": window.start})


def shortest_duration(graph: TemporalGraph, sources, window: Window, predicate: Ordering | None = None, cost: str = "duration", access: str = "scan", plan=None) -> DataFrame:
    """(source, v, cost): least sum of edge durations, or of non-negative weights with cost="weight"."""
    predicate = predicate or graph.predicate
    if not predicate.one_sided:
        raise ValueError("shortest paths take one-sided predicates")
    edges = lay(graph, window, "out", access, plan, ("src", "dst", "t_start", "t_end", "weight"))
    price = (F.col("t_end") - F.col("t_start")) if cost == "duration" else F.col("weight")
    seed = _first_edges(graph, sources, edges).select("source", F.col("dst").alias("v"), F.col("t_end").alias("x"), price.alias("y"))
    step = lambda d: expand_forward(d.withColumnRenamed("x", "label"), edges, predicate).select("source", F.col("dst").alias("v"), F.col("t_end").alias("x"), (F.col("y") + price).alias("y"))
    found = pareto_fixpoint(seed, step).groupBy("source", "v").agg(F.min("y").alias("cost")).where("v <> source")
    kind = "long" if cost == "duration" else "double"
    empty = source_frame(graph.edges.sparkSession, sources).select("source", F.col("source").alias("v"), F.lit(0).cast(kind).alias("cost"))
    return found.unionByName(empty)


def temporal_bfs(graph: TemporalGraph, sources, window: Window, predicate: Ordering | None = None, mode: str = "time_respecting", access: str = "scan", plan=None) -> DataFrame:
    """(source, v, hops): fewest edges of a valid path, or of any path inside the window (mode "window").

    The arrival of the best path of at most h edges is carried from round to round, so the
    first round that reaches a vertex is its hop count.
    """
    predicate = predicate or graph.predicate
    if mode == "window":
        edges = lay(graph, window, "out", access, plan)
        seed = source_frame(graph.edges.sparkSession, sources).select("source", F.col("source").alias("v"))
        step = lambda d: edges.meet(d).select("source", F.col("dst").alias("v"))
        return reach_fixpoint(seed, step, ["source", "v"]).select("source", "v", (F.col("round") - 1).cast("long").alias("hops"))
    if predicate.one_sided:
        found = _forward_labels(graph, sources, window, predicate, access, None, plan=plan)
        return found.select("source", "v", F.col("round").cast("long").alias("hops"))
    states, edges = edge_states(graph, sources, window, predicate)
    found = states.join(edges, "edge_id").groupBy("source", F.col("dst").alias("v")).agg(F.min("round").cast("long").alias("hops"))
    return _with_source(found, graph.edges.sparkSession, sources, {"hops": 0})


def reachable(graph: TemporalGraph, sources, window: Window, predicate: Ordering | None = None, max_hops: int | None = None, targets: list[int] | None = None, access: str = "scan", plan=None) -> DataFrame:
    """(source, v) of all reached vertices; with `targets` only those, stopping once all are settled."""
    predicate = predicate or graph.predicate
    if predicate.one_sided:
        found = _forward_labels(graph, sources, window, predicate, access, max_hops, targets, plan)
    else:
        states, edges = edge_states(graph, sources, window, predicate, max_hops)
        found = _with_source(states.join(edges, "edge_id").select("source", F.col("dst").alias("v")).distinct(), graph.edges.sparkSession, sources, {})
    found = found.select("source", "v")
    return found if targets is None else found.where(F.col("v").isin(*targets))


def arrival_paths(graph: TemporalGraph, sources, window: Window, predicate: Ordering | None = None) -> DataFrame:
    """(source, v, arrival, path): one earliest-arrival path, as an array of its edges in order.

    The last edge into v is the least by content among those that end at v's arrival and may
    follow their tail's arrival; walking back from tail to tail gives the path. Where tail and
    head have the same arrival (zero-length edges under `succeeds`) the tail must have got it in
    an earlier round, so the walk can't circle.
    """
    predicate = predicate or graph.predicate
    labels = settle(_forward_labels(graph, sources, window, predicate, "scan", None))
    edges = settle(graph.restrict(window).walkable().select("src", "dst", "t_start", "t_end"))
    tails = labels.select("source", F.col("v").alias("src"), F.col("label").alias("tail"), F.col("settled").alias("tail_round"))
    heads = labels.where("v <> source").select("source", F.col("v").alias("dst"), F.col("label").alias("t_end"), F.col("settled").alias("head_round"))
    fits = edges.join(tails, "src").where(predicate.follows_label(F.col("tail"), F.col("t_start"))).join(heads, ["source", "dst", "t_end"])
    ahead = (F.col("tail") < F.col("t_end")) | (F.col("src") == F.col("source")) | (F.col("tail_round") < F.col("head_round"))
    last = settle(fits.where(ahead).groupBy("source", "dst").agg(F.min(F.struct("t_start", "t_end", "src", "dst")).alias("e")))
    walk = settle(last.select("source", F.col("dst").alias("v"), F.col("e.t_end").alias("arrival"), F.col("e.src").alias("at"), F.array("e").alias("path")))
    done = [walk.where("at = source").select("source", "v", "arrival", "path")]
    walk = walk.where("at <> source")
    while not walk.isEmpty():
        step = last.select("source", F.col("dst").alias("at"), F.col("e").alias("before"))
        walk = settle(walk.join(step, ["source", "at"]).select("source", "v", "arrival", F.col("before.src").alias("at"), F.concat(F.array("before"), "path").alias("path")))
        done.append(walk.where("at = source").select("source", "v", "arrival", "path"))
        walk = walk.where("at <> source")
    out = done[0]
    for d in done[1:]:
        out = out.unionByName(d)
    return out


def exposure(graph: TemporalGraph, seeds: list[int], window: Window, predicate: Ordering | None = None, infectious: int | None = None) -> DataFrame:
    """(v, exposed): first time contact could have carried something from any seed to v.

    With `infectious`, a contact must start at most so long after its tail was exposed; then an
    earlier exposure may expire, so every exposure is a state.
    """
    predicate = predicate or graph.predicate
    spark = graph.edges.sparkSession
    edges = window_edges(graph.restrict(window).walkable())
    start = predicate.seed(window.start)
    seed = source_frame(spark, seeds).select(F.lit(0).cast("long").alias("source"), F.col("source").alias("v"), F.lit(start).cast("long").alias("label"))
    if infectious is None:
        found = scalar_fixpoint(seed, lambda d: expand_forward(d, edges, predicate).select("source", F.col("dst").alias("v"), F.col("t_end").alias("label"))).select("v", "label")
    else:
        step = lambda d: expand_forward(d, edges, predicate).where(F.col("t_start") <= F.greatest("label", F.lit(window.start)) + infectious).select("source", F.col("dst").alias("v"), F.col("t_end").alias("label"))
        found = reach_fixpoint(seed, step, ["source", "v", "label"]).groupBy("v").agg(F.min("label").alias("label"))
    return found.select("v", F.greatest("label", F.lit(window.start).cast("long")).alias("exposed"))
