"""k-cores, PageRank and betweenness of a window."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..functions.predicates import Ordering, Window
from ..session import release, settle, settle_laid, settle_partitioned
from .edgemap import FrontierEdges, window_edges
from .graph import TemporalGraph, with_edge_ids


#: Rounds of coreness before one task may finish it, and the most pairs that such a task may hold.
CORE_ROUNDS, TASK_PAIRS = 6, 4_000_000


def _incidences(graph: TemporalGraph, window: Window, degree: str) -> DataFrame:
    """(v, u): one row for every incident edge end, or for every distinct neighbour."""
    e = graph.restrict(window).edges
    both = e.select(F.col("src").alias("v"), F.col("dst").alias("u")).unionByName(e.select(F.col("dst").alias("v"), F.col("src").alias("u")))
    return both if degree == "edges" else both.where("u <> v").distinct()


def _partitions(df: DataFrame) -> int:
    return int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))


def _laid(pairs: DataFrame) -> FrontierEdges:
    """Pairs (v, u) laid out by v once, hubs dealt out."""
    return window_edges(pairs.select(F.col("v").alias("src"), F.col("u").alias("dst")), columns=("src", "dst"), partitions=_partitions(pairs))


def k_core(graph: TemporalGraph, window: Window, k: int, degree: str = "edges") -> DataFrame:
    """(v) of the largest part in which every vertex has degree k or more: peeled to a fixpoint.

    Degrees are kept by vertex; a round moves the pairs of the vertices peeled in it, and each
    vertex is peeled once, so all rounds together move every pair at most once.
    """
    ends = _laid(_incidences(graph, window, degree))
    left = settle_laid(ends.df.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("d")))
    while True:
        weak = left.where(F.col("d") < k).select("v")
        if weak.isEmpty():
            return left.select("v")
        lost = ends.meet(weak).groupBy(F.col("dst").alias("v")).agg(F.count("*").alias("lost"))
        new = settle_laid(left.where(F.col("d") >= k).join(lost, "v", "left").select("v", (F.col("d") - F.coalesce("lost", F.lit(0))).alias("d")))
        release(left)
        left = new


def _settle_values(ends: FrontierEdges, value: DataFrame) -> DataFrame:
    """(v, coreness): the same h-indices from the values so far, in one task that follows changes from neighbour to neighbour.

    Along paths a change moves one edge a round, so rounds can be as many as a path has edges.
    """
    pairs = ends.df.groupBy("src", "dst").agg(F.count("*").alias("n"))
    rows = pairs.join(value.select(F.col("v").alias("src"), "c"), "src").select("src", "dst", "n", "c")

    def settle_down(batches):
        import numpy as np
        import pandas as pd

        rows = pd.concat(list(batches), ignore_index=True)
        names, own = np.unique(rows["src"].to_numpy(), return_inverse=True)
        order = np.argsort(own, kind="stable")
        begin = np.searchsorted(own[order], np.arange(len(names) + 1)).tolist()
        near = np.searchsorted(names, rows["dst"].to_numpy())[order].tolist()
        often = rows["n"].to_numpy()[order].tolist()
        value = np.zeros(len(names), dtype=np.int64)
        value[own] = rows["c"].to_numpy()
        value = value.tolist()
        todo, waits = list(range(len(names))), bytearray(b"\1") * len(names)
        while todo:
            x = todo.pop()
            waits[x] = 0
            old = value[x]
            counts = [0] * (old + 1)
            for k in range(begin[x], begin[x + 1]):
                counts[min(old, value[near[k]])] += often[k]
            new, above = old, counts[old]
            while new > 0 and above < new:
                new -= 1
                above += counts[new]
            if new < old:
                value[x] = new
                for y in near[begin[x] : begin[x + 1]]:
                    if new < value[y] and not waits[y]:
                        waits[y] = 1
                        todo.append(y)
        yield pd.DataFrame({"v": names, "coreness": value})

    return settle(rows.coalesce(1).mapInPandas(settle_down, "v long, coreness long"))


def coreness(graph: TemporalGraph, window: Window, degree: str = "edges", task_pairs: int = TASK_PAIRS) -> DataFrame:
    """(v, coreness): every vertex takes the h-index of its neighbours' values, from its degree down.

    Only counts by (v, value) are kept for a vertex, never its list of neighbours; pairs stay
    where they are, a round moves values and those counts. If values still fall after some rounds
    and all pairs fit one task (`task_pairs`), that task finishes; otherwise the rounds go on.
    """
    ends = _laid(_incidences(graph, window, degree))
    value = settle_laid(ends.df.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("c")))
    rounds, fits = 0, ends.df.count() <= task_pairs
    while True:
        if fits and rounds == CORE_ROUNDS:
            return _settle_values(ends, value)
        rounds += 1
        told = ends.meet(value.withColumnRenamed("c", "cu")).groupBy(F.col("dst").alias("v"), "cu").agg(F.count("*").alias("n"))
        counts = told.join(value, "v").groupBy("v", "c", F.least("c", "cu").alias("x")).agg(F.sum("n").alias("n"))
        at_least = F.sum("n").over(W.partitionBy("v").orderBy(F.desc("x")))
        new = counts.withColumn("at_least", at_least).groupBy("v").agg(F.first("c").alias("old"), F.max(F.least("x", "at_least")).alias("c"))
        new = settle_laid(new)
        release(value)
        value = new.select("v", "c")
        if new.where("c < old").isEmpty():
            return value.select("v", F.col("c").alias("coreness"))


def pagerank(graph: TemporalGraph, window: Window, damping: float = 0.85, max_iter: int = 100, tol: float | None = None, weighted: bool = False) -> DataFrame:
    """(v, rank) over the window's edges; mass of vertices without out-edges is spread evenly.

    Parallel edges are folded into transition shares and laid out by tail once; ranks are kept in
    the same partitions, so a round moves only partial sums of the flow.
    """
    e = graph.restrict(window).walkable()
    parts = _partitions(e)
    amount = F.sum("weight") if weighted else F.count("*")
    pairs = settle(e.groupBy("src", "dst").agg(amount.cast("double").alias("w")))
    shares = window_edges(pairs.join(pairs.groupBy("src").agg(F.sum("w").alias("all")), "src").select("src", "dst", (F.col("w") / F.col("all")).alias("p")), columns=("src", "dst", "p"), partitions=parts)
    nodes = shares.df.groupBy(F.col("src").alias("v")).agg(F.lit(True).alias("out")).unionByName(shares.df.select(F.col("dst").alias("v"), F.lit(None).cast("boolean").alias("out")))
    nodes = settle_laid(nodes.groupBy("v").agg(F.max("out").alias("out")))
    release(pairs)
    n = nodes.count()
    rank = settle_partitioned(nodes.select("v", "out", F.lit(1.0 / max(1, n)).alias("rank")), parts, "v")
    loose = rank.where("out is null").agg(F.sum("rank")).head()[0] or 0.0
    for _ in range(max_iter):
        flow = shares.meet(rank.where("out").select("v", "rank")).groupBy(F.col("dst").alias("v")).agg(F.sum(F.col("rank") * F.col("p")).alias("inflow"))
        new = rank.withColumnRenamed("rank", "old").join(flow, "v", "left")
        new = settle_laid(new.select("v", "out", "old", ((1 - damping) / max(1, n) + damping * (F.coalesce("inflow", F.lit(0.0)) + F.lit(loose / max(1, n)))).alias("rank")))
        release(rank)
        rank = new.drop("old")
        loose, moved = new.agg(F.sum(F.when(F.col("out").isNull(), F.col("rank"))), F.sum(F.abs(F.col("rank") - F.col("old")))).head()
        loose = loose or 0.0
        if tol is not None and (moved or 0.0) < tol:
            break
    return rank.select("v", "rank")


def betweenness(graph: TemporalGraph, window: Window, sources: DataFrame | None = None, predicate: Ordering = Ordering.STRICTLY_SUCCEEDS) -> DataFrame:
    """(v, score): over pairs (s, t), the share of shortest-duration valid paths that pass v inside.

    States are last edges. For each source: the least cost of every edge state, then path counts
    along tight successions, the share of targets' paths that each state still leads to, and the
    sum. Counts are doubles. Edges need positive durations, or counts are not defined.
    """
    if not predicate.one_sided:
        raise ValueError("betweenness takes one-sided predicates")
    edges = graph.restrict(window).walkable().select("src", "dst", "t_start", "t_end")
    if not edges.where("t_end <= t_start").isEmpty():
        raise ValueError("betweenness needs edges of positive duration")
    laid = window_edges(settle(with_edge_ids(edges).withColumn("d", F.col("t_end") - F.col("t_start"))), columns=("src", "dst", "t_start", "t_end", "edge_id", "d"), partitions=_partitions(edges))
    edges = laid.df.select("src", "dst", "t_start", "t_end", "edge_id", "d")
    a = edges.select(F.col("edge_id").alias("p"), F.col("dst").alias("v"), F.col("t_start").alias("p_start"), F.col("t_end").alias("p_end"))
    follows = predicate.column("p_start", "p_end", "t_start", "t_end") & (F.col("p") != F.col("edge_id"))
    # successions are found at hubs salt by salt and laid out by the edge they follow
    next_to = settle_partitioned(laid.meet(a).where(follows).select("p", F.col("edge_id").alias("e"), "d"), _partitions(edges), "p")
    some = edges.select(F.col("src").alias("source")).distinct() if sources is None else sources.select(F.col(sources.columns[0]).alias("source"))
    first = some.join(edges, F.col("source") == F.col("src")).select("source", F.col("edge_id").alias("e"), F.col("d").alias("cost"))
    best = settle(first)
    delta = best
    while not delta.isEmpty():
        found = delta.withColumnRenamed("e", "p").join(next_to, "p").groupBy("source", "e").agg(F.min(F.col("cost") + F.col("d")).alias("cost"))
        delta = settle(found.join(best.withColumnRenamed("cost", "old"), ["source", "e"], "left").where("old is null or cost < old").select("source", "e", "cost"))
        best = settle(best.unionByName(delta).groupBy("source", "e").agg(F.min("cost").alias("cost")))
    tight = best.select("source", F.col("e").alias("p"), F.col("cost").alias("p_cost")).join(next_to, "p").join(best, ["source", "e"]).where("p_cost + d = cost").select("source", "p", "e")
    tight = settle(tight)

    def spread(start: DataFrame, origin: str, goal: str) -> DataFrame:
        """Sums over all tight walks from `start` (source, e, w), the start itself included."""
        total, wave = [start], start
        while True:
            wave = settle(wave.withColumnRenamed("e", origin).join(tight, ["source", origin]).groupBy("source", F.col(goal).alias("x")).agg(F.sum("w").alias("w")).withColumnRenamed("x", "e"))
            if wave.isEmpty():
                break
            total.append(wave)
        out = total[0]
        for t in total[1:]:
            out = out.unionByName(t)
        return settle(out.groupBy("source", "e").agg(F.sum("w").alias("w")))

    begins = settle(first.join(best.withColumnRenamed("cost", "least"), ["source", "e"]).where("cost = least").select("source", "e", F.lit(1.0).alias("w")))
    sigma = spread(begins, "p", "e").withColumnRenamed("w", "sigma")
    heads = edges.select(F.col("edge_id").alias("e"), F.col("dst").alias("v"))
    ended = best.join(heads, "e").join(sigma, ["source", "e"]).where("v <> source")
    least = ended.groupBy("source", "v").agg(F.min("cost").alias("least"))
    final = ended.join(least, ["source", "v"]).where("cost = least")
    paths = final.groupBy("source", "v").agg(F.sum("sigma").alias("paths"))
    ends = settle(final.join(paths, ["source", "v"]).select("source", "e", (1.0 / F.col("paths")).alias("w")))
    onward = spread(ends, "e", "p").join(ends.withColumnRenamed("w", "own"), ["source", "e"], "left").select("source", "e", (F.col("w") - F.coalesce("own", F.lit(0.0))).alias("onward"))
    passed = sigma.join(onward, ["source", "e"]).join(heads, "e").where("v <> source").groupBy("v").agg(F.sum(F.col("sigma") * F.col("onward")).alias("score"))
    vertices = edges.select(F.explode(F.array("src", "dst")).alias("v")).distinct()
    return vertices.join(passed, "v", "left").select("v", F.coalesce("score", F.lit(0.0)).alias("score"))


def sampled_betweenness(graph: TemporalGraph, window: Window, k: int, seed: int = 1, predicate: Ordering = Ordering.STRICTLY_SUCCEEDS) -> DataFrame:
    """Estimate from k sources drawn by hash, scaled by the share drawn."""
    everyone = graph.restrict(window).walkable().select(F.col("src").alias("source")).distinct()
    drawn = settle(everyone.orderBy(F.xxhash64("source", F.lit(seed)), "source").limit(k))
    scale = everyone.count() / max(1, drawn.count())
    return betweenness(graph, window, drawn, predicate).withColumn("score", F.col("score") * scale)


def top_central(graph: TemporalGraph, window: Window, k: int, predicate: Ordering = Ordering.STRICTLY_SUCCEEDS) -> DataFrame:
    """The k vertices of largest betweenness, ties by least id."""
    return betweenness(graph, window, predicate=predicate).withColumn("score", F.round("score", 9)).orderBy(F.desc("score"), "v").limit(k)
