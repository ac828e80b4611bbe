"""The ways of answering that the engine is compared with; all give the arrivals of `earliest_arrival`."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql import Window as W

from ..functions.predicates import Ordering, Window
from ..plans.fixpoint import reach_fixpoint, scalar_fixpoint
from ..session import settle, settle_partitioned
from .edgemap import window_edges
from .graph import TemporalGraph
from .paths import _seeds, source_frame


#: Rounds of the search over the expanded graph before one task may finish it, and the most arcs (times sources) that such a task may hold.
SEARCH_ROUNDS, TASK_ARCS = 12, 4_000_000


def message_passing_arrival(graph: TemporalGraph, sources, window: Window, predicate: Ordering | None = None) -> tuple[DataFrame, DataFrame]:
    """Supersteps in which every improved vertex sends along all its edges; receivers test window and order.

    (source, v, arrival), and (round, messages).
    """
    predicate = predicate or graph.predicate
    edges = window_edges(graph.walkable())  # all edges, laid out once; only messages move
    sent = []

    def superstep(delta: DataFrame) -> DataFrame:
        messages = edges.meet(delta.select("source", "v", "label"))
        sent.append(messages.agg(F.count("*").alias("messages")).withColumn("round", F.lit(len(sent) + 1)))
        return messages.where(window.contains() & predicate.follows_label(F.col("label"), F.col("t_start"))).select("source", F.col("dst").alias("v"), F.col("t_end").alias("label"))

    found = scalar_fixpoint(_seeds(source_frame(graph.edges.sparkSession, sources), predicate.seed(window.start)), superstep)
    counts = sent[0]
    for s in sent[1:]:
        counts = counts.unionByName(s)
    arrival = F.when(F.col("v") == F.col("source"), F.lit(window.start).cast("long")).otherwise(F.col("label"))
    return found.select("source", "v", arrival.alias("arrival")), counts.select("round", "messages")


def time_expanded(graph: TemporalGraph, window: Window, predicate: Ordering | None = None) -> tuple[DataFrame, DataFrame]:
    """(nodes, arcs) of the static graph of (vertex, time, side) copies.

    Travel arcs lead from the departing side at a start to the arriving side at an end. An
    arriving copy waits for a departing copy of the same vertex at the same time or later
    (strictly later under `strictly_succeeds`), departing copies wait for later ones.
    """
    predicate = predicate or graph.predicate
    e = graph.restrict(window).walkable().select("src", "dst", "t_start", "t_end")
    out = e.select(F.col("src").alias("v"), F.col("t_start").alias("t")).distinct().withColumn("side", F.lit(1))
    arrive = e.select(F.col("dst").alias("v"), F.col("t_end").alias("t")).distinct().withColumn("side", F.lit(0))
    nodes = out.unionByName(arrive)
    copy = lambda v, t, side: F.struct(F.col(v).alias("v"), F.col(t).alias("t"), F.lit(side).alias("side"))
    travel = e.select(copy("src", "t_start", 1).alias("a"), copy("dst", "t_end", 0).alias("b")).distinct()
    # the next departure of every copy, in one sweep of a vertex's times from the last to the first
    gap = 1 if predicate is Ordering.STRICTLY_SUCCEEDS else 0
    departs = F.min(F.when(F.col("side") == 1, F.col("t")))
    back = W.partitionBy("v").orderBy(-F.col("t"))
    ahead = nodes.withColumn("t2", F.when(F.col("side") == 0, departs.over(back.rangeBetween(W.unboundedPreceding, -gap))).otherwise(departs.over(back.rangeBetween(W.unboundedPreceding, -1)))).where("t2 is not null")
    first, follow = ahead.where("side = 0"), ahead.where("side = 1")
    wait = first.select(copy("v", "t", 0).alias("a"), copy("v", "t2", 1).alias("b")).unionByName(follow.select(copy("v", "t", 1).alias("a"), copy("v", "t2", 1).alias("b")))
    return nodes, travel.unionByName(wait)


def _search_rest(arcs: DataFrame, states: DataFrame, last: int) -> DataFrame:
    """(source, v, arrival): the static search carried on in one task from the states that round `last` reached.

    A chain of waits and of touching edges is as many arcs deep as it has events, far more rounds than jobs can pay for.
    """
    none = F.lit(0).cast("long")
    ends = [F.col(f"{x}.{c}").cast("long").alias(f"{x}_{c}") for x in "ab" for c in ("v", "t", "side")]
    known = [F.col(f"at.{c}").cast("long").alias(f"a_{c}") for c in ("v", "t", "side")]
    rows = arcs.select(none.alias("source"), *ends, F.lit(-1).alias("round")).unionByName(
        states.select("source", *known, *[none.alias(f"b_{c}") for c in ("v", "t", "side")], F.col("round").cast("int").alias("round"))
    )

    def search(batches):
        import numpy as np
        import pandas as pd

        rows = pd.concat(list(batches), ignore_index=True)
        is_arc = (rows["round"] < 0).to_numpy()
        names = ["v", "t", "side"]
        tails = rows[["a_v", "a_t", "a_side"]].set_axis(names, axis=1)
        heads = rows.loc[is_arc, ["b_v", "b_t", "b_side"]].set_axis(names, axis=1)
        nodes = pd.concat([tails, heads], ignore_index=True)
        ids = nodes.groupby(names, sort=False).ngroup().to_numpy()
        first = np.unique(ids, return_index=True)[1]
        v, t, arrives = nodes["v"].to_numpy()[first], nodes["t"].to_numpy()[first], nodes["side"].to_numpy()[first] == 0
        tail, head = ids[: len(rows)][is_arc], ids[len(rows) :]
        order = np.argsort(tail, kind="stable")
        begin = np.searchsorted(tail[order], np.arange(len(first) + 1)).tolist()
        head = head[order].tolist()
        at, own, reached = ids[: len(rows)], rows["source"].to_numpy(), rows["round"].to_numpy()
        for source in np.unique(own[~is_arc]):
            mine = ~is_arc & (own == source)
            seen = np.zeros(len(first), dtype=np.uint8)
            seen[at[mine]] = 1
            seen = bytearray(seen)
            stack = at[mine & (reached == last)].tolist()
            while stack:
                x = stack.pop()
                for y in head[begin[x] : begin[x + 1]]:
                    if not seen[y]:
                        seen[y] = 1
                        stack.append(y)
            hit = (np.frombuffer(seen, dtype=np.uint8) == 1) & arrives & (v != source)
            yield pd.DataFrame({"v": v[hit], "arrival": t[hit]}).groupby("v", as_index=False).min().assign(source=source)[["source", "v", "arrival"]]

    return settle(rows.coalesce(1).mapInPandas(search, "source long, v long, arrival long"))


def time_expanded_arrival(graph: TemporalGraph, sources, window: Window, predicate: Ordering | None = None, task_arcs: int = TASK_ARCS) -> DataFrame:
    """(source, v, arrival) by a static search of the expanded graph.

    Rounds of joins reach what lies near. If they don't end it, and all arcs fit one task
    (`task_arcs`, for each source), that task finishes the search; otherwise the rounds go on.
    """
    nodes, arcs = time_expanded(graph, window, predicate)
    nodes, arcs = settle(nodes), settle_partitioned(arcs, int(graph.edges.sparkSession.conf.get("spark.sql.shuffle.partitions")), "a")
    src = source_frame(arcs.sparkSession, sources)
    begin = src.join(nodes.where("side = 1"), F.col("source") == F.col("v")).groupBy("source", "v", "side").agg(F.min("t").alias("t"))
    seed = begin.select("source", F.struct("v", "t", "side").alias("at"))
    step = lambda d: d.join(arcs, F.col("at") == F.col("a")).select("source", F.col("b").alias("at"))
    fits = arcs.count() * max(1, src.count()) <= task_arcs
    states = reach_fixpoint(seed, step, ["source", "at"], SEARCH_ROUNDS if fits else None)
    if fits and not states.where(F.col("round") == SEARCH_ROUNDS).isEmpty():
        found = _search_rest(arcs, states, SEARCH_ROUNDS)
    else:
        found = states.where("at.side = 0 and at.v <> source").groupBy("source", F.col("at.v").alias("v")).agg(F.min("at.t").alias("arrival"))
    return found.unionByName(src.select("source", F.col("source").alias("v"), F.lit(window.start).cast("long").alias("arrival")))


def one_pass_arrival(graph: TemporalGraph, sources: list[int], window: Window, predicate: Ordering | None = None) -> DataFrame:
    """(source, v, arrival) by one sweep over the window's edges in order of start.

    The sweep is sequential by nature: one sorted partition carries the labels of all sources.
    It suits windows that one task can read; the engine's own loops have no such bound.
    """
    predicate = predicate or graph.predicate
    strict, start = predicate is Ordering.STRICTLY_SUCCEEDS, window.start
    given = sorted({int(s) for s in sources})
    edges = graph.restrict(window).walkable().select("src", "dst", "t_start", "t_end").coalesce(1).sortWithinPartitions("t_start", "t_end", "src", "dst")
    schema = T.StructType([T.StructField(c, T.LongType()) for c in ("source", "v", "arrival")])

    def sweep(batches):
        import pandas as pd

        seed = start - 1 if strict else start
        labels = {s: {s: seed} for s in given}

        def relax(group) -> None:
            # equal starts: a zero-length edge can make an edge of the group usable, so repeat until stable
            again = True
            while again:
                again = False
                for u, v, t0, t1 in group:
                    for own in labels.values():
                        at = own.get(u)
                        if at is not None and (at < t0 if strict else at <= t0) and t1 < own.get(v, t1 + 1):
                            own[v] = t1
                            again = again or t1 == t0
        held, now = [], None
        for b in batches:
            for row in zip(b["src"].tolist(), b["dst"].tolist(), b["t_start"].tolist(), b["t_end"].tolist()):
                if row[2] != now and held:
                    relax(held)
                    held = []
                now = row[2]
                held.append(row)
        relax(held)
        rows = [(s, v, start if v == s else t) for s, own in labels.items() for v, t in own.items()]
        yield pd.DataFrame(rows, columns=["source", "v", "arrival"])

    found = edges.mapInPandas(sweep, schema)
    if graph.edges.isEmpty():
        return source_frame(graph.edges.sparkSession, given).select("source", F.col("source").alias("v"), F.lit(start).cast("long").alias("arrival"))
    return found.groupBy("source", "v").agg(F.min("arrival").alias("arrival"))
