"""Loops to a fixpoint over labelled states.

Every round is one job: candidates from the states that changed last, reduced per key, minus
what the states so far make useless, settled in the shared folder. States are kept as the union
of the rounds' changes and compacted now and then, so a round's cost follows the frontier.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..session import release, settle

COMPACT = 8


def _union(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def scalar_fixpoint(seed: DataFrame, step: Callable[[DataFrame], DataFrame], largest: bool = False, max_rounds: int | None = None, stop: Callable[[DataFrame], bool] | None = None) -> DataFrame:
    """(source, v, label, round, settled): best label of each key, the first round that reached it at all, and the first that found that label.

    `step` turns changed states into candidates (source, v, label). A key comes back whenever its
    label improves; labels are drawn from finitely many times and improve strictly, so it ends.
    """
    best = F.max if largest else F.min
    better = (lambda new, old: new > old) if largest else (lambda new, old: new < old)
    delta = settle(seed.select("source", "v", "label").withColumns({"round": F.lit(0), "settled": F.lit(0)}))
    parts, n, compacted = [delta], 0, None
    sign = -1 if largest else 1

    def compact(frames: list[DataFrame]) -> DataFrame:
        rows = _union(frames).groupBy("source", "v").agg(F.min("round").alias("round"), F.min(F.struct((F.col("label") * sign).alias("key"), "settled")).alias("b"))
        return rows.select("source", "v", (F.col("b.key") * sign).alias("label"), "round", "b.settled")

    while max_rounds is None or n < max_rounds:
        n += 1
        found = step(delta).groupBy("source", "v").agg(best("label").alias("label"))
        known = (compact(parts) if len(parts) > 1 else parts[0]).select("source", "v", F.col("label").alias("old"))
        fresh = found.join(known, ["source", "v"], "left").where(F.col("old").isNull() | better(F.col("label"), F.col("old")))
        delta = settle(fresh.select("source", "v", "label", F.lit(n).alias("round"), F.lit(n).alias("settled")))
        if delta.isEmpty():
            break
        parts.append(delta)
        if len(parts) > COMPACT:
            parts = [settle(compact(parts))]
            release(compacted)
            compacted = parts[0]
        if stop is not None and stop(_union(parts)):
            break
    return compact(parts)


def pareto(df: DataFrame, keys: list[str], x: str = "x", y: str = "y") -> DataFrame:
    """Rows of each key that no other equals or beats in both coordinates; smaller is better."""
    order = W.partitionBy(*keys).orderBy(x, y)
    least = F.min(y).over(order.rowsBetween(W.unboundedPreceding, -1))
    return df.withColumn("__least", least).where(F.col("__least").isNull() | (F.col(y) < F.col("__least"))).drop("__least")


def pareto_fixpoint(seed: DataFrame, step: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """(source, v, x, y): for each key all labels that none dominates.

    Rounds append what no earlier label dominates; labels that a later one dominates stay until
    the parts are compacted and do no harm.
    """
    keys = ["source", "v"]
    delta = settle(pareto(seed.select("source", "v", "x", "y").distinct(), keys))
    parts, compacted = [delta], None
    while True:
        found = pareto(step(delta).distinct(), keys)
        old = _union(parts).select(F.col("source").alias("s0"), F.col("v").alias("v0"), F.col("x").alias("x0"), F.col("y").alias("y0"))
        fresh = found.join(old, (F.col("source") == F.col("s0")) & (F.col("v") == F.col("v0")) & (F.col("x0") <= F.col("x")) & (F.col("y0") <= F.col("y")), "left_anti")
        delta = settle(fresh)
        if delta.isEmpty():
            return settle(pareto(_union(parts), keys))
        parts.append(delta)
        if len(parts) > COMPACT:
            parts = [settle(pareto(_union(parts), keys))]
            release(compacted)
            compacted = parts[0]


def reach_fixpoint(seed: DataFrame, step: Callable[[DataFrame], DataFrame], keys: list[str], max_rounds: int | None = None) -> DataFrame:
    """(keys, round): every state reached, each once, with the first round that reached it."""
    delta = settle(seed.select(*keys).distinct().withColumn("round", F.lit(1)))
    parts, n, compacted = [delta], 1, None
    while not delta.isEmpty() and (max_rounds is None or n < max_rounds):
        n += 1
        fresh = step(delta).select(*keys).distinct().join(_union(parts).select(*keys), keys, "left_anti")
        delta = settle(fresh.withColumn("round", F.lit(n)))
        parts.append(delta)
        if len(parts) > COMPACT:
            parts = [settle(_union(parts))]
            release(compacted)
            compacted = parts[0]
    return _union(parts)
