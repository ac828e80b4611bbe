"""Looking into plans: their text, what they move, and counters that a job leaves behind."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Observation


def plan_text(df: DataFrame, mode: str = "formatted") -> str:
    """What `explain` prints."""
    return df.sparkSession._jvm.PythonSQLUtils.explainString(df._jdf.queryExecution(), mode)


def exchanges(df: DataFrame) -> list[str]:
    """The partitionings that the physical plan moves rows to; of a plan that has run, those of its final form."""
    plan = df._jdf.queryExecution().executedPlan().toString().split("Initial Plan")[0]
    return [line.split("Exchange ", 1)[1].strip() for line in plan.splitlines() if "Exchange " in line and "BroadcastExchange" not in line]


def counted(df: DataFrame, **counters: Column) -> tuple[DataFrame, Observation]:
    """`df`, and what its next job finds for the aggregates given; nothing is computed twice for it."""
    seen = Observation()
    return df.observe(seen, *[c.alias(name) for name, c in counters.items()]), seen
