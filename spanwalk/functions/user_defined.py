"""User-defined functions where built-in ones can't say it, all batched through Arrow."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.pandas_udf(T.DoubleType())
def burstiness(starts: pd.Series) -> float:
    """Burstiness of a group's start times: (sd - mean) / (sd + mean) of the gaps."""
    gaps = starts.sort_values().diff().dropna()
    total = gaps.std(ddof=0) + gaps.mean() if len(gaps) else 0
    return float((gaps.std(ddof=0) - gaps.mean()) / total) if total > 0 else None


@F.pandas_udf(T.DoubleType())
def log_scale(x: pd.Series) -> pd.Series:
    return pd.Series(np.log1p(x.clip(lower=0)))


class RecentWindows:
    """Table function: one row (k, start, end) for each of the last `n` spans of `width` before `end`."""

    def eval(self, end: int, width: int, n: int):
        for k in range(n):
            yield k, end - (k + 1) * width, end - k * width


def register(spark: SparkSession) -> None:
    spark.udtf.register("recent_windows", F.udtf(RecentWindows, returnType="k int, start bigint, `end` bigint"))
