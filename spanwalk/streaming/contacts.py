"""Structured Streaming over event and edge streams."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout
from pyspark.sql.types import StructType

from ..session import remove, shared_dir

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, path: str, files_per_trigger: int = 1, schema: str = EVENTS) -> DataFrame:
    """Events as a file stream; times become timestamps so that they can carry watermarks."""
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling_counts(events: DataFrame, width: str = "1 day", late: str = "1 hour", slide: str | None = None) -> DataFrame:
    span = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.withWatermark("ts", late).groupBy(span.alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total"))


def session_counts(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))


def without_repeats(events: DataFrame, keys: list[str], late: str | None = "1 hour") -> DataFrame:
    """One row for each value of `keys`. Without `late` none is dropped for its time, and the state holds every value to the end."""
    if late is None:
        return events.dropDuplicates(keys)
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(keys)


def two_hop_contacts(first: DataFrame, second: DataFrame, within: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """Stream-stream join: events of one user of two kinds, the second after the first and within a span."""
    a = first.select(F.col("user_id"), F.col("ts").alias("t0"), F.col("event_id").alias("id0")).withWatermark("t0", late)
    b = second.select(F.col("user_id").alias("__u"), F.col("ts").alias("t1"), F.col("event_id").alias("id1")).withWatermark("t1", late)
    return a.join(b, F.expr(f"user_id = __u AND t1 > t0 AND t1 <= t0 + INTERVAL {within}")).drop("__u")


def longest_gaps(events: DataFrame) -> DataFrame:
    """(user_id, longest_gap): largest distance in microseconds between a user's successive events.

    A key's state is its last time and its largest gap so far; micro-batches must be in time
    order of their files, events inside a batch need not be.
    """

    def update(key, frames, state):
        last, largest = state.get if state.exists else (None, -1)
        times = sorted(t for f in frames for t in f["t"].tolist())
        for t in times:
            if last is not None:
                largest = max(largest, t - last)
            last = t
        state.update((last, largest))
        yield pd.DataFrame({"user_id": [key[0]], "longest_gap": [largest]}) if largest >= 0 else pd.DataFrame({"user_id": pd.Series([], dtype="int64"), "longest_gap": pd.Series([], dtype="int64")})

    timed = events.select("user_id", F.unix_micros("ts").alias("t"))
    return timed.groupBy("user_id").applyInPandasWithState(update, "user_id long, longest_gap long", "last long, largest long", "update", GroupStateTimeout.NoTimeout)


class FileSink:
    """Rows of a stream as Parquet in the shared folder (foreachBatch); none of them pass through the driver.

    Every batch has a folder of its own, so one that is retried is written over. In complete mode a
    batch holds all rows, and the one before it is deleted.
    """

    def __init__(self, spark: SparkSession, root: str, schema: StructType, mode: str):
        self.spark, self.root, self.schema, self.mode = spark, root, schema, mode
        self.batches: list[int] = []

    def _path(self, batch_id: int) -> str:
        return f"{self.root}/batch-{batch_id}"

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(self._path(batch_id))
        if self.mode == "complete":
            for old in self.batches:
                if old != batch_id:
                    remove(self.spark, self._path(old))
            self.batches = []
        if batch_id not in self.batches:
            self.batches.append(batch_id)

    def rows(self) -> DataFrame:
        if not self.batches:
            return self.spark.createDataFrame([], self.schema)
        return self.spark.read.schema(self.schema).parquet(*map(self._path, self.batches))


def run_to_end(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Process what the sources hold now and return the sink's rows."""
    spark = stream.sparkSession
    path = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    sink = FileSink(spark, f"{path}-rows", stream.schema, mode)
    started = stream.writeStream.foreachBatch(sink).outputMode(mode).option("checkpointLocation", path).trigger(availableNow=True).start()
    started.awaitTermination()
    return sink.rows()


class OnlineArrival:
    """Earliest arrival kept up to date over a stream of edges, batch by batch (foreachBatch).

    A batch is joined with the labels so far and relaxed to a fixpoint inside the batch and over
    the edges kept, so edges may come in any order. Labels and edges are Parquet versions in the
    shared folder; a batch that is retried writes the same version again.
    """

    def __init__(self, spark: SparkSession, source: int, start: int, strict: bool = True):
        from ..functions.predicates import Ordering

        self.spark, self.source, self.start = spark, source, start
        self.predicate = Ordering.STRICTLY_SUCCEEDS if strict else Ordering.SUCCEEDS
        self.root = f"{shared_dir(spark)}/online-{uuid.uuid4().hex}"
        self.version = -1

    def labels(self, version: int | None = None) -> DataFrame:
        version = self.version if version is None else version
        if version < 0:
            return self.spark.createDataFrame([(self.source, self.source, self.predicate.seed(self.start))], "source long, v long, label long")
        return self.spark.read.parquet(f"{self.root}/labels-{version}")

    def edges(self) -> DataFrame:
        return self.spark.read.schema("src long, dst long, t_start long, t_end long").parquet(f"{self.root}/edges")

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        from ..operators.edgemap import expand_forward, window_edges
        from ..plans.fixpoint import scalar_fixpoint

        batch.select("src", "dst", "t_start", "t_end").write.mode("overwrite").parquet(f"{self.root}/edges/batch={batch_id}")
        old = self.labels(batch_id - 1)
        edges = window_edges(self.edges())
        # every vertex known so far may gain from the batch; later rounds follow only improvements
        found = scalar_fixpoint(old, lambda d: expand_forward(d, edges, self.predicate).select("source", F.col("dst").alias("v"), F.col("t_end").alias("label")))
        found.select("source", "v", "label").write.mode("overwrite").parquet(f"{self.root}/labels-{batch_id}")
        self.version = batch_id

    def arrivals(self) -> DataFrame:
        return self.labels().select("source", "v", F.greatest("label", F.lit(self.start).cast("long")).alias("arrival"))
