"""Reading and writing edge lists."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMA = "src long, dst long, t_start long, t_end long, weight double"


def read_edges(spark: SparkSession, path: str, kind: str = "parquet", mapping: dict[str, str] | None = None) -> DataFrame:
    """Edges from parquet, orc, csv, json or text (white-space separated); `mapping` names source columns."""
    if kind == "text":
        parts = spark.read.text(path).select(F.split(F.trim("value"), r"\s+").alias("p")).where(F.size("p") >= 4)
        return parts.select(*[F.col("p")[k].cast(t).alias(c) for k, (c, t) in enumerate([("src", "long"), ("dst", "long"), ("t_start", "long"), ("t_end", "long")])], F.coalesce(F.get("p", F.lit(4)).cast("double"), F.lit(1.0)).alias("weight"))
    reader = spark.read.schema(SCHEMA) if mapping is None and kind in ("csv", "json") else spark.read
    reader = reader.option("header", "true") if kind == "csv" else reader
    df = reader.format(kind).load(path)
    for ours, theirs in (mapping or {}).items():
        df = df.withColumnRenamed(theirs, ours)
    weight = F.col("weight").cast("double") if "weight" in df.columns else F.lit(1.0)
    return df.select(*[F.col(c).cast("long") for c in ("src", "dst", "t_start", "t_end")], weight.alias("weight"))


def write_edges(edges: DataFrame, path: str, slice_width: int | None = None, kind: str = "parquet") -> None:
    """Sorted by source and start; with `slice_width` laid out by coarse time slice, so windows prune files."""
    if slice_width:
        sliced = edges.withColumn("slice", F.floor(F.col("t_start") / slice_width))
        sliced.repartition("slice", F.pmod("src", F.lit(16))).sortWithinPartitions("slice", "src", "t_start").write.partitionBy("slice").format(kind).mode("overwrite").save(path)
    else:
        edges.sortWithinPartitions("src", "t_start").write.format(kind).mode("overwrite").option("header", "true").save(path)


def write_bucketed(edges: DataFrame, table: str, buckets: int = 64) -> None:
    """A table bucketed by source, so that frontier joins move only the frontier."""
    edges.write.bucketBy(buckets, "src").sortBy("src", "t_start").mode("overwrite").saveAsTable(table)
