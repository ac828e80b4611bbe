"""Session helpers: the shared folder for cut lineage, and a session for local use."""

from __future__ import annotations

import os
import tempfile
import threading
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession


_planning = threading.RLock()


def local_session(cores: int = 8, shuffle_partitions: int = 8) -> SparkSession:
    return (
        SparkSession.builder.master(f"local[{cores}]")
        .config("spark.sql.shuffle.partitions", str(shuffle_partitions))
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )


def shared_dir(spark: SparkSession) -> str:
    """The checkpoint folder that all executors share; where none is named, a temporary one on a local master only."""
    sc = spark.sparkContext
    found = sc.getCheckpointDir()
    if found is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not (sc.master or "").startswith("local"):
            raise RuntimeError("name a folder that all executors share in spark.checkpoint.dir")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="spanwalk-"))
        found = sc.getCheckpointDir()
    return found


def settle(df: DataFrame) -> DataFrame:
    """Materialise `df` in the shared folder."""
    shared_dir(df.sparkSession)
    return df.checkpoint()


def settle_laid(df: DataFrame) -> DataFrame:
    """Materialise `df` with the partitioning and order its plan gives it, which later joins rely on.

    A plan made under adaptive execution doesn't report its partitioning, and a frame settled from
    it would be shuffled by every later join; so this one job is planned without it. The lock keeps
    jobs of other threads from restoring the setting in between.
    """
    spark = df.sparkSession
    shared_dir(spark)
    with _planning:
        before = spark.conf.get("spark.sql.adaptive.enabled")
        spark.conf.set("spark.sql.adaptive.enabled", "false")
        try:
            return df.checkpoint()
        finally:
            spark.conf.set("spark.sql.adaptive.enabled", before)


def settle_partitioned(df: DataFrame, partitions: int, *keys: str) -> DataFrame:
    """Materialise `df` hash-partitioned by `keys` so that joins on them don't move it again."""
    return settle_laid(df.repartition(max(2, partitions), *keys))


def settle_columns(df: DataFrame) -> DataFrame:
    """Write `df` as Parquet in the shared folder and read it again: less disk than `settle` where values repeat."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/columns-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def settle_sorted(df: DataFrame, *keys: str) -> DataFrame:
    """Write `df` as Parquet in the shared folder in order of `keys`, so that bounds on them prune files and pages, and read it again."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/sorted-{uuid.uuid4().hex}"
    df.repartitionByRange(*keys).sortWithinPartitions(*keys).write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def remove(spark: SparkSession, path: str) -> None:
    """Delete a folder of the shared one."""
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def release(*frames: DataFrame | None) -> None:
    """Delete the files of settled frames that nothing will read any more."""
    for df in frames:
        if df is None:
            continue
        leaves = df._jdf.queryExecution().analyzed().collectLeaves()
        for k in range(leaves.size()):
            leaf = leaves.apply(k)
            if leaf.getClass().getSimpleName() != "LogicalRDD":
                continue
            kept = leaf.rdd().getCheckpointFile()
            if kept.isDefined():
                remove(df.sparkSession, kept.get())


def ship(spark: SparkSession) -> None:
    """Make this package importable in Python workers, whatever folder they start in."""
    package = Path(__file__).resolve().parent
    sc = spark.sparkContext
    if str(package.parent) in os.environ.get("PYTHONPATH", "").split(os.pathsep) or getattr(sc, "_spanwalk_shipped", False):
        return
    path = Path(tempfile.mkdtemp(prefix="spanwalk-")) / "spanwalk_package.zip"
    with zipfile.ZipFile(path, "w") as z:
        for p in package.rglob("*.py"):
            z.write(p, p.relative_to(package.parent))
    sc.addPyFile(str(path))
    sc._spanwalk_shipped = True
