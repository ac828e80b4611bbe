"""Helpers shared by the training-data operators."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import release, settle, settle_laid, shared_dir, ship

__all__ = ["ASCII_SPACE", "id_and_text", "lower_ascii", "map_texts", "pieces", "read", "release", "settle", "settle_laid", "shared_dir", "ship", "small_batches", "store", "stretch", "text_of"]

#: The white space that several contracts strip or split at: [\x20\x09-\x0D].
ASCII_SPACE = " \t\n\x0b\x0c\r"


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def store(df: DataFrame, name: str) -> DataFrame:
    """Write `df` as Parquet in the shared folder and read it again (compact, columns prunable)."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def text_of(column: str = "text") -> Column:
    return F.coalesce(F.col(column).cast("string"), F.lit(""))


def lower_ascii(text: Column) -> Column:
    """A-Z lower-cased, all else kept; `lower` alone would also change letters beyond ASCII."""
    upper = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
    return F.when(F.octet_length(text) == F.char_length(text), F.lower(text)).otherwise(F.translate(text, upper, upper.lower()))


def id_and_text(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Only the two columns that an operator reads, so that other columns can't clash with its own."""
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))


def stretch(text: Column, most: int) -> Column:
    """The text, or of a longer one `most` characters from a place given by its hash; bounds what training rows weigh."""
    room = F.char_length(text) - F.lit(most)
    return F.when(room <= 0, text).otherwise(F.substring(text, F.pmod(F.xxhash64(text), F.greatest(room, F.lit(1))).cast("int") + 1, F.lit(most)))


def map_texts(docs: DataFrame, make: Callable[[], Callable[[list], dict]], schema: str, key: str = "long") -> DataFrame:
    """Rows (doc_id, text) to rows (doc_id, columns of `schema`), one for one.

    `make()` runs once a task and gives a function from a list of texts (None for null) to
    lists or Arrow arrays by column name. Batches are cut so that a run of very long texts
    does not sit in memory at once.
    """
    ship(docs.sparkSession)
    small_batches(docs.sparkSession)
    names = [x.split()[0] for x in schema.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        work = make()
        for batch in batches:
            for part in pieces(batch):
                out = work(part.column("text").to_pylist())
                columns = [out[n] for n in names]
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), *(c if isinstance(c, pa.Array) else pa.array(c) for c in columns)], ["doc_id", *names])

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {key}, {schema}")


def small_batches(spark: SparkSession, most: int = 8 << 20) -> None:
    """Bound the bytes that go to a Python worker at once; texts may be long and workers are many."""
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    now = spark.conf.get(key, None)
    if now is None or not now.rstrip("b").isdigit() or int(now.rstrip("b")) > most:
        spark.conf.set(key, f"{most}b")


def pieces(batch: pa.RecordBatch, most_bytes: int = 4_000_000) -> Iterator[pa.RecordBatch]:
    rows, total = batch.num_rows, max(1, batch.nbytes)
    step = max(1, min(rows, rows * most_bytes // total))
    for at in range(0, rows, step):
        yield batch.slice(at, step)
