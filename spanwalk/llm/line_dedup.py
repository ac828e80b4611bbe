"""Exact line deduplication over levelled sorted runs of line hashes.

Lines of all texts are hashed once and dealt into batches by ascending doc_id. A run holds
distinct keys with the first doc_id of each, hash-partitioned and sorted by key; all runs share
one number of partitions, so a batch's keys, grouped into the same partitions, are
merge-anti-joined with every run without moving or sorting the run again. What is left is new and
becomes a run of its own; when a level has `fanout` runs they are compacted into one run of the
next level and deleted, so the number of runs to read stays logarithmic. After the last batch
the runs say which document keeps a line: lines are anti-joined with them by key and doc_id
together, so a line that a third of all documents hold is spread over as many partitions as any
other rows. Everything is DataFrame expressions; a key is identified by 128 bits of hash.

There are as many batches as the table has BATCH_BYTES, but four at least (so that levels are
used at any size) and MOST_BATCHES at most (each batch reads the runs before it).

Defined results: a null or empty text is one empty line; a key is counted once per doc_id, so
repeated rows of one doc_id lose or keep their lines alike; rows with a null id are returned
whole; keys shorter than `least` code points never count; extra columns are not read.
"""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ASCII_SPACE, id_and_text, lower_ascii, release, settle_laid, store, text_of

LEAST, FANOUT = 10, 2
LEAST_BATCHES, MOST_BATCHES, BATCH_BYTES = 4, 12, 1 << 40


def line_key(line: Column) -> Column:
    return lower_ascii(F.btrim(line, F.lit(ASCII_SPACE)))


class LineRuns:
    """Runs (k1, k2, first), partitioned and sorted by key; no key is in two runs."""

    def __init__(self, fanout: int = FANOUT):
        self.fanout = fanout
        self.levels: list[list[DataFrame]] = [[]]
        self.compacted = 0

    @property
    def runs(self) -> list[DataFrame]:
        return [run for level in self.levels for run in level]

    def unknown(self, keys: DataFrame) -> DataFrame:
        """The rows of `keys` that no run holds."""
        for run in self.runs:
            keys = keys.join(run.select("k1", "k2").hint("merge"), ["k1", "k2"], "left_anti")
        return keys

    def add(self, keys: DataFrame, more: bool = True) -> None:
        """Append a batch's new keys, grouped by (k1, k2), as a run; compact levels that are full if batches follow."""
        self.levels[0].append(settle_laid(keys.sortWithinPartitions("k1", "k2")))
        at = 0
        while more and len(self.levels[at]) >= self.fanout:
            if at + 1 == len(self.levels):
                self.levels.append([])
            merged = reduce(DataFrame.unionByName, self.levels[at]).groupBy("k1", "k2").agg(F.min("first").alias("first"))
            self.levels[at + 1].append(settle_laid(merged.sortWithinPartitions("k1", "k2")))
            release(*self.levels[at])
            self.levels[at] = []
            self.compacted += 1
            at += 1


def _lines(docs: DataFrame, least: int) -> DataFrame:
    """(doc_id, sign, pos, k1, k2) of every line whose key is long enough."""
    each = docs.where("doc_id is not null").select("doc_id", F.hash("text").alias("sign"), F.posexplode(F.split(text_of(), "\n", -1)).alias("pos", "line"))
    keyed = each.where(F.octet_length("line") >= least).select("doc_id", "sign", "pos", line_key(F.col("line")).alias("key")).where(F.char_length("key") >= least)
    return keyed.select("doc_id", "sign", "pos", F.xxhash64("key").alias("k1"), F.xxhash64(F.lit("second"), "key").alias("k2"))


def batch_cuts(docs: DataFrame, batches: int) -> list[int]:
    """The last doc_id of every batch but the last."""
    if batches < 2:
        return []
    return sorted(set(docs.agg(F.percentile_approx("doc_id", [k / batches for k in range(1, batches)], 1000).alias("c")).head().c or []))


def batches_for(docs: DataFrame) -> int:
    """From the size that the planner knows; a plan that knows none says 2^63 and more."""
    size = int(str(docs._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return LEAST_BATCHES if size >= 1 << 62 else min(MOST_BATCHES, max(LEAST_BATCHES, math.ceil(size / BATCH_BYTES)))


def repeated_lines(docs: DataFrame, least: int = LEAST, batches: int | None = None, fanout: int = FANOUT, runs: LineRuns | None = None) -> DataFrame:
    """(doc_id, sign, pos) of the lines to drop."""
    cuts = batch_cuts(docs, batches or batches_for(docs))
    batch = sum([F.when(F.col("doc_id") > c, 1).otherwise(0) for c in cuts], F.lit(0))
    lines = store(_lines(docs, least).withColumn("batch", batch), "lines")
    runs = runs or LineRuns(fanout)
    for b in range(len(cuts) + 1):
        keys = lines.where(F.col("batch") == b).groupBy("k1", "k2").agg(F.min("doc_id").alias("first"))
        runs.add(runs.unknown(keys), more=b < len(cuts))
    keeps = reduce(DataFrame.unionByName, runs.runs).select("k1", "k2", F.col("first").alias("doc_id"))
    return lines.select("doc_id", "sign", "pos", "k1", "k2").join(keeps.hint("merge"), ["doc_id", "k1", "k2"], "left_anti").select("doc_id", "sign", "pos")


def dedup_lines(docs: DataFrame, least: int = LEAST, batches: int | None = None, fanout: int = FANOUT, keep: list[str] = ()) -> DataFrame:
    """(doc_id, columns of `keep`, kept_text, n_lines, n_dropped) of every row."""
    plain = id_and_text(docs)
    gone = repeated_lines(plain, least, batches, fanout).groupBy(F.col("doc_id").alias("__id"), F.col("sign").alias("__sign")).agg(F.array_sort(F.collect_set("pos")).alias("__gone"))
    rows = docs.select(F.col("doc_id").cast("long").alias("__doc"), F.col("text").cast("string").alias("__text"), *[F.col(c).alias(f"__keep_{c}") for c in keep])
    rows = rows.join(gone.hint("shuffle_hash"), (F.col("__doc") == F.col("__id")) & (F.hash("__text") == F.col("__sign")), "left")
    text = text_of("__text")
    counted = F.char_length(text) - F.char_length(F.replace(text, F.lit("\n"), F.lit(""))) + 1
    return rows.select(
        F.col("__doc").alias("doc_id"), *[F.col(f"__keep_{c}").alias(c) for c in keep],
        F.when(F.col("__gone").isNull(), text).otherwise(F.array_join(_kept_lines(text), "\n")).alias("kept_text"),
        counted.cast("long").alias("n_lines"), F.coalesce(F.size("__gone"), F.lit(0)).cast("long").alias("n_dropped"),
    )


def _kept_lines(text: Column) -> Column:
    """The lines at positions not in __gone, in linear time: the split array is bound once."""
    both = F.array(F.split(text, "\n", -1))
    return F.flatten(F.transform(both, lambda parts: F.transform(F.array_except(F.sequence(F.lit(0), F.size(parts) - 1), F.col("__gone")), lambda k: F.get(parts, k))))


def digest(done: DataFrame) -> DataFrame:
    return done.select("doc_id", "n_lines", "n_dropped", F.sha2("kept_text", 256).alias("kept_sha256"))


def rewrite(docs: DataFrame) -> DataFrame:
    """`docs` with the kept lines as text and n_chars to match; columns and order unchanged."""
    others = [c for c in docs.columns if c not in ("doc_id", "text", "n_chars")]
    done = dedup_lines(docs, keep=others).withColumn("n_chars", F.char_length("kept_text").cast("long")).withColumnRenamed("kept_text", "text")
    return done.select(docs.columns)


ORACLE_SQL = r"""
WITH d AS (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS parts FROM documents),
l AS (SELECT doc_id, unnest(parts) AS line, unnest(range(len(parts))) AS pos FROM d),
k AS (SELECT doc_id, pos, line,
  translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM l),
o AS (SELECT key, min(doc_id) AS owner FROM k WHERE length(key) >= 10 GROUP BY key HAVING count(DISTINCT doc_id) >= 2),
m AS (SELECT k.doc_id, k.pos, k.line, o.owner IS NOT NULL AND o.owner <> k.doc_id AS gone FROM k LEFT JOIN o USING (key))
SELECT doc_id, count(*)::BIGINT AS n_lines, count(*) FILTER (WHERE gone)::BIGINT AS n_dropped,
  sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT gone), '')) AS kept_sha256
FROM m GROUP BY doc_id
"""
