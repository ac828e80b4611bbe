"""Embedding near-duplicates by random-hyperplane sign hashing.

Vectors of one label whose signs against `bits` random hyperplanes agree meet in a bucket of
that table; `tables` tables are independent. Inside a bucket cosines are computed in double
precision. A pair that meets in several tables is counted in the first of them only: rows carry
the codes of all tables, so no pair is ever shuffled to remove repeats. A bucket gives at most
one row for each of its members (links counted) and a spanning forest, never its pairs. Equal
vectors are folded first; buckets above `block` members are dealt out as pairs of blocks.

`plan_tables` chooses bits by the number of vectors, and tables so that a pair at the threshold
is found with the stated probability; closer pairs are found more surely.

Defined results: only vectors of one length are compared, each length with its own hyperplanes.
Vectors that are null, zero, or hold null or non-finite components, and rows with a null label,
link with nothing (their own component); vectors are scaled by their largest component before
their length is taken, so tiny and huge ones link like others. Labels may be of any type and are
compared as text. Rows with a null vec_id are returned with no links and a null component. A
vec_id is one vector: if its rows hold several, the one of the least hash stands for it, and each
of its rows gets the same result. Extra columns are not read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import settle, ship
from .components import connected_components

THRESHOLD, RECALL, BLOCK, SEED = 0.93, 0.995, 2000, 7


def plan_tables(n: int, threshold: float = THRESHOLD, recall: float = RECALL) -> tuple[int, int]:
    """(bits, tables): buckets of a few vectors if they were spread evenly, and the wished recall."""
    bits = min(24, max(8, math.ceil(math.log2(max(2, n))) - 4))
    agree = (1 - math.acos(min(1.0, threshold)) / math.pi) ** bits
    return bits, max(1, math.ceil(math.log(1 - recall) / math.log(1 - agree)))


def planes(width: int, bits: int, tables: int, seed: int = SEED) -> np.ndarray:
    return np.random.default_rng(seed).standard_normal((width, bits * tables))


def unit_rows(x: np.ndarray) -> np.ndarray:
    """Rows of length one; scaled first, so that squares neither vanish nor overflow."""
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def sign_codes(x: np.ndarray, normals: np.ndarray, bits: int, tables: int) -> np.ndarray:
    signs = (x @ normals > 0).reshape(len(x), tables, bits)
    return signs @ (1 << np.arange(bits, dtype=np.int64))


def _forest(near: np.ndarray) -> tuple[list[int], list[int]]:
    """A spanning forest of the graph whose neighbour matrix is given."""
    left, a, b = np.ones(len(near), dtype=bool), [], []
    for k in range(len(near)):
        if not left[k]:
            continue
        left[k] = False
        queue = [k]
        while queue:
            at = queue.pop()
            new = np.flatnonzero(near[at] & left)
            left[new] = False
            a += [at] * len(new)
            b += new.tolist()
            queue += new.tolist()
    return a, b


class _Bucket:
    """Verifies one bucket (or one pair of blocks of a large one)."""

    def __init__(self, threshold: float):
        self.threshold = threshold
        self.counts: list[tuple[np.ndarray, np.ndarray]] = []
        self.links: list[tuple[np.ndarray, np.ndarray]] = []

    def add(self, t: int, node: np.ndarray, copies: np.ndarray, unit: np.ndarray, codes: np.ndarray, side: np.ndarray) -> None:
        one, two = np.flatnonzero(side != 2), np.flatnonzero(side != 1)
        within = bool((side == 0).all())
        if within:
            one = two = np.arange(len(node))
        if len(one) == 0 or len(two) == 0:
            return
        near = unit[one] @ unit[two].T >= self.threshold
        if within:
            np.fill_diagonal(near, False)
        for earlier in range(t):
            if not near.any():
                return
            near &= codes[one, earlier][:, None] != codes[two, earlier][None, :]
        if not near.any():
            return
        self.counts.append((node[one], near @ copies[two]))
        if within:
            a, b = _forest(near)
            self.links.append((node[a], node[b]))
        else:
            self.counts.append((node[two], near.T @ copies[one]))
            full = np.zeros((len(node), len(node)), dtype=bool)
            full[: len(one), len(one) :] = near
            a, b = _forest(full | full.T)
            both = np.concatenate([node[one], node[two]])
            self.links.append((both[a], both[b]))

    def rows(self) -> pa.RecordBatch:
        node = np.concatenate([np.zeros(0, np.int64), *(n for n, _ in self.counts), *(a for a, _ in self.links)])
        links = np.concatenate([np.zeros(0, np.int64), *(c for _, c in self.counts), *(np.zeros(len(a), np.int64) for a, _ in self.links)])
        other = np.concatenate([np.zeros(0, np.int64), *(n for n, _ in self.counts), *(b for _, b in self.links)])
        some = (links > 0) | (node != other)
        self.counts, self.links = [], []
        return pa.RecordBatch.from_arrays([pa.array(x[some].astype(np.int64)) for x in (node, links, other)], ["node", "links", "other"])


def _verify(batches: Iterator[pa.RecordBatch], threshold: float, bits: int, tables: int) -> Iterator[pa.RecordBatch]:
    """Rows sorted by (space, width, t, code, pair); one bucket is held at a time."""
    held, held_key = [], None
    bucket, normals = _Bucket(threshold), None

    def done():
        rows = [np.concatenate([h[k] for h in held]) for k in range(4)]
        if len(rows[0]) < 2:
            return
        nonlocal normals
        unit = unit_rows(rows[2])
        if normals is None or len(normals) != unit.shape[1]:
            normals = planes(unit.shape[1], bits, tables)
        bucket.add(held_key[2], rows[0], rows[1], unit, sign_codes(unit, normals, bits, tables), rows[3])

    for batch in batches:
        if not batch.num_rows:
            continue
        keys = np.stack([np.asarray(batch.column(c)).astype(np.int64) for c in ("space", "width", "t", "code", "pair")], axis=1)
        node, copies, side = (np.asarray(batch.column(c)) for c in ("node", "copies", "side"))
        flat = np.asarray(batch.column("embedding").flatten())
        places = np.concatenate([[0], np.cumsum(keys[:, 1])])
        new = np.flatnonzero((keys[1:] != keys[:-1]).any(axis=1)) + 1
        for a, b in zip([0, *new.tolist()], [*new.tolist(), len(keys)]):
            key = tuple(keys[a].tolist())
            if key != held_key and held_key is not None:
                done()
                held = []
            held_key = key
            held.append((node[a:b], copies[a:b], flat[places[a] : places[b]].reshape(b - a, -1), side[a:b]))
        if bucket.counts or bucket.links:
            yield bucket.rows()
    if held:
        done()
    yield bucket.rows()


def usable(vectors: DataFrame, id_col: str, vector_col: str, label_col: str) -> DataFrame:
    """(vec_id, label, embedding) of the rows that can link, components in double precision."""
    rows = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(label_col).cast("string").alias("label"), F.col(vector_col).cast("array<double>").alias("embedding"))
    finite = F.forall("embedding", lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf")))
    some = F.exists("embedding", lambda v: v != 0)
    return rows.where("vec_id is not null and label is not null and embedding is not null").where(finite & some)


def link_embeddings(vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", label_col: str = "label", threshold: float = THRESHOLD, recall: float = RECALL, block: int = BLOCK) -> DataFrame:
    """(vec_id, n_links, component_id, kept) of every row."""
    spark = vectors.sparkSession
    ship(spark)
    good = usable(vectors, id_col, vector_col, label_col)
    # equal vectors of a label are one class: its smallest id stands for it, with its number of ids
    sign = F.struct(F.xxhash64("label", "embedding").alias("h1"), F.xxhash64(F.lit("second"), "label", "embedding").alias("h2"))
    members = good.withColumn("h", sign)
    ids = settle(members.groupBy("vec_id").agg(F.min("h").alias("h")).select("vec_id", "h.h1", "h.h2"))
    classes = members.groupBy("h").agg(F.first("label").alias("label"), F.first("embedding").alias("embedding")).select("h.h1", "h.h2", F.xxhash64("label").alias("space"), F.size("embedding").alias("width"), "embedding")
    sizes = ids.groupBy("h1", "h2").agg(F.min("vec_id").alias("node"), F.count("*").alias("copies"))
    nodes = settle(classes.join(sizes, ["h1", "h2"]).select("h1", "h2", "node", "copies", "space", "width", "embedding"))
    bits, tables = plan_tables(nodes.count(), threshold, recall)
    vectors_of = ["node", "space", "width"]

    def spread(batches):
        normals: dict[int, np.ndarray] = {}
        for batch in batches:
            width = np.asarray(batch.column("width"))
            for w in np.unique(width).tolist():
                if w not in normals:
                    normals = {w: planes(w, bits, tables)}  # one width's at a time
                own = batch.filter(pa.array(width == w))
                for at in range(0, own.num_rows, 2000):
                    part = own.slice(at, 2000)
                    codes = sign_codes(unit_rows(np.asarray(part.column("embedding").flatten()).reshape(part.num_rows, -1)), normals[w], bits, tables)
                    lists = pa.ListArray.from_arrays(np.arange(0, len(codes) * tables + 1, tables, dtype=np.int32), pa.array(codes.ravel()))
                    yield pa.RecordBatch.from_arrays([*(part.column(c) for c in vectors_of), lists], [*vectors_of, "codes"])

    codes = settle(nodes.select(*vectors_of, "embedding").mapInArrow(spread, "node long, space long, width int, codes array<long>"))
    keyed = codes.select(*vectors_of, F.posexplode("codes").alias("t", "code"))
    heavy = keyed.groupBy("space", "width", "t", "code").agg(F.count("*").alias("n")).where(F.col("n") > 1)
    # buckets of one need no vectors; large ones are dealt out as pairs of blocks
    parts = F.ceil(F.col("n") / F.lit(block)).cast("int")
    met = keyed.join(heavy, ["space", "width", "t", "code"]).withColumn("parts", parts).withColumn("own", F.pmod(F.xxhash64("node"), F.col("parts")).cast("int"))
    places = F.when(F.col("parts") == 1, F.array(F.struct(F.lit(0).alias("pair"), F.lit(0).alias("side")))).otherwise(
        F.transform(F.sequence(F.lit(0), F.col("parts") - 1), lambda k: F.struct((F.least(k, F.col("own")) * F.col("parts") + F.greatest(k, F.col("own"))).cast("int").alias("pair"), F.when(k == F.col("own"), 0).when(F.col("own") < k, 1).otherwise(2).cast("int").alias("side")))
    )
    dealt = met.select(*vectors_of, "t", "code", F.explode(places).alias("p")).select(*vectors_of, "t", "code", "p.pair", "p.side")
    bucket = ["space", "width", "t", "code", "pair"]
    full = dealt.join(nodes.select("node", "copies", "embedding"), "node").select("node", "copies", *bucket, "side", "embedding")
    found = settle(full.repartition(*bucket).sortWithinPartitions(*bucket).mapInArrow(lambda it: _verify(it, threshold, bits, tables), "node long, links long, other long"))
    counts = found.where("links > 0").groupBy("node").agg(F.sum("links").alias("links"))
    groups = connected_components(found.where("node <> other").select(F.col("node").alias("a"), F.col("other").alias("b")))
    by_class = nodes.select("h1", "h2", "node", "copies").join(counts, "node", "left").join(groups, "node", "left").select("h1", "h2", (F.col("copies") - 1 + F.coalesce("links", F.lit(0))).alias("n_links"), F.coalesce("component", "node").alias("component_id"))
    by_id = ids.join(by_class, ["h1", "h2"]).select("vec_id", "n_links", "component_id")
    out = vectors.select(F.col(id_col).cast("long").alias("vec_id")).join(by_id, "vec_id", "left")
    return out.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component_id", "vec_id").alias("component_id")).withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(False)))
