"""Language identification by nearest centroid.

A text becomes a vector of hashed character n-gram counts (UTF-8 byte trigrams of its letters),
damped, weighted by inverse document frequency and normalised. Each language has several
centroids, found by spherical k-means over a bounded sample of labelled texts. The language of
the closest centroid by cosine is predicted; a text farther from it than training texts of that
language ever are, by a margin, is rejected.

Training rows are sampled by a hash of the id, about `per_language` of each label, fewer where
there are more than MOST_ROWS of them in all; of a text longer than MOST_CHARS a stretch at a
hashed place trains. Labels beyond the MOST_LANGUAGES most frequent can't be predicted.
Prediction covers every whole text.

Defined results: null texts and texts without a letter are `und`, score 0, rejected; without any
labelled row everything is `und`; repeated rows repeat; null ids can't train but are predicted;
extra columns are not read.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import id_and_text, map_texts, ship, small_batches, stretch

BINS, CENTROIDS, PER_LANGUAGE = 8192, 4, 400
#: Bounds of what the driver holds: languages (the most frequent ones), training rows of all of them, characters of a row.
MOST_LANGUAGES, MOST_ROWS, MOST_CHARS = 1000, 16_000, 20_000
#: A text is rejected below this share of the lowest training cosines of its language.
MARGIN = 0.25
_LETTER = re.compile(r"[^\W\d_]")
_CLEAN = bytes(b if b >= 128 or chr(b).isalpha() else 32 for b in range(256))


def gram_counts(text: str) -> np.ndarray:
    raw = b" " + b" ".join(text.lower().encode("utf-8", "surrogatepass").translate(_CLEAN).split()) + b" "
    b = np.frombuffer(raw, dtype=np.uint8).astype(np.uint32)
    h = ((b[:-2] << 16) | (b[1:-1] << 8) | b[2:]) * np.uint32(2654435761)
    return np.bincount(h >> np.uint32(19), minlength=BINS)


def has_letter(text: str | None) -> bool:
    """Is any character a letter? Fractions, superscripts and number signs aren't."""
    return bool(text) and any(m.group().isalpha() for m in _LETTER.finditer(text))


@dataclass
class Centroids:
    labels: list[str]  # one for each centroid
    centers: np.ndarray
    idf: np.ndarray
    floor: np.ndarray  # one for each centroid: below it a text is rejected

    def vectors(self, texts: list[str]) -> np.ndarray:
        x = np.log1p(np.stack([gram_counts(t) for t in texts]).astype(np.float32)) * self.idf
        return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)

    def predict(self, texts: list[str | None]) -> tuple[list[str], np.ndarray, np.ndarray]:
        label, score, kept = ["und"] * len(texts), np.zeros(len(texts)), np.zeros(len(texts), dtype=bool)
        known = [k for k, t in enumerate(texts) if has_letter(t)] if self.labels else []
        for at in range(0, len(known), 64):
            rows = known[at : at + 64]
            near = self.vectors([texts[k] for k in rows]) @ self.centers.T
            best = near.argmax(axis=1)
            value = near[np.arange(len(rows)), best]
            for k, b, v in zip(rows, best.tolist(), value.tolist()):
                label[k], score[k], kept[k] = self.labels[b], min(1.0, max(0.0, v)), v >= self.floor[b]
        return label, score, kept


def _cluster(x: np.ndarray, k: int) -> np.ndarray:
    """Spherical k-means from farthest-first centres; deterministic."""
    centers = [x.mean(axis=0)]
    while len(centers) < min(k, len(x)):
        centers.append(x[(x @ np.stack(centers).T).max(axis=1).argmin()])
    c = np.stack(centers)
    for _ in range(12):
        c = c / np.maximum(np.linalg.norm(c, axis=1, keepdims=True), 1e-12)
        own = (x @ c.T).argmax(axis=1)
        c = np.stack([x[own == j].mean(axis=0) if (own == j).any() else c[j] for j in range(len(c))])
    return c / np.maximum(np.linalg.norm(c, axis=1, keepdims=True), 1e-12)


def fit(samples: list[tuple[str, str]], k: int = CENTROIDS) -> Centroids:
    """From (text, label) pairs; texts without a letter are left out."""
    samples = sorted((label, text) for text, label in samples if has_letter(text))
    if not samples:
        return Centroids([], np.zeros((0, BINS), np.float32), np.ones(BINS, np.float32), np.zeros(0))
    counts = np.stack([gram_counts(t) for _, t in samples]).astype(np.float32)
    idf = np.log((1 + len(samples)) / (1 + (counts > 0).sum(axis=0))).astype(np.float32) + 1
    x = np.log1p(counts) * idf
    x /= np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)
    tags = np.array([label for label, _ in samples])
    labels, centers, floor = [], [], []
    for label in sorted(set(tags)):
        own = x[tags == label]
        c = _cluster(own, k)
        low = float(np.quantile((own @ c.T).max(axis=1), 0.001)) * MARGIN
        labels += [label] * len(c)
        centers.append(c)
        floor += [low] * len(c)
    return Centroids(labels, np.concatenate(centers).astype(np.float32), idf, np.array(floor))


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string")) % 4 == 2, F.lit(False))


def train(docs: DataFrame, per_language: int = PER_LANGUAGE) -> Centroids:
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang"))
    rows = rows.where("doc_id is not null and text is not null and lang is not null").where(~held_out(F.col("doc_id")))
    sizes = {r.lang: r.n for r in rows.groupBy("lang").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "lang").limit(MOST_LANGUAGES).collect()}
    if not sizes:
        return fit([])
    per_language = max(1, min(per_language, MOST_ROWS // len(sizes)))
    share = F.lit(0.0)
    for lang, n in sizes.items():
        share = F.when(F.col("lang") == lang, min(1.0, per_language / n)).otherwise(share)
    dice = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) / float(1 << 30)
    drawn = rows.withColumn("dice", dice).where(F.col("dice") < share).select("dice", "doc_id", "lang", stretch(F.col("text"), MOST_CHARS).alias("text"))
    return fit([(r.text, r.lang) for r in drawn.orderBy("dice", "doc_id").limit(2 * per_language * len(sizes)).collect()])


def identify(docs: DataFrame, model: Centroids | None = None) -> DataFrame:
    """(doc_id, lang_pred, score, accepted) of every text; trains on `docs` unless a model is given."""
    model = model or train(docs)
    spark: SparkSession = docs.sparkSession
    ship(spark)
    small_batches(spark)
    shared = spark.sparkContext.broadcast(model)

    def make():
        def work(texts: list) -> dict:
            label, score, kept = shared.value.predict(texts)
            return {"lang_pred": label, "score": score, "accepted": kept}

        return work

    return map_texts(id_and_text(docs), make, "lang_pred string, score double, accepted boolean")


def digest(found: DataFrame) -> DataFrame:
    return found.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score", "accepted")


def accepted_documents(docs: DataFrame) -> DataFrame:
    """The rows of `docs` that are not rejected: filtered where they stand, without a join."""
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast(train(docs))
    ship(spark)
    small_batches(spark)
    import pyarrow as pa

    from .common import pieces

    place = docs.columns.index("text")

    def run(batches):
        for batch in batches:
            for part in pieces(batch):
                yield part.filter(pa.array(shared.value.predict(part.column(place).to_pylist())[2]))

    return docs.mapInArrow(run, docs.schema)
