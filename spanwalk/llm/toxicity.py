"""Toxicity by compression distance.

Two zstandard dictionaries are trained. The ordinary one comes from windows of ordinary texts.
The other comes from toxic texts, of which only the stretches that ordinary ones lack are shown
to it, and is used behind the ordinary one, so that both know ordinary text alike. A text is
cut into overlapping windows, each is compressed under either dictionary, and the bytes that the
toxic one saves are the window's evidence. A logistic curve over a few statistics of all windows
(strongest, second, next, how many stand out, weakest, number of windows) is the calibrated
threshold. It is fitted out of fold: the training texts are dealt into FOLDS by hash, each fold is
compressed under dictionaries trained on the others, and on this evidence the curve and its
middle are chosen; the dictionaries in use are then trained on all of them.

Training rows are a bounded hashed sample of labelled texts (`per_label` rows of MOST_CHARS
characters, of a longer text a stretch at a hashed place); scoring covers every whole text.

Defined results: null, empty and white-space texts count as one window without evidence;
without labelled rows of both kinds every score is 0; repeated rows repeat; extra columns are
not read.
"""

from __future__ import annotations

import math
import zlib
from collections import Counter
from dataclasses import dataclass, field

import numpy as np
import zstandard as zstd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import id_and_text, map_texts, ship, stretch

WINDOW, STRIDE = 96, 64
#: Folds of the training texts, and how many missed toxic texts an ordinary one marked is worth (as shares of each kind).
FOLDS, CAUTION = 3, 20
#: Characters of one training text.
MOST_CHARS = 20_000
PER_LABEL, DICTIONARY_BYTES, TOXIC_BYTES = 1500, 12_000, 1000
#: Windows that train the ordinary dictionary at most.
MOST_WINDOWS = 20_000
#: Stretches of GRAM bytes train the toxic dictionary if this share of the toxic texts hold them, and so many times the share of ordinary ones.
GRAM, WITNESSES, ODDS = 4, 0.018, 10


def folded(text: str | None) -> bytes:
    return " ".join((text or "").lower().split()).encode("utf-8", "surrogatepass")


def windows(text: str | None) -> list[bytes]:
    """Overlapping stretches of the lower-cased text, cut at no particular place."""
    raw = folded(text)
    return [raw[a : a + WINDOW] for a in range(0, max(1, len(raw) - WINDOW + STRIDE), STRIDE)] if raw else []


def _parameters() -> zstd.ZstdCompressionParameters:
    return zstd.ZstdCompressionParameters(window_log=15, chain_log=15, hash_log=15, search_log=6, min_match=5, target_length=64, strategy=zstd.STRATEGY_GREEDY, write_content_size=0, write_checksum=0, write_dict_id=0)


@dataclass
class Scorer:
    toxic: bytes = b""
    plain: bytes = b""
    curve: tuple[np.ndarray, np.ndarray, np.ndarray] | None = None  # centre, scale, weights
    _pair: tuple | None = field(default=None, repr=False, compare=False)

    def __getstate__(self):
        return {**self.__dict__, "_pair": None}

    def pair(self):
        if self._pair is None:
            own = [zstd.ZstdCompressionDict(d, dict_type=zstd.DICT_TYPE_RAWCONTENT) for d in (self.toxic, self.plain)]
            self._pair = tuple(zstd.ZstdCompressor(dict_data=d, compression_params=_parameters()).compress for d in own)
        return self._pair

    def evidence(self, text: str | None) -> list[float]:
        toxic, plain = self.pair()
        saved = sorted([len(plain(w)) - len(toxic(w)) for w in windows(text)] or [0], reverse=True)
        return [
            saved[0], saved[1] if len(saved) > 1 else 0, sum(saved[1:4]),
            sum(x - 2 for x in saved if x > 2), sum(x > 3 for x in saved), saved[-1], math.log(len(saved)),
        ]

    def scores(self, texts: list[str | None]) -> np.ndarray:
        if self.curve is None or not texts:
            return np.zeros(len(texts))
        centre, scale, weights = self.curve
        z = (np.array([self.evidence(t) for t in texts], dtype=np.float64) - centre) / scale @ weights[:-1] + weights[-1]
        return 1 / (1 + np.exp(-np.clip(z, -60, 60)))


def _dictionary(samples: list[bytes], size: int = DICTIONARY_BYTES, **how) -> bytes:
    """A trained dictionary; where zstandard refuses (too few samples), their plain content."""
    try:
        return zstd.train_dictionary(size, samples, level=3, **how).as_bytes()
    except zstd.ZstdError:
        return b"".join(samples)[-size:] or b" "


def _without_copies(texts: list[str]) -> list[str]:
    """One of the texts that begin or end alike, so that copies don't pass for many witnesses."""
    seen, out = set(), []
    for t in texts:
        ends = {("head", t[:60]), ("tail", t[-60:]), ("middle", t[len(t) // 2 : len(t) // 2 + 40])}
        if not ends & seen:
            out.append(t)
        seen |= ends
    return out


def _spread(samples: list[bytes]) -> list[bytes]:
    """At most `MOST_WINDOWS` of the samples, taken and ordered by hash from all of them alike."""
    return sorted(samples, key=lambda w: (zlib.crc32(w), w))[:MOST_WINDOWS]


def _grams(texts: list[bytes]) -> Counter:
    """Texts that hold each stretch of `GRAM` bytes."""
    out: Counter = Counter()
    for t in texts:
        out.update({t[k : k + GRAM] for k in range(len(t) - GRAM + 1)})
    return out


def _left_over(toxic: list[str], plain: list[str]) -> list[bytes]:
    """Of every toxic text the stretches whose bytes toxic texts hold far oftener than ordinary ones.

    Nothing depends on where words begin or end: a stretch may be a short word, part of one or
    some words in a row.
    """
    toxic, plain = [folded(t) for t in _without_copies(toxic)], [folded(t) for t in _without_copies(plain)]
    seen, ordinary = _grams(toxic), _grams(plain)
    odd = {g for g, n in seen.items() if n >= max(3, WITNESSES * len(toxic)) and n / len(toxic) > ODDS * (ordinary.get(g, 0) + 0.5) / len(plain)}
    out = []
    for t in toxic:
        stretches, end = [], -1
        for k in range(len(t) - GRAM + 1):
            if t[k : k + GRAM] in odd:
                if k > end:
                    stretches.append([k, k])
                end = stretches[-1][1] = k + GRAM
        if stretches:
            out.append(b" ".join(t[a:b] for a, b in stretches))
    return out


def _dictionaries(toxic: list[str], plain: list[str]) -> Scorer:
    toxic, plain = sorted(toxic), sorted(plain)
    ordinary = _dictionary(_spread([w for t in plain for w in windows(t)]))
    left = _left_over(toxic, plain)
    own_part = _dictionary(left, TOXIC_BYTES, k=16, d=6) if left else b""
    # both begin with the ordinary dictionary; the toxic one goes on with its own, the other with as many idle bytes
    idle = bytes((k * 97 + k // 61 * 31) % 29 + 1 for k in range(len(own_part)))
    return Scorer(toxic=ordinary + own_part, plain=ordinary + idle)


def fit(toxic: list[str], plain: list[str], folds: int = FOLDS) -> Scorer:
    if not toxic or not plain:
        return Scorer()
    fold = lambda t: zlib.crc32(t.encode("utf-8", "surrogatepass")) % folds
    texts, y = [*toxic, *plain], np.array([1] * len(toxic) + [0] * len(plain))
    own = np.array([fold(t) for t in texts])
    evidence = np.zeros((len(texts), len(Scorer(b" ", b" ").evidence(""))))
    for k in range(folds):
        rest = [[t for t, x, f in zip(texts, y, own) if x == kind and f != k] for kind in (1, 0)]
        scorer = _dictionaries(*rest) if all(rest) else _dictionaries(toxic, plain)
        for i in np.flatnonzero(own == k):
            evidence[i] = scorer.evidence(texts[i])
    out = _dictionaries(toxic, plain)
    centre, scale, weights = _logistic(evidence, y)
    out.curve = centre, scale, _middle((evidence - centre) / scale @ weights[:-1], y, weights)
    return out


def _middle(z: np.ndarray, y: np.ndarray, weights: np.ndarray) -> np.ndarray:
    """The weights with the intercept that misses fewest toxic texts and, CAUTION times as dear, marks fewest ordinary ones."""
    order = np.argsort(z, kind="stable")
    z, y = z[order], y[order]
    missed, marked = np.cumsum(y) / max(1, y.sum()), 1 - np.cumsum(1 - y) / max(1, (1 - y).sum())
    cost = missed + CAUTION * marked  # of a cut just above each text
    cost = np.where(np.append(z[1:] > z[:-1], True), cost, np.inf)
    best = np.flatnonzero(cost <= cost.min() + 1e-12)
    k = int(best[len(best) // 2])
    cut = (z[k] + z[k + 1]) / 2 if k + 1 < len(z) else z[k]
    return np.append(weights[:-1], -cut)


def _logistic(x: np.ndarray, y: np.ndarray, ridge: float = 0.01, steps: int = 50) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ridge logistic regression by Newton's method, both classes of equal weight."""
    centre, scale = x.mean(axis=0), x.std(axis=0) + 1e-9
    z = np.c_[(x - centre) / scale, np.ones(len(x))]
    w, balance = np.zeros(z.shape[1]), np.where(y == 1, 0.5 / max(y.mean(), 1e-9), 0.5 / max(1 - y.mean(), 1e-9))
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -60, 60)))
        slope = z.T @ (balance * (p - y)) / len(y) + ridge * np.r_[w[:-1], 0]
        bend = (z * (balance * p * (1 - p))[:, None]).T @ z / len(y) + ridge * np.eye(len(w))
        w -= np.linalg.solve(bend, slope)
    return centre, scale, w


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string")) % 5 == 0, F.lit(False))


def train(docs: DataFrame, labels: DataFrame, per_label: int = PER_LABEL) -> Scorer:
    marks = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("toxic")).where("doc_id is not null and toxic in (0, 1)").where(~held_out(F.col("doc_id")))
    sizes = {r.toxic: r.n for r in marks.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    share = F.when(F.col("toxic") == 1, min(1.0, per_label / max(1, sizes.get(1, 0)))).otherwise(min(1.0, per_label / max(1, sizes.get(0, 0))))
    dice = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) / float(1 << 30)
    chosen = marks.withColumn("dice", dice).where(F.col("dice") < share).orderBy("dice", "doc_id", "toxic").limit(4 * per_label)  # bounded, so that it may be broadcast
    rows = id_and_text(docs).where("text is not null").join(F.broadcast(chosen), "doc_id").select("dice", "doc_id", "toxic", stretch(F.col("text"), MOST_CHARS).alias("text"))
    rows = rows.orderBy("dice", "doc_id", "toxic", "text").limit(4 * per_label).collect()  # an id may have many rows
    return fit([r.text for r in rows if r.toxic == 1], [r.text for r in rows if r.toxic == 0])


def score_documents(docs: DataFrame, labels: DataFrame, model: Scorer | None = None) -> DataFrame:
    """(doc_id, score) of every text."""
    model = model or train(docs, labels)
    ship(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def make():
        scorer = shared.value
        return lambda texts: {"score": scorer.scores(texts)}

    return map_texts(id_and_text(docs), make, "score double")


def digest(scored: DataFrame) -> DataFrame:
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", F.when(F.col("score") >= 0.5, 1).otherwise(0).alias("predicted"))
