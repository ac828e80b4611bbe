"""SimHash near-duplicates by pigeonhole blocks.

Fingerprints within `distance` differing bits of 64 agree on at least `blocks - distance` of
`blocks` blocks. Every choice of that many blocks is a table whose key are their bits, so every
close pair meets in some table. Equal fingerprints are folded first. Inside a bucket links are
verified by Hamming distance and reduced to a spanning forest at once: a bucket of m
fingerprints gives at most m - 1 rows, never all its pairs. Buckets above `most` members are
dealt out as pairs of parts, so none is one task.

For near copies by similarity (five words, 0.8 and more) three differing bits of 64 are far too
few: a fingerprint of several 64-bit words is taken there, and two texts are linked if they
differ in no more bits than texts of that similarity do on average. Blocks are stretches of
`key_bits` bits that start every eighth bit; `plan_wide` takes longer blocks for more texts, and
so many words that texts of similarity 0.85 share a block with the stated probability.

Defined results: a null or wordless text has fingerprint zero and links like any other; rows
with a null id get their fingerprint but link with nothing (component null); repeated rows
repeat their result; different texts under one id are told apart; extra columns are not read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import id_and_text, map_texts, settle, ship
from .components import connected_components

WORDS, DISTANCE, BLOCKS = 3, 3, 6
#: Shingles and similarity of the near copies that a filtering stage drops, and the share of those a little more alike that it finds.
NEAR_WORDS, SIMILARITY, RECALL = 5, 0.8, 0.95
#: Members of a bucket that one task compares.
MOST = 4000
#: Rows of a table small enough to broadcast.
FEW = 200_000
_STEP = 50_000
_GOLDEN = 0x9E3779B97F4A7C15


def _shingle_hashes(text: str | None, words: int) -> Iterator[np.ndarray]:
    """XXH64 (seed 42) of the text's word shingles, a bounded number at a time."""
    # bytes.lower() changes A-Z alone and bytes.split() cuts at [\x20\x09-\x0D] alone
    parts = text.encode("utf-8", "surrogatepass").lower().split() if text else []
    if not parts:
        return
    hashed = xxhash.xxh64_intdigest
    ends = np.cumsum([0, *map(len, parts)]) + np.arange(len(parts) + 1)
    whole, width = b" ".join(parts), min(words, len(parts))
    starts, stops = ends[: len(parts) - width + 1].tolist(), (ends[width:] - 1).tolist()
    for at in range(0, len(starts), _STEP):
        yield np.array([hashed(whole[a:b], 42) for a, b in zip(starts[at : at + _STEP], stops[at : at + _STEP])], dtype="<u8")


def _majority(hashes: Iterator[np.ndarray], width: int) -> np.ndarray:
    """The bits set in over half of all rows of `width` 64-bit words."""
    ones, n = np.zeros(64 * width, dtype=np.int64), 0
    for h in hashes:
        ones += np.unpackbits(h.view(np.uint8).reshape(-1, 8 * width), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
        n += len(h) // width
    return np.packbits(ones * 2 > n, bitorder="little").view("<u8")


def fingerprint(text: str | None, words: int = WORDS) -> int:
    """64 majority bits over the hashes of the text's word shingles."""
    return int(_majority(_shingle_hashes(text, words), 1)[0])


def wide_fingerprint(text: str | None, words: int, width: int) -> np.ndarray:
    """Majority bits of `width` 64-bit words, each mixed anew from the shingles' hashes."""

    def mixed():
        for h in _shingle_hashes(text, words):
            x = h[:, None] + np.arange(1, width + 1, dtype=np.uint64) * np.uint64(_GOLDEN)
            x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
            x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
            yield np.ascontiguousarray(x ^ (x >> np.uint64(31))).ravel()

    return _majority(mixed(), width)


def fingerprints(docs: DataFrame, words: int = WORDS, width: int = 0) -> DataFrame:
    """(doc_id, sign, b0, b1, ...) of every text; `width` 0 gives the one word of `fingerprint`, sign tells texts apart."""
    names = [f"b{k}" for k in range(max(1, width))]

    def make():
        def work(texts: list) -> dict:
            found = [wide_fingerprint(t, words, width) if width else [fingerprint(t, words)] for t in texts]
            bits = np.array(found, dtype="<u8").reshape(len(texts), -1).view("<i8")
            signs = [None if t is None else xxhash.xxh64_intdigest(t.encode("utf-8", "surrogatepass"), 42) for t in texts]
            signs = [None if x is None else x - (1 << 64) if x >> 63 else x for x in signs]
            return {"sign": pa.array(signs, pa.int64()), **{n: np.ascontiguousarray(bits[:, k]) for k, n in enumerate(names)}}

        return work

    return map_texts(id_and_text(docs), make, "sign long, " + ", ".join(f"{n} long" for n in names))


def block_masks(distance: int, blocks: int) -> list[int]:
    """One mask for every choice of `blocks - distance` of the blocks of 64 bits."""
    cuts = [64 * k // blocks for k in range(blocks + 1)]
    own = [((1 << cuts[k + 1]) - 1) ^ ((1 << cuts[k]) - 1) for k in range(blocks)]
    return [sum(own[k] for k in some) for some in combinations(range(blocks), blocks - distance)]


def wide_distance(similarity: float, width: int) -> int:
    """Differing bits that texts of this shingle similarity have on average."""
    return math.floor(64 * width * math.acos(2 * similarity / (1 + similarity)) / math.pi)


def plan_wide(n: int, similarity: float = SIMILARITY, recall: float = RECALL) -> tuple[int, int]:
    """(key_bits, words of 64 bits) for n texts: blocks of few texts if they were spread evenly, and the wished recall."""
    key_bits = min(24, max(16, math.ceil(math.log2(max(2, n))) - 6))
    alike = similarity + (1 - similarity) / 4
    agree = (1 - math.acos(2 * alike / (1 + alike)) / math.pi) ** key_bits
    # neighbouring blocks overlap and are worth some three quarters of a block of their own
    return key_bits, max(2, math.ceil(math.log(1 - recall) / math.log(1 - agree) / 0.75 / 8))


def forest(bits: np.ndarray, distance: int) -> tuple[np.ndarray, np.ndarray]:
    """Positions (from, to) of links that connect what is connected at `distance` within one bucket; a row of `bits` is a fingerprint."""
    left, parents, children = np.arange(len(bits)), [], []
    while len(left) > 1:
        queue, left = [left[0]], left[1:]
        while queue and len(left):
            at = queue.pop()
            near = np.bitwise_count(bits[left] ^ bits[at]).sum(axis=1) <= distance
            if near.any():
                found = left[near]
                left = left[~near]
                parents.append(np.full(len(found), at))
                children.append(found)
                queue.extend(found.tolist())
    none = np.zeros(0, dtype=np.int64)
    return (np.concatenate(parents), np.concatenate(children)) if parents else (none, none)


def _bucket_links(batches: Iterator[pa.RecordBatch], distance: int) -> Iterator[pa.RecordBatch]:
    """Rows (t, key, pair, node, bits) sorted by (t, key, pair); a bucket may run over several batches, but is of bounded size."""
    held: list[tuple[np.ndarray, np.ndarray]] = []

    def links(keys: np.ndarray, bits: np.ndarray) -> pa.RecordBatch:
        node = keys[:, 3]
        new = np.flatnonzero((keys[1:, :3] != keys[:-1, :3]).any(axis=1)) + 1
        starts, ends = np.concatenate([[0], new]), np.concatenate([new, [len(keys)]])
        pairs = starts[ends - starts == 2]
        near = pairs[np.bitwise_count(bits[pairs] ^ bits[pairs + 1]).sum(axis=1) <= distance]
        a, b = [node[near]], [node[near + 1]]
        for k in np.flatnonzero(ends - starts > 2):
            own = slice(starts[k], ends[k])
            x, y = forest(bits[own], distance)
            a.append(node[own][x])
            b.append(node[own][y])
        return pa.RecordBatch.from_arrays([pa.array(np.concatenate(a)), pa.array(np.concatenate(b))], ["a", "b"])

    for batch in batches:
        if not batch.num_rows:
            continue
        columns = [np.asarray(c) for c in batch.columns]
        keys, bits = np.stack(columns[:4], axis=1).astype(np.int64), np.stack(columns[4:], axis=1).astype("<i8").view("<u8")
        # hold back the last bucket: it may go on in the next batch
        other = np.flatnonzero((keys[:, :3] != keys[-1, :3]).any(axis=1))
        cut = int(other[-1]) + 1 if len(other) else 0
        if cut:
            yield links(np.concatenate([*(k for k, _ in held), keys[:cut]]), np.concatenate([*(x for _, x in held), bits[:cut]]))
            held = []
        held.append((keys[cut:], bits[cut:]))
    if held:
        yield links(np.concatenate([k for k, _ in held]), np.concatenate([x for _, x in held]))


def _links(keyed: DataFrame, names: list[str], distance: int, most: int) -> DataFrame:
    """Links (a, b) inside the buckets of rows (t, key, node, bits); those of large buckets by pairs of parts."""
    ship(keyed.sparkSession)
    large = settle(keyed.groupBy("t", "key").agg(F.count("*").alias("n")).where(F.col("n") > most).select("t", "key", F.ceil(F.col("n") / F.lit(most)).cast("int").alias("parts")))
    few = large.count()
    if few:
        # broadcast only if there are few of them; else the rows are moved once more
        met = keyed.join(F.broadcast(large) if few <= FEW else large, ["t", "key"], "left").withColumn("own", F.pmod(F.xxhash64("node"), F.col("parts")).cast("int"))
        pairs = F.when(F.col("parts").isNull(), F.array(F.lit(0))).otherwise(F.transform(F.sequence(F.lit(0), F.col("parts") - 1), lambda k: (F.least(k, F.col("own")) * F.col("parts") + F.greatest(k, F.col("own"))).cast("int")))
    else:
        met, pairs = keyed, F.array(F.lit(0))
    dealt = met.select("t", "key", F.explode(pairs).alias("pair"), "node", *names)
    return dealt.repartition("t", "key", "pair").sortWithinPartitions("t", "key", "pair").mapInArrow(lambda it: _bucket_links(it, distance), "a long, b long")


def near_links(nodes: DataFrame, distance: int = DISTANCE, blocks: int = BLOCKS, most: int = MOST) -> DataFrame:
    """Links (a, b) that connect all `nodes` (node, b0; b0 distinct) within `distance`."""
    masks = F.array(*[F.lit(m - (1 << 64) if m >> 63 else m) for m in block_masks(distance, blocks)])
    tables = nodes.select("b0", "node", F.posexplode(masks).alias("t", "mask"))
    return _links(tables.select("t", F.col("b0").bitwiseAND(F.col("mask")).alias("key"), "node", "b0"), ["b0"], distance, most)


def wide_links(nodes: DataFrame, width: int, key_bits: int, distance: int, most: int = MOST) -> DataFrame:
    """Links (a, b) of `nodes` (node, b0, b1, ...) that share a block and are within `distance`."""
    names = [f"b{k}" for k in range(width)]
    mask = (1 << key_bits) - 1

    def stretch(word: Column, at: int) -> Column:  # from bit `at` on, round the end of the word
        turned = word if at == 0 else F.shiftrightunsigned(word, at).bitwiseOR(F.shiftleft(word, 64 - at))
        return turned.bitwiseAND(F.lit(mask))

    keys = F.array(*[stretch(F.col(n), at) for n in names for at in range(0, 64, 8)])
    tables = nodes.select("node", *names, F.posexplode(keys).alias("t", "key"))
    return _links(tables.select("t", "key", "node", *names), names, distance, most)


def _with_components(marked: DataFrame, links, names: list[str]) -> DataFrame:
    """`marked` (doc_id, ..., b0, b1, ...) with component_id; `links` gives the links of the distinct fingerprints."""
    nodes = settle(marked.where("doc_id is not null").groupBy(*names).agg(F.min("doc_id").alias("doc_id")).withColumn("node", F.monotonically_increasing_id()))
    found = settle(links(nodes))
    groups = connected_components(found)
    named = nodes.join(groups, "node", "left").withColumn("component", F.coalesce("component", "node"))
    least = named.groupBy("component").agg(F.min("doc_id").alias("component_id"))
    classes = named.join(least, "component").select(*names, "component_id")
    joined = marked.join(classes, names, "left")
    return joined.withColumn("component_id", F.when(F.col("doc_id").isNotNull(), F.col("component_id")))


def group_near_copies(docs: DataFrame, words: int = WORDS, distance: int = DISTANCE, blocks: int = BLOCKS, most: int = MOST) -> DataFrame:
    """(doc_id, sign, bits, component_id): component_id is the smallest doc_id reachable over links."""
    marked = settle(fingerprints(docs, words))
    return _with_components(marked, lambda nodes: near_links(nodes, distance, blocks, most), ["b0"]).select("doc_id", "sign", F.col("b0").alias("bits"), "component_id")


def group_similar(docs: DataFrame, words: int = NEAR_WORDS, similarity: float = SIMILARITY, recall: float = RECALL, most: int = MOST) -> DataFrame:
    """(doc_id, sign, component_id) over texts whose shingles are `similarity` alike or more, as wide fingerprints tell."""
    key_bits, width = plan_wide(docs.count(), similarity, recall)
    marked = settle(fingerprints(docs, words, width))
    names = [f"b{k}" for k in range(width)]
    return _with_components(marked, lambda nodes: wide_links(nodes, width, key_bits, wide_distance(similarity, width), most), names).select("doc_id", "sign", "component_id")


def digest(grouped: DataFrame) -> DataFrame:
    return grouped.select("doc_id", F.lower(F.lpad(F.hex("bits"), 16, "0")).alias("fingerprint"), "component_id")


def keep_one_of_each_group(docs: DataFrame, grouped: DataFrame | None = None) -> DataFrame:
    """The rows of `docs` without those whose doc_id is not its group's smallest; null ids stay.

    Groups are those of `group_similar` unless given (doc_id, sign, component_id).
    """
    grouped = group_similar(docs) if grouped is None else grouped
    gone = grouped.where("doc_id <> component_id").select(F.col("doc_id").alias("__id"), F.coalesce("sign", F.lit(0)).alias("__sign")).distinct()
    sign = F.when(F.col("text").isNull(), 0).otherwise(F.xxhash64(F.col("text").cast("string")))
    return docs.join(gone, (F.col("doc_id").cast("long") == F.col("__id")) & (sign == F.col("__sign")), "left_anti")
