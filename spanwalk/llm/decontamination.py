"""Benchmark decontamination by the q-gram lemma.

Texts and benchmark items are lower-cased with white space folded. Any SEGMENT characters of an
item are a passage (a shorter item is one passage as a whole). A passage of m characters found
with at most e edits shares at least m - q + 1 - q * e of its q-grams with the text, all on
diagonals of a band e + 1 wide. Shared q-grams are sorted by item, band and place in the item
(bands overlap by half), so one comparison of every place with the one `need` places further on
finds all stretches of an item, wherever they start, that meet the bound. A passage that stands
there letter by letter is read off the diagonals; the rest is decided by a banded alignment of
passages that start FINE characters apart inside such a stretch, so that an edited passage is
found if one of those starts is within the edits. Places already covered by a passage found are
not aligned again.

Texts are worked on in runs of bounded length, several short texts or a part of a long one at a
time, and the shared q-grams of a run are laid out in portions of bounded number, so memory
doesn't grow with a text or with how often it repeats itself.

Long items are cut into overlapping parts of PART characters. The index of a block of parts is
broadcast, its characters being bounded; where a benchmark needs several blocks, one pass over
the texts keeps those that hold enough grams of any block (a bit table of fixed size), and only
these are searched block by block.

Defined results: null and empty texts leak nothing; null or blank items are not searched; items
of fewer than `least` characters count only as a whole line of a text; rows with a null id are
reported with a null id; repeated rows repeat their leaks once each; several passages of one item
in one text make one row (first start, last end, number of passages found, fewest edits); extra
columns are not read.
"""

from __future__ import annotations

import math
import re
from bisect import bisect_left, insort
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import id_and_text, pieces, ship, small_batches, store

Q, RATE, SEGMENT, LEAST = 8, 0.08, 100, 24
#: Distance of the starts that are aligned inside a stretch that meets the bound.
FINE = 8
#: Characters of an item that one part of it holds, and of all parts in one broadcast index (about 30 bytes each).
PART, BLOCK_CHARS = 4000, 4_000_000
#: Characters of an item that reach the driver as one row.
PIECE = 60_000
#: Characters of texts worked on at once, and shared q-grams laid out at once.
RUN_CHARS, PORTION = 400_000, 400_000
_MULT = 0x9E3779B97F4A7C15
_TABLE_BITS = 22
_NO_LETTER = 0xFFFFFFFF

Hit = tuple[int, int, int, int]


def fold(text: str) -> str:
    low = text.lower()
    if len(low) != len(text):  # a few letters grow when lowered; those stay
        low = "".join([c.lower() if len(c.lower()) == 1 else c for c in text])
    return " ".join(low.split())


def _letters(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), dtype="<u4")


def gram_hashes(letters: np.ndarray, q: int) -> np.ndarray:
    """A hash for each q letters in a row, put together from hashes of shorter rows."""
    n = len(letters) - q + 1
    if n <= 0:
        return np.zeros(0, dtype=np.uint64)
    row, width, out, done = letters.astype(np.uint64), 1, None, 0
    while True:
        if q & width:
            out = row[:n].copy() if out is None else out * np.uint64(pow(_MULT, width, 1 << 64)) + row[done : done + n]
            done += width
        if done == q:
            return out ^ (out >> np.uint64(31))
        row, width = row[:-width] * np.uint64(pow(_MULT, width, 1 << 64)) + row[width:], width * 2


class PassageIndex:
    """Postings of the q-grams of a block of benchmark items, in parts of bounded length."""

    def __init__(self, items: list[tuple[int, str]], q: int = Q, rate: float = RATE, segment: int = SEGMENT, least: int = LEAST, part: int = PART):
        part = min(part, 1 << 14)
        self.q, self.names, self.parts = q, [], []
        self.lines: dict[str, list[int]] = {}
        for item, text in items:
            whole = fold(text or "")
            if len(whole) < max(least, q):
                if whole:
                    self.lines.setdefault(whole, []).append(item)
                continue
            for at in range(0, max(1, len(whole) - segment), part - segment):
                self.names.append(item)
                self.parts.append(whole[at : at + part])
        self.sizes = np.array([len(t) for t in self.parts], dtype=np.int64)
        self.lengths = np.minimum(self.sizes, segment)
        # the most edits for which the lemma still asks for a shared q-gram
        self.edits = np.minimum(np.floor(self.lengths * rate), np.maximum(0, (self.lengths - q) // q)).astype(np.int64)
        self.need = self.lengths - q + 1 - q * self.edits
        places, hashes = [np.zeros(0, np.int32)], [np.zeros(0, np.uint64)]
        seen: dict[int, np.ndarray] = {}
        for name, text, length in zip(self.names, self.parts, self.lengths.tolist()):
            letters = _letters(text)
            places.append(np.flatnonzero(self._first_passages(letters, length, name, seen)).astype(np.int32))
            hashes.append(gram_hashes(letters, q)[places[-1]])
        h, pos = np.concatenate(hashes), np.concatenate(places)
        part_of = np.repeat(np.arange(len(self.parts), dtype=np.int32), [len(x) for x in places[1:]])
        order = np.argsort(h, kind="stable")
        self.part_of, self.pos = part_of[order], pos[order]
        self.grams, first = np.unique(h[order], return_index=True)
        self.first = np.append(first, len(h)).astype(np.int64)
        self.table = np.zeros(1 << _TABLE_BITS, dtype=bool)
        self.table[self.grams >> np.uint64(64 - _TABLE_BITS)] = True
        self.fewest = int(self.need.min()) if len(self.need) else 0
        self.reach = int((self.lengths + 2 * self.edits).max()) if len(self.lengths) else 0
        self.widest = int(self.edits.max()) + 1 if len(self.edits) else 1
        self.margin = part + 4 * self.widest

    def _first_passages(self, letters: np.ndarray, length: int, name: int, seen: dict[int, np.ndarray]) -> np.ndarray:
        """Which grams belong to a passage that its item doesn't hold before; a periodic item has few."""
        whole, at = np.unique(gram_hashes(letters, length), return_index=True)
        if name in seen:
            at = at[~np.isin(whole, seen[name])]
            whole = np.concatenate([whole, seen[name]])
        seen[name] = whole
        cover = np.zeros(len(letters) + 1, dtype=np.int32)
        cover[at] += 1
        np.add.at(cover, at + length - self.q + 1, -1)
        return np.cumsum(cover)[: len(letters) - self.q + 1] > 0

    # ---- texts in runs

    def search(self, texts: list[str]) -> list[set[Hit]]:
        """For each folded text the set of (item, start, end, edits) found in it."""
        out: list[set[Hit]] = [set() for _ in texts]
        if not len(self.grams):
            return out
        held, size, overlap = [], 0, self.reach + self.q
        for k, text in enumerate(texts):
            if len(text) < self.fewest + self.q - 1:
                continue
            for at in range(0, max(1, len(text) - overlap), RUN_CHARS):
                part = text[at : at + RUN_CHARS + overlap]
                held.append((k, at, part))
                size += len(part)
                if size >= RUN_CHARS:
                    self._run(held, out)
                    held, size = [], 0
        if held:
            self._run(held, out)
        return out

    def near_spots(self, h: np.ndarray, table: np.ndarray, shift: int) -> np.ndarray:
        """Places whose gram may be known and that have `fewest` such places within a passage's reach."""
        spots = np.flatnonzero(table[h >> np.uint64(shift)])
        k = self.fewest - 1
        if len(spots) <= k:
            return spots[:0]
        close = np.flatnonzero(spots[k:] - spots[: len(spots) - k] <= self.reach)
        opened = np.zeros(len(spots) + 1, dtype=np.int32)
        opened[close] += 1
        opened[close + k + 1] -= 1
        return spots[np.cumsum(opened[:-1]) > 0]

    def _run(self, held: list[tuple[int, int, str]], out: list[set[Hit]]) -> None:
        letters = _letters("\0".join([p for _, _, p in held])).copy()
        begins = np.cumsum([0] + [len(p) + 1 for _, _, p in held])
        letters[begins[1:-1] - 1] = _NO_LETTER
        h = gram_hashes(letters, self.q)
        spots = self.near_spots(h, self.table, 64 - _TABLE_BITS)
        if not len(spots):
            return
        at = np.searchsorted(self.grams, h[spots])
        known = (at < len(self.grams)) & (self.grams[np.minimum(at, len(self.grams) - 1)] == h[spots])
        spots, at = spots[known], at[known]
        # portions begin anew where the next spot is out of reach; a longer one is cut with an overlap
        n = self.first[at + 1] - self.first[at]
        for a, b in self._portions(spots, n):
            for low, high in self._part_ranges(at[a:b], int(n[a:b].sum())):
                self._portion(spots[a:b], at[a:b], low, high, begins, held, out)

    def _portions(self, spots: np.ndarray, n: np.ndarray) -> Iterator[tuple[int, int]]:
        total, a = np.concatenate([[0], np.cumsum(n)]), 0
        while a < len(spots):
            b = max(a + 1, int(np.searchsorted(total, total[a] + PORTION, side="right")) - 1)
            # at least one reach more than the overlap, or the next portion wouldn't get on
            b = max(b, int(np.searchsorted(spots, spots[a] + 2 * self.reach, side="right")))
            yield a, min(b, len(spots))
            if b >= len(spots):
                return
            a = int(np.searchsorted(spots, spots[b] - self.reach))

    def _part_ranges(self, at: np.ndarray, total: int) -> Iterator[tuple[int, int]]:
        """Ranges of parts whose postings of the portion are bounded (one part's always are)."""
        n = len(self.parts)
        if total <= 4 * PORTION:
            yield 0, n
            return
        counts = np.zeros(n, dtype=np.int64)
        grams, times = np.unique(at, return_counts=True)
        for g, t in zip(grams.tolist(), times.tolist()):
            counts += np.bincount(self.part_of[self.first[g] : self.first[g + 1]], minlength=n) * t
        low, held = 0, 0
        for k in range(n):
            if held and held + counts[k] > 4 * PORTION:
                yield low, k
                low, held = k, 0
            held += int(counts[k])
        yield low, n

    # ---- counting in bands

    def _portion(self, spots: np.ndarray, at: np.ndarray, low: int, high: int, begins: np.ndarray, held: list, out: list[set[Hit]]) -> None:
        first, last = self.first[at], self.first[at + 1]
        if (low, high) != (0, len(self.parts)):  # postings of a gram are in order of parts
            first = np.array([a + np.searchsorted(self.part_of[a:b], low) for a, b in zip(first, last)], dtype=np.int64)
            last = np.array([a + np.searchsorted(self.part_of[a:b], high) for a, b in zip(self.first[at], last)], dtype=np.int64)
        n = last - first
        which = np.repeat(first - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(n.sum())
        part, pos = self.part_of[which].astype(np.int64), self.pos[which].astype(np.int64)
        diagonal = np.repeat(spots, n) - pos + self.margin  # positive, two bands and more
        # one coarse band for all parts first: most shared grams fall out here, without a sort by place
        seen, back, count = np.unique(part << 32 | diagonal // (2 * self.widest), return_inverse=True, return_counts=True)
        beside = np.zeros(len(seen), dtype=np.int64)
        next_to = seen[1:] == seen[:-1] + 1
        beside[:-1] += np.where(next_to, count[1:], 0)
        beside[1:] += np.where(next_to, count[:-1], 0)
        some = (count + beside >= self.need[seen >> 32])[back]
        if not some.any():
            return
        part, pos, diagonal = part[some], pos[some], diagonal[some]
        known: dict[int, list[int]] = {}  # by part: places of the run where a passage of it begins, sorted
        for p, place in zip(*self._exact(part, pos, diagonal)):
            known.setdefault(p, []).append(place)
            k = int(np.searchsorted(begins, place, side="right")) - 1
            shift = held[k][1] + place - int(begins[k])
            out[held[k][0]].add((self.names[p], shift, shift + int(self.lengths[p]), 0))
        self._edited(part, pos, diagonal, known, begins, held, out)

    def _exact(self, part: np.ndarray, pos: np.ndarray, diagonal: np.ndarray) -> tuple[list[int], list[int]]:
        """Parts, and places in the run, of passages all of whose grams stand on one diagonal.

        Of a longer stretch the first and the last passage and some between; where a text repeats
        itself, the first and the last for each half passage of it.
        """
        order = np.lexsort((pos, diagonal, part))
        p, s, d = part[order], pos[order], diagonal[order]
        new = np.flatnonzero(np.concatenate([[True], (p[1:] != p[:-1]) | (d[1:] != d[:-1]) | (s[1:] != s[:-1] + 1)]))
        spare = np.diff(np.append(new, len(p))) - (self.lengths[p[new]] - self.q + 1)
        new, spare = new[spare >= 0], spare[spare >= 0]
        length = self.lengths[p[new]]
        times = spare // length + 1
        run = np.repeat(np.arange(len(new)), times)
        step = np.arange(len(run)) - np.repeat(np.cumsum(times) - times, times)
        run, ahead = np.concatenate([run, np.arange(len(new))]), np.concatenate([step * length[run], spare])
        owner = p[new][run]
        place = (s + d)[new][run] + ahead - self.margin
        order = np.lexsort((place, owner))
        owner, place = owner[order], place[order]
        cell = place // (self.lengths[owner] // 2)
        edge = np.flatnonzero((owner[1:] != owner[:-1]) | (cell[1:] != cell[:-1]))
        keep = np.unique(np.concatenate([[0], edge, edge + 1, [len(owner) - 1]])) if len(owner) else order
        return owner[keep].tolist(), place[keep].tolist()

    def _edited(self, part: np.ndarray, pos: np.ndarray, diagonal: np.ndarray, known: dict[int, list[int]], begins: np.ndarray, held: list, out: list[set[Hit]]) -> None:
        """Aligned passages where the shared grams of two neighbouring bands meet the bound."""
        band = diagonal // (self.edits[part] + 1)
        # part, band, place as one number: places < 2^14, bands < 2^30
        key = np.unique(np.concatenate([(part << 44) | (band << 14) | pos, (part << 44) | ((band - 1) << 14) | pos]))
        group, s = key >> 14, key & ((1 << 14) - 1)
        p = group >> 30
        ahead = np.arange(len(key)) + self.need[p] - 1
        met = ahead < len(key)
        ahead = np.where(met, ahead, 0)
        met = np.flatnonzero(met & (group[ahead] == group) & (s[ahead] - s <= self.lengths[p] - self.q))
        if not len(met):
            return
        # a passage that holds these grams starts between `least` and `most`
        group, p = group[met], p[met]
        most = np.minimum(s[met], self.sizes[p] - self.lengths[p])
        least = np.minimum(np.maximum(0, s[ahead[met]] + self.q - self.lengths[p]), most)
        first = np.flatnonzero(np.concatenate([[True], (group[1:] != group[:-1]) | (least[1:] > most[:-1])]))
        cells = np.unique(np.stack([group, -(-least // FINE), most // FINE], axis=1), axis=0)
        times = np.maximum(0, cells[:, 2] - cells[:, 1] + 1)
        inner = np.repeat(cells[:, 1], times) + np.arange(times.sum()) - np.repeat(np.cumsum(times) - times, times)
        ends = np.append(first[1:], len(group)) - 1
        tries = np.unique(np.concatenate([(np.repeat(cells[:, 0], times) << 14) | (inner * FINE), (group[first] << 14) | least[first], (group[ends] << 14) | most[ends]]))
        owner, start = tries >> 44, tries & ((1 << 14) - 1)
        wide = self.edits[owner] + 1
        low = ((tries >> 14) & ((1 << 30) - 1)) * wide - self.margin + start  # place in the run on the lowest diagonal
        for k in np.lexsort((low, owner)).tolist():
            q, at, e, length = int(owner[k]), int(start[k]), int(wide[k]) - 1, int(self.lengths[owner[k]])
            here, done = int(low[k]) + e, known.setdefault(q, [])
            near = bisect_left(done, here - length // 2)
            if near < len(done) and done[near] <= here + length // 2:
                continue
            t = min(len(held), max(1, int(np.searchsorted(begins, here + length // 2, side="right")))) - 1
            base, (row, shift, own) = int(begins[t]), held[t]
            hit = _align(self.parts[q][at : at + length], own, int(low[k]) - base, int(low[k]) + 2 * e + 1 - base, e)
            if hit:
                insort(done, base + hit[0])
                out[row].add((self.names[q], shift + hit[0], shift + hit[1], hit[2]))


def _align(text: str, folded: str, low: int, high: int, e: int) -> Hit | None:
    """Best alignment of the whole passage along diagonals low..high, widened by e; within e edits or None."""
    low, high = low - e, high + e
    exact = folded.find(text, max(0, low), max(0, high) + len(text))
    if exact >= 0:
        return exact, exact + len(text), 0
    width = high - low + 1
    far = len(text) + width
    # column d of a row i stands for the text position i + low + d before which the row ends
    place = np.arange(width) + low
    row = np.where((place >= 0) & (place <= len(folded)), 0, far)
    start = place.copy()
    shift, steps = max(0, low), np.arange(width)
    # letters along the band, with a margin where the text has none
    letters = np.full(len(text) + width + 2, _NO_LETTER, dtype=np.uint32)
    own = _letters(folded[shift : max(0, high) + len(text) + 1])[: len(letters) - (shift - low)]
    letters[shift - low : shift - low + len(own)] = own
    for i, letter in enumerate(_letters(text).tolist(), 1):
        at = i + low + steps  # places after taking `i` letters of the passage
        differs = letters[i - 1 : i - 1 + width] != letter
        take = row + differs
        skip = np.append(row[1:] + 1, far)  # the passage's letter is missing in the text
        better = skip < take
        new, new_start = np.where(better, skip, take), np.where(better, np.append(start[1:], 0), start)
        if at[0] < 0 or at[-1] > len(folded):
            new = np.where((at >= 0) & (at <= len(folded)), new, far)
        # letters of the text that the passage lacks: a running minimum along the row
        slope = new - steps
        best = np.minimum.accumulate(slope)
        source = np.maximum.accumulate(np.where(slope == best, steps, 0))
        row, start = np.minimum(best + steps, far), new_start[source]
        if row.min() > e:
            return None
    k = int(row.argmin())
    return (int(start[k]), int(len(text) + low + k), int(row[k])) if row[k] <= e else None


def _back(text: str, spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Spans of the folded text as spans of the text itself."""
    ends, starts, total = [], [], 0
    for m in re.finditer(r"\S+", text):  # one entry a word, not a letter
        starts.append(m.start())
        ends.append(total)
        total += m.end() - m.start() + 1
    words = np.array(ends)

    def place(x: int) -> int:
        k = int(np.searchsorted(words, x, side="right")) - 1
        return starts[k] + x - ends[k]

    return [(place(a), place(max(b - 1, a)) + 1) for a, b in spans]


def leaks_in(texts: list[str | None], index: PassageIndex) -> list[list[tuple[int, int, int, int, int]]]:
    """For each text (item, start, end, passages, edits) in code points of the text itself, one for each item."""
    folded = [fold(t) if t else "" for t in texts]
    out = []
    for text, found in zip(texts, index.search(folded)):
        by_item: dict[int, list[tuple[int, int, int]]] = {}
        for item, a, b, e in found:
            by_item.setdefault(item, []).append((a, b, e))
        rows = {}
        spans = _back(text, [(min(h[0] for h in hits), max(h[1] for h in hits)) for hits in by_item.values()]) if by_item else []
        for (item, hits), span in zip(by_item.items(), spans):
            rows[item] = (item, *span, len(hits), min(h[2] for h in hits))
        if index.lines and text:
            for m in re.finditer(r"[^\n]+", text):
                for item in index.lines.get(fold(m.group()), ()) if m.end() - m.start() < 8 * LEAST else ():
                    a, b, n, _ = rows.get(item, (item, m.start(), m.end(), 0, 0))[1:]
                    rows[item] = (item, min(a, m.start()), max(b, m.end()), n + 1, 0)
        out.append([rows[k] for k in sorted(rows)])
    return out


def leaks_of(text: str | None, index: PassageIndex) -> list[tuple[int, int, int, int, int]]:
    return leaks_in([text], index)[0]


# ---- tables

def _pieces_of(benchmark: DataFrame) -> DataFrame:
    """(item_id, nth, text): items in overlapping pieces of bounded length."""
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.regexp_replace(F.col("text").cast("string"), r"(?U)\s+", " ").alias("text")).where("item_id is not null and text is not null")
    starts = F.sequence(F.lit(0), F.greatest(F.lit(0), F.char_length("text") - SEGMENT - 1), F.lit(PIECE - SEGMENT))
    if_line = F.when(F.char_length("text") <= PIECE, F.array(F.lit(0))).otherwise(starts)
    return items.select("item_id", "text", F.posexplode(if_line).alias("nth", "at")).select("item_id", "nth", F.expr(f"substring(text, at + 1, {PIECE})").alias("text"))


def indexes(benchmark: DataFrame, block_chars: int = BLOCK_CHARS, **how) -> tuple[int, Iterator[PassageIndex]]:
    """The number of blocks, and one index for each; the characters of a block are bounded."""
    parts = _pieces_of(benchmark)
    total = parts.agg(F.coalesce(F.sum(F.char_length("text")), F.lit(0)).alias("n")).head().n
    blocks = max(1, math.ceil(total / block_chars))

    def each() -> Iterator[PassageIndex]:
        for k in range(blocks):
            own = parts.where(F.pmod(F.xxhash64("item_id", "nth"), F.lit(blocks)) == k) if blocks > 1 else parts
            yield PassageIndex([(r.item_id, r.text) for r in sorted(own.collect())], **how)

    return blocks, each()


class Suspicion:
    """A bit table of the grams and short lines of all blocks: texts that can't hold anything fall out."""

    def __init__(self, indexes: Iterator[PassageIndex], total_chars: int):
        self.bits = min(30, max(22, math.ceil(math.log2(max(2, total_chars))) + 3))
        self.table = np.zeros(1 << (self.bits - 3), dtype=np.uint8)
        self.fewest, self.reach, self.lines, self.q = None, 0, False, Q
        for index in indexes:
            self._set(index.grams)
            self._set(np.array([xxhash.xxh64_intdigest(x.encode("utf-8", "surrogatepass")) for x in index.lines], dtype=np.uint64))
            self.lines = self.lines or bool(index.lines)
            if len(index.parts):
                self.fewest = index.fewest if self.fewest is None else min(self.fewest, index.fewest)
                self.reach, self.q = max(self.reach, index.reach), index.q

    def _set(self, h: np.ndarray) -> None:
        place = h >> np.uint64(64 - self.bits)
        np.bitwise_or.at(self.table, place >> np.uint64(3), np.uint8(1) << (place & np.uint64(7)).astype(np.uint8))

    def _has(self, h: np.ndarray) -> np.ndarray:
        place = h >> np.uint64(64 - self.bits)
        return (self.table[place >> np.uint64(3)] >> (place & np.uint64(7)).astype(np.uint8)) & 1 > 0

    def suspects(self, text: str | None) -> bool:
        folded = fold(text) if text else ""
        for at in range(0, len(folded) if self.fewest else 0, RUN_CHARS):
            h = gram_hashes(_letters(folded[at : at + RUN_CHARS + self.reach + self.q]), self.q)
            spots = np.flatnonzero(self._has(h))
            k = self.fewest - 1
            if len(spots) > k and (spots[k:] - spots[: len(spots) - k] <= self.reach).any():
                return True
        if not self.lines:
            return False
        short = [fold(line) for line in (text or "").split("\n") if len(line) < 8 * LEAST]
        return bool(short) and bool(self._has(np.array([xxhash.xxh64_intdigest(x.encode("utf-8", "surrogatepass")) for x in short], dtype=np.uint64)).any())


_LEAKS = "item_id long, start long, end long, passages long, edits long"


def _search(rows: DataFrame, index: PassageIndex, key: str) -> DataFrame:
    """(key, leaks) of rows (key, text)."""
    shared = rows.sparkSession.sparkContext.broadcast(index)

    def run(batches):
        for batch in batches:
            for part in pieces(batch):
                found = leaks_in(part.column("text").to_pylist(), shared.value)
                which = np.repeat(np.arange(len(found)), [len(f) for f in found])
                flat = [x for f in found for x in f]
                yield pa.RecordBatch.from_arrays([part.column(key).take(pa.array(which)), *(pa.array([x[k] for x in flat], pa.int64()) for k in range(5))], [key, "item_id", "start", "end", "passages", "edits"])

    return rows.mapInArrow(run, f"{key} long, {_LEAKS}")


def _suspects(rows: DataFrame, benchmark: DataFrame, block_chars: int, **how) -> DataFrame:
    """The rows (with column text) that may hold something of some block."""
    blocks, each = indexes(benchmark, block_chars, **how)
    shared = rows.sparkSession.sparkContext.broadcast(Suspicion(each, blocks * block_chars))
    place = rows.columns.index("text")

    def run(batches):
        for batch in batches:
            for part in pieces(batch):
                yield part.filter(pa.array([shared.value.suspects(t) for t in part.column(place).to_pylist()], pa.bool_()))

    return rows.mapInArrow(run, rows.schema)


def find_leaks(docs: DataFrame, benchmark: DataFrame, block_chars: int = BLOCK_CHARS, **how) -> DataFrame:
    """(doc_id, item_id, start, end, passages, edits): one row for each text and item that leaks into it."""
    ship(docs.sparkSession)
    small_batches(docs.sparkSession)
    rows = id_and_text(docs)
    blocks, each = indexes(benchmark, block_chars, **how)
    if blocks == 1:
        return _search(rows, next(each), "doc_id")
    few = store(_suspects(rows, benchmark, block_chars, **how).withColumn("row", F.monotonically_increasing_id()), "suspects")
    out = None
    for index in each:
        part = _search(few.select("row", "text"), index, "row")
        out = part if out is None else out.unionByName(part)
    whole = out.groupBy("row", "item_id").agg(F.min("start").alias("start"), F.max("end").alias("end"), F.sum("passages").alias("passages"), F.min("edits").alias("edits"))
    return whole.join(few.select("row", "doc_id"), "row").select("doc_id", "item_id", "start", "end", "passages", "edits")


def clean_documents(docs: DataFrame, benchmark: DataFrame, block_chars: int = BLOCK_CHARS, **how) -> DataFrame:
    """The rows of `docs` into which nothing leaks; filtered where they stand, without a join."""
    ship(docs.sparkSession)
    small_batches(docs.sparkSession)
    place = docs.columns.index("text")
    for index in indexes(benchmark, block_chars, **how)[1]:
        shared = docs.sparkSession.sparkContext.broadcast(index)

        def run(batches, shared=shared):
            for batch in batches:
                for part in pieces(batch):
                    yield part.filter(pa.array([not found for found in leaks_in(part.column(place).to_pylist(), shared.value)], pa.bool_()))

        docs = docs.mapInArrow(run, docs.schema)
    return docs
