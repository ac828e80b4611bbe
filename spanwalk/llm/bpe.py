"""BPE encoding and decoding by forced-boundary splitting.

A byte pair that stands inside no vocabulary token can never be merged over: whatever merges
happen left and right of it, no token will span it. Each such pair is a certain cut. A word is
cut there, its fragments are encoded independently (the last one with the end-of-word mark, the
others without), and their ids are concatenated. Chunks between white space are remembered in a
table of bounded size.

Defined results: null and empty texts give no ids and an empty decoded text; very long texts
are handled word by word; repeated rows give repeated results; an empty table gives an empty
result; columns other than id and text are not read.
"""

from __future__ import annotations

import json
import re
from functools import lru_cache
from itertools import chain
from operator import add

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import id_and_text, map_texts

#: White space as Unicode has it; Python's own split() also cuts at \x1c-\x1f.
_SPACE = re.compile("[\t-\r \x85\xa0  -     　]+")
_ODD = re.compile("[\x1c-\x1f]")
#: Words of letters that Python's `re` and the tokenizer's pattern class alike (Latin up to U+017F).
_PLAIN = re.compile("[!-~\xc0-\xd6\xd8-\xf6\xf8-įĲ-ſ]+")
_REMEMBER = 100_000


def _letter_table() -> dict[int, str]:
    """The printable stand-in of each byte, by the published byte-level rule."""
    keep = [*range(33, 127), *range(161, 173), *range(174, 256)]
    table, extra = {b: chr(b) for b in keep}, 0
    for b in range(256):
        if b not in table:
            table[b] = chr(256 + extra)
            extra += 1
    return table


class ForcedSplitEncoder:
    """Encodes like the tokenizer file at `path`, without special tokens being added."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer
        from tokenizers.models import BPE

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.library = Tokenizer.from_file(path)
        self.library.no_truncation()
        self.library.no_padding()
        model = spec["model"]
        vocab: dict[str, int] = model["vocab"]
        self.suffix: str = model["end_of_word_suffix"] or ""
        self.ending = self.library.model
        self.inner = BPE(vocab=vocab, merges=[tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in model["merges"]])
        self.added = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.specials = re.compile("(" + "|".join(map(re.escape, self.added)) + ")") if self.added else None
        self.letters = _letter_table()
        n = max([*vocab.values(), *self.added.values()]) + 1
        self.names = [""] * n
        for token, k in [*vocab.items(), *self.added.items()]:
            self.names[k] = token
        self.inside = self._pairs_inside_tokens(vocab)
        self.word_pattern = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[^\W\d_]+|\d|(?:[^\s\w]|_)+")
        self.fragments: dict[str, tuple[int, ...]] = {}
        self.chunks: dict[str, tuple[int, ...]] = {}
        self.older: dict[str, tuple[int, ...]] = {}  # the generation before, so that frequent chunks outlive a full table

    def _pairs_inside_tokens(self, vocab) -> set[str]:
        """Adjacent letters inside any token; all other pairs are certain cuts."""
        pairs = set()
        for token in vocab:
            body = token.removesuffix(self.suffix) if self.suffix and token != self.suffix else token
            pairs.update(map("".join, zip(body, body[1:])))
        return pairs

    def split(self, word: str) -> list[str]:
        """Fragments of a word of byte letters, cut at every pair that no token holds inside."""
        cuts = [i for i in range(1, len(word)) if word[i - 1 : i + 1] not in self.inside]
        return [word[a:b] for a, b in zip([0, *cuts], [*cuts, len(word)])]

    def _word(self, word: str) -> tuple[int, ...]:
        if self.inside.issuperset(map(add, word, word[1:])):
            return tuple([t.id for t in self.ending.tokenize(word)])
        *inner, last = self.split(word)
        out: list[int] = []
        for part in inner:
            ids = self.fragments.get(part)
            if ids is None:
                ids = tuple([t.id for t in self.inner.tokenize(part)])
                if len(self.fragments) >= _REMEMBER:
                    self.fragments.clear()
                if len(part) < 100:
                    self.fragments[part] = ids
            out.extend(ids)
        out.extend([t.id for t in self.ending.tokenize(last)])
        return tuple(out)

    def _chunk(self, chunk: str) -> tuple[int, ...]:
        """Ids of a stretch without white space."""
        if self.specials and "<|" in chunk and (parts := self.specials.split(chunk))[1:]:
            return tuple(chain.from_iterable((self.added[p],) if k % 2 else self._chunk(p) for k, p in enumerate(parts) if p))
        if chunk.isascii() and chunk.isprintable():
            words = self.word_pattern.findall(chunk.lower())
            return tuple(chain.from_iterable(map(self._word, words)))
        if _PLAIN.fullmatch(chunk):
            letters = self.letters
            words = self.word_pattern.findall(chunk.lower())
            return tuple(chain.from_iterable(self._word("".join([letters[b] for b in w.encode()])) for w in words))
        words = [w for w, _ in self.library.pre_tokenizer.pre_tokenize_str(self.library.normalizer.normalize_str(chunk))]
        return tuple(chain.from_iterable(map(self._word, words)))

    def encode(self, text: str | None) -> list[int]:
        if not text:
            return []
        known = self.chunks
        chunks = _SPACE.split(text) if _ODD.search(text) else text.split()
        out: list[int] = []
        for c in chunks:
            ids = known.get(c)
            if ids is None:
                ids = self.older.get(c)
                if ids is None:
                    ids = self._chunk(c) if c else ()
                if len(c) < 100:
                    if len(known) >= _REMEMBER:
                        self.older, self.chunks = known, {}
                        known = self.chunks
                    known[c] = ids
            out += ids
        return out

    def decode(self, ids) -> str:
        """Token names joined by a space: the file names no decoder, and the library then does that."""
        names = self.names
        return " ".join([names[i] for i in ids])


@lru_cache(maxsize=2)
def encoder(path: str) -> ForcedSplitEncoder:
    return ForcedSplitEncoder(path)


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def encode_documents(docs: DataFrame, vocabulary: str | None = None) -> DataFrame:
    """(doc_id, ids array<int>, decoded string) of every text; decoded comes from the ids."""
    path = vocabulary or default_vocabulary()

    def make():
        enc = encoder(path)

        def work(texts: list) -> dict:
            ids = [np.array(enc.encode(t), dtype=np.int32) for t in texts]
            ends = np.cumsum([0, *map(len, ids)]).astype(np.int32)
            flat = np.concatenate(ids) if ids else np.zeros(0, np.int32)
            return {"ids": pa.ListArray.from_arrays(pa.array(ends), pa.array(flat)), "decoded": [enc.decode(x.tolist()) for x in ids]}

        return work

    return map_texts(id_and_text(docs), make, "ids array<int>, decoded string")


def digest(encoded: DataFrame) -> DataFrame:
    return encoded.select("doc_id", F.size("ids").cast("long").alias("n_tokens"), F.sha2(F.array_join("ids", " "), 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))
