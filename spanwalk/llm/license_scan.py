"""License scans by a positional index of rare words.

Templates (short notices and opening grants of licences) are sequences of words. Corpus-wide
document counts of their words give each an inverse document frequency; every template is
indexed by its rarest words only, together with their positions. A text's indexed words look up
the postings, and postings that agree on the relative position (place in the text minus place in
the template) vouch for one placement of the template. A placement counts when the words that
agree carry at least `agree` of the template's rare weight and all words of its mandatory phrase
stand where the template has them. Phrases that must stand word for word are templates whose
every word is mandatory. All of it is DataFrame expressions.

Defined results: null, empty and wordless texts have no words, places or labels and score 0;
repeated rows are scanned one by one; overlapping placements all count; an empty table gives an
empty result; extra columns are not read.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import id_and_text, lower_ascii, settle, text_of

#: Fixed value: what separates words.
SEPARATORS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: Phrases that count by themselves, with their labels.
PHRASES = {"mit license": "mit", "apache license": "apache", "general public license": "gpl"}
#: (label, mandatory phrase, words of the template); the phrase is part of the template.
TEMPLATES = (
    ("mit", "mit license", "released under the mit license"),
    ("mit", "permission is hereby granted", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction"),
    ("mit", "without warranty of any kind", "the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of merchantability fitness for a particular purpose and noninfringement"),
    ("apache", "apache license version 2", "licensed under the apache license version 2 0"),
    ("apache", "compliance with the license", "you may not use this file except in compliance with the license you may obtain a copy of the license at"),
    ("gpl", "gnu general public license", "licensed under the gnu general public license version"),
    ("gpl", "gnu general public license", "redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation"),
    ("lgpl", "gnu lesser general public license", "under the terms of the gnu lesser general public license"),
    ("agpl", "gnu affero general public license", "under the terms of the gnu affero general public license"),
    ("bsd", "redistribution and use in source and binary forms", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met"),
    ("bsd", "bsd license", "licensed under the bsd license"),
    ("isc", "permission to use copy modify and", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted"),
    ("mpl", "mozilla public license", "this source code form is subject to the terms of the mozilla public license v 2 0"),
    ("epl", "eclipse public license", "made available under the terms of the eclipse public license"),
    ("unlicense", "unencumbered software released into the public domain", "this is free and unencumbered software released into the public domain"),
    ("cc-by", "cc by", "licensed under cc by"),
    ("cc-by-nc", "cc by nc", "licensed under cc by nc"),
    ("cc-by-sa", "cc by sa", "licensed under cc by sa"),
    ("cc-by", "creative commons attribution", "licensed under a creative commons attribution license"),
    ("cc0", "cc0 1 0 universal", "cc0 1 0 universal public domain dedication"),
    ("proprietary", "all rights reserved", "confidential and proprietary all rights reserved"),
)
RARE, AGREE = 6, 0.6


def words_of(text: Column) -> Column:
    return F.array_remove(F.split(lower_ascii(text), SEPARATORS, -1), "")


def document_counts(docs: DataFrame, vocabulary: list[str]) -> tuple[dict[str, int], int]:
    """Documents that hold each word of the vocabulary, and all documents; the result is bounded by the vocabulary."""
    seen = docs.select(F.explode(F.array_append(F.array_distinct(words_of(text_of())), "")).alias("w")).where(F.col("w").isin(*vocabulary, ""))
    found = {r.w: r.n for r in seen.groupBy("w").agg(F.count("*").alias("n")).collect()}
    return found, found.get("", 0)


def build_index(counts: dict[str, int], n: int, rare: int = RARE) -> list[tuple]:
    """Postings (template, label, kind, word, place, weight, must) of rare and mandatory words."""
    out = []
    for k, (phrase, label) in enumerate(PHRASES.items()):
        out += [(k, label, "phrase", w, p, 0.0, True) for p, w in enumerate(phrase.split())]
    for k, (label, phrase, body) in enumerate(TEMPLATES, len(PHRASES)):
        words, must = body.split(), phrase.split()
        at = next(i for i in range(len(words)) if words[i : i + len(must)] == must)
        idf = {w: math.log((n + 1) / (counts.get(w, 0) + 1)) + 1e-6 for w in words}
        # a word that no document holds can't vouch for a placement
        chosen = set(sorted((p for p in range(len(words)) if counts.get(words[p])), key=lambda p: (-idf[words[p]], p))[:rare])
        for p, w in enumerate(words):
            inside = at <= p < at + len(must)
            if p in chosen or inside:
                out.append((k, label, "template", w, p, idf[w] if p in chosen else 0.0, inside))
    return out


def anchors_of(index: list[tuple], counts: dict[str, int]) -> list[str]:
    """For each template the mandatory word that fewest documents hold: no placement can do without it."""
    must: dict[int, list[str]] = {}
    for k, _, _, word, _, _, inside in index:
        if inside:
            must.setdefault(k, []).append(word)
    return sorted({min(words, key=lambda w: (counts.get(w, 0), w)) for words in must.values()})


def scan_licenses(docs: DataFrame, rare: int = RARE, agree: float = AGREE) -> DataFrame:
    """(doc_id, n_words, places, base_labels, labels, score); places are (start, label, kind, score)."""
    docs, spark = id_and_text(docs), docs.sparkSession
    vocabulary = sorted({w for _, _, body in TEMPLATES for w in body.split()})
    counts, n = document_counts(docs, vocabulary)
    index = build_index(counts, n, rare)
    postings = spark.createDataFrame(index, "template int, label string, kind string, word string, place int, weight double, must boolean")
    indexed = sorted({p[3] for p in index})
    words = words_of(text_of())
    anchored = F.arrays_overlap(words, F.array(*map(F.lit, anchors_of(index, counts))))
    hits = F.when(~anchored, F.array().cast("array<struct<i:int,w:string>>")).otherwise(F.filter(F.transform(words, lambda w, i: F.when(w.isin(*indexed), F.struct(i.alias("i"), w.alias("w")))), lambda x: x.isNotNull()))
    rows = settle(docs.select("doc_id", F.struct(F.size(words).cast("long").alias("n_words"), hits.alias("hits")).alias("x")).select("doc_id", "x.*").withColumn("row", F.monotonically_increasing_id()))
    need = postings.groupBy("template").agg(F.sum("weight").alias("whole"), F.sum(F.col("must").cast("int")).alias("n_must"))
    # the index is of fixed size: a few hundred postings whatever the corpus
    table = F.broadcast(postings.join(need, "template"))
    met = rows.select("row", F.explode("hits").alias("x")).select("row", "x.i", F.col("x.w").alias("word")).join(table, "word")
    placed = met.groupBy("row", "template", "label", "kind", (F.col("i") - F.col("place")).alias("at"), "whole", "n_must").agg(
        F.sum("weight").alias("got"), F.sum(F.col("must").cast("int")).alias("musts"), F.min(F.when(F.col("must"), F.col("i"))).alias("start")
    )
    share = F.when(F.col("kind") == "phrase", 1.0).otherwise(F.round(F.col("got") / F.col("whole"), 6))
    good = placed.where("musts = n_must").withColumn("score", share).where(F.col("score") >= agree)
    by_row = good.groupBy("row").agg(
        F.sum(F.when(F.col("kind") == "phrase", 1).otherwise(0)).cast("long").alias("n_base"),
        F.min(F.when(F.col("kind") == "phrase", F.col("at"))).cast("long").alias("first_word"),
        F.max(F.when(F.col("kind") == "phrase", F.col("at"))).cast("long").alias("last_word"),
        F.array_sort(F.collect_set(F.when(F.col("kind") == "phrase", F.col("label")))).alias("base_labels"),
        F.array_sort(F.collect_set("label")).alias("labels"),
        F.max(F.when(F.col("kind") == "template", F.col("score"))).alias("best"),
    )
    joined = rows.select("row", "doc_id", "n_words").join(by_row, "row", "left")
    none = F.array().cast("array<string>")
    return joined.select(
        "doc_id", "n_words", F.coalesce("n_base", F.lit(0).cast("long")).alias("n_base"), "first_word", "last_word",
        F.coalesce("base_labels", none).alias("base_labels"), F.coalesce("labels", none).alias("labels"),
        # a phrase alone, in no template's surroundings, is weaker evidence than a whole notice
        F.when(F.col("labels").isNull(), 0.0).otherwise(F.coalesce("best", F.lit(0.5))).alias("score"),
    )


def digest(found: DataFrame) -> DataFrame:
    return found.withColumns({c: F.array_join(c, ",") for c in ("base_labels", "labels")})
