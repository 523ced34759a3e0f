"""Licence scans over a positional rare-token index (DataFrame functions only).

Corpus document frequencies of the licence words give each word an IDF. Every template is indexed
under its rarest words with their relative positions. A file's occurrences of the rarest word of a
template propose a start; the postings of the template's other indexed words must fall on the same
start, and the mandatory key phrase must stand there word for word. Base phrases are templates whose
key phrase is the whole template, so their places are exact.

Only the document frequencies of the licence vocabulary (as many numbers as the templates have
words) reach the driver; the scan itself is row-local and moves nothing.

Defined cases: null, empty and word-free texts have no words, no places, empty labels and score 0;
an empty table gives no rows; repeated rows each get a result; other columns are ignored.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sparkcurate.llm.native import words

INDEXED_WORDS = 3


@dataclass(frozen=True)
class Template:
    label: str
    text: str
    key: str
    base: bool = False

    @property
    def words(self) -> list[str]:
        return self.text.split()

    @property
    def key_offset(self) -> int:
        key = self.key.split()
        return next(i for i in range(len(self.words)) if self.words[i : i + len(key)] == key)


# The base phrases with their labels, then the notices and names the method adds.
TEMPLATES = (
    Template("mit", "mit license", "mit license", True),
    Template("apache", "apache license", "apache license", True),
    Template("gpl", "general public license", "general public license", True),
    Template("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software", "permission is hereby granted free of charge"),
    Template("apache", "licensed under the apache license version 2 0", "apache license version"),
    Template("gpl", "licensed under the gnu general public license version 3", "gnu general public license"),
    Template("lgpl", "gnu lesser general public license", "lesser general public license"),
    Template("agpl", "gnu affero general public license", "affero general public license"),
    Template("bsd", "redistribution and use in source and binary forms with or without modification are permitted", "redistribution and use in source and binary forms"),
    Template("cc-by-nc", "licensed under cc by nc 4 0", "cc by nc"),
    Template("cc-by-sa", "licensed under cc by sa 4 0", "cc by sa"),
    Template("cc-by", "licensed under cc by 4 0", "cc by 4"),
    Template("cc-by", "creative commons attribution", "creative commons attribution"),
    Template("mpl", "mozilla public license", "mozilla public license"),
    Template("epl", "eclipse public license", "eclipse public license"),
    Template("isc", "isc license", "isc license"),
    Template("bsl", "boost software license", "boost software license"),
    Template("apache", "you may not use this file except in compliance with the license you may obtain a copy of the license at", "you may not use this file except in compliance"),
    Template("gpl", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation", "this program is free software you can redistribute it"),
    Template("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", "permission to use copy modify and or distribute this software"),
    Template("mpl", "this source code form is subject to the terms of the mozilla public license v 2 0", "this source code form is subject"),
    Template("zlib", "this software is provided as is without any express or implied warranty in no event will the authors be held liable for any damages", "in no event will the authors be held liable"),
    Template("cc0", "to the extent possible under law the author has waived all copyright and related or neighboring rights to this work", "waived all copyright and related or neighboring rights"),
    Template("bsd", "neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products", "nor the names of its contributors may be used to endorse"),
    Template("unlicense", "this is free and unencumbered software released into the public domain", "free and unencumbered software"),
)


def document_frequencies(docs: DataFrame, vocabulary: list[str]) -> tuple[int, dict[str, int]]:
    """Number of documents, and of those that hold each licence word; over all documents."""
    found = F.array_intersect(words(F.col("text")), F.array(*[F.lit(w) for w in vocabulary]))
    rows = docs.select(F.explode(F.concat(found, F.array(F.lit("")))).alias("__w")).groupBy("__w").count().collect()
    counts = {r["__w"]: r["count"] for r in rows}
    return counts.pop("", 0), counts


def inverse_frequencies(docs: DataFrame, templates: tuple[Template, ...]) -> dict[str, float]:
    vocabulary = sorted({w for t in templates for w in t.words})
    total, df = document_frequencies(docs, vocabulary)
    return {w: math.log((total + 1) / (df.get(w, 0) + 1)) + 1 for w in vocabulary}


def indexed_offsets(template: Template, idf: dict[str, float]) -> list[int]:
    """Offsets of the template's rarest words, rarest first; ties by word, then offset."""
    order = sorted(range(len(template.words)), key=lambda o: (-idf[template.words[o]], template.words[o], o))
    return order[:INDEXED_WORDS]


def _starts(template: Template, idf: dict[str, float], text_words: Column, hits: Column) -> Column:
    """Starts of the template: aligned rare words and the key phrase word for word."""
    offsets = indexed_offsets(template, idf)
    rarest, rest, key = offsets[0], offsets[1:], template.key.split()
    word_at = lambda i: F.get(text_words, i)

    def stands(hit: Column) -> Column:
        start = hit["i"] - rarest
        good = (hit["w"] == template.words[rarest]) & (start >= 0)
        for o in [*rest, *(template.key_offset + j for j in range(len(key)))]:
            if o != rarest:
                good = good & F.coalesce(word_at(start + o) == template.words[o], F.lit(False))
        return good

    return F.transform(F.filter(hits, stands), lambda hit: hit["i"] - rarest)


def _share(template: Template, idf: dict[str, float], text_words: Column, starts: Column) -> Column:
    """Largest IDF share of the template's words that stand at their places."""
    total = sum(idf[w] for w in template.words)

    def one(start: Column) -> Column:
        parts = [F.when(F.get(text_words, start + o) == w, idf[w]).otherwise(0.0) for o, w in enumerate(template.words)]
        return sum(parts[1:], parts[0]) / total

    return F.aggregate(starts, F.lit(0.0), lambda best, start: F.greatest(best, one(start)))


def scan_licenses(docs: DataFrame, templates: tuple[Template, ...] = TEMPLATES) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score for every row."""
    idf = inverse_frequencies(docs, templates)
    anchors = sorted({t.words[indexed_offsets(t, idf)[0]] for t in templates})
    base = docs.select("doc_id", words(F.col("text")).alias("__w"))
    hits = F.filter(F.transform("__w", lambda w, i: F.when(w.isin(anchors), F.struct(i.alias("i"), w.alias("w")))), lambda h: h.isNotNull())
    none = F.filter(F.array(F.struct(F.lit(0).alias("i"), F.lit("").alias("w"))), lambda h: F.lit(False))
    found = base.withColumn("__h", F.when(F.arrays_overlap("__w", F.array(*[F.lit(a) for a in anchors])), hits).otherwise(none))
    nowhere = F.filter(F.array(F.lit(0)), lambda i: F.lit(False))
    any_hit = F.size("__h") > 0
    found = found.withColumn("__s", F.when(any_hit, F.array(*[_starts(t, idf, F.col("__w"), F.col("__h")) for t in templates])).otherwise(F.array(*[nowhere for _ in templates])))
    of = lambda k: F.get(F.col("__s"), F.lit(k))
    places = F.flatten(F.slice("__s", 1, sum(t.base for t in templates)))
    assert all(t.base for t in templates[: sum(t.base for t in templates)]), "base templates come first"

    def labels(base_only: bool) -> Column:
        names = [F.when(F.size(of(k)) > 0, t.label) for k, t in enumerate(templates) if t.base or not base_only]
        return F.concat_ws(",", F.array_sort(F.array_distinct(F.array_compact(F.array(*names)))))

    shares = [_share(t, idf, F.col("__w"), of(k)) for k, t in enumerate(templates)]
    return found.select(
        "doc_id", F.size("__w").cast("long").alias("n_words"), F.size(places).cast("long").alias("n_base"),
        F.array_min(places).cast("long").alias("first_word"), F.array_max(places).cast("long").alias("last_word"),
        labels(True).alias("base_labels"), labels(False).alias("labels"),
        F.when(any_hit, F.round(F.greatest(*shares), 6)).otherwise(0.0).alias("score"),
    )
