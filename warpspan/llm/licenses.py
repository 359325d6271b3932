"""License scans as an exact set-similarity join of templates and text blocks.

A template is a license phrase or notice; its words are put in order of how
rare they are in the whole corpus (counted over all documents first). A block
is a run of consecutive words as long as the template. It matches if it holds
at least a share ``threshold`` of the template's distinct words.

Finding every such block needs few comparisons:

* prefix: a block that holds ``need`` of k words must hold one of the
  template's ``k - need + 1`` rarest; only occurrences of these are looked at;
* length: a block shorter than ``need`` words at a text's end is left out;
* position: the places of the template's words in the text bound what a block
  can hold, so a block with fewer than ``need`` of these places is left out.

What passes is verified by counting. A phrase (``ordered``) must also have its
words one after another. Templates and their words' counts are bounded by the
caller's list, not by the corpus, and travel to every task.

A text's score is the highest share that a matching block holds, or 0. Counts of
other documents change which words are looked at first and never the result.

Null and empty texts have no words and score 0. Repeated rows are scanned each
for itself; an empty table gives an empty result.
"""

from __future__ import annotations

import math
from collections import Counter
from typing import NamedTuple

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from warpspan.llm.common import utf8, values, words_of


class Template(NamedTuple):
    label: str
    text: str
    ordered: bool
    threshold: float = 1.0


# Phrases of the base rule and their labels.
PHRASES = (
    Template("gpl", "gnu general public license", True),
    Template("apache", "apache license", True),
    Template("cc-by", "cc by", True),
    Template("mit", "mit license", True),
)

# Notices that the method finds besides.
NOTICES = (
    Template("apache-notice", "licensed under the apache license version 2.0 you may not use this file except in compliance with the license", False, 0.8),
    Template("mit-notice", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files", False, 0.8),
    Template("gpl-notice", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation", False, 0.8),
    Template("bsd-notice", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met", False, 0.8),
    Template("cc-notice", "this work is licensed under a creative commons attribution license", False, 0.8),
    Template("mpl-notice", "this source code form is subject to the terms of the mozilla public license", False, 0.8),
    Template("all-rights-reserved", "all rights reserved", True),
)

FOUND = T.StructType(
    [
        T.StructField("n_words", T.LongType()),
        T.StructField("score", T.DoubleType()),
        T.StructField(
            "places",
            T.ArrayType(
                T.StructType(
                    [
                        T.StructField("template", T.IntegerType()),
                        T.StructField("word", T.LongType()),
                        T.StructField("after", T.LongType()),
                        T.StructField("share", T.DoubleType()),
                    ]
                )
            ),
        ),
    ]
)
_ARROW_FOUND = pa.struct(
    [
        ("n_words", pa.int64()),
        ("score", pa.float64()),
        ("places", pa.list_(pa.struct([("template", pa.int32()), ("word", pa.int64()), ("after", pa.int64()), ("share", pa.float64())]))),
    ]
)


def template_words(templates: tuple[Template, ...]) -> list[list[bytes]]:
    return [words_of(t.text.encode()) for t in templates]


def word_counts(documents: DataFrame, templates: tuple[Template, ...], text: str = "text") -> dict[bytes, int]:
    """How often each template word occurs in all documents; one row per template word comes to the driver."""
    wanted = frozenset(w for words in template_words(templates) for w in words)

    def count(source):
        for batch in source:
            total: Counter = Counter()
            for value in values(batch.column(0)):
                total.update(w for w in words_of(value) if w in wanted)
            yield pa.record_batch([pa.array(list(total), pa.binary()), pa.array(list(total.values()), pa.int64())], names=["word", "n"])

    rows = documents.select(utf8(text).alias("text")).mapInArrow(count, "word binary, n bigint")
    found = {bytes(r.word): r.n for r in rows.groupBy("word").agg(F.sum("n").alias("n")).collect()}
    return {w: found.get(w, 0) for w in wanted}


class TemplateIndex:
    """Templates by the words of their prefixes; ``looked_at`` and ``verified`` count blocks before and after the positional filter."""

    def __init__(self, templates: tuple[Template, ...], counts: dict[bytes, int]):
        self.templates = templates
        self.words = template_words(templates)
        self.sets = [frozenset(words) for words in self.words]
        self.need = [max(1, math.ceil(t.threshold * len(s) - 1e-9)) for t, s in zip(templates, self.sets, strict=True)]
        self.probes: dict[bytes, list[int]] = {}
        for number, (words, need) in enumerate(zip(self.sets, self.need, strict=True)):
            rarest_first = sorted(words, key=lambda w: (counts.get(w, 0), w))
            for word in rarest_first[: len(words) - need + 1]:
                self.probes.setdefault(word, []).append(number)
        self.keys = frozenset(self.probes)
        self.looked_at = self.verified = 0

    def scan(self, words: list[bytes]) -> tuple[float, list[tuple[int, int, int, float]]]:
        """The best share of a match, and places ``(template, first word, word after, share)`` in order."""
        if self.keys.isdisjoint(words):
            return 0.0, []
        places: list[tuple[int, int, int, float]] = []
        met: dict[int, list[int]] = {}
        for at, word in enumerate(words):
            for number in self.probes.get(word, ()):
                met.setdefault(number, []).append(at)
        for number, probes in met.items():
            places += self._phrases(number, probes, words) if self.templates[number].ordered else self._blocks(number, probes, words)
        places.sort(key=lambda p: (p[1], p[0]))
        return max((p[3] for p in places), default=0.0), places

    def _phrases(self, number: int, probes: list[int], words: list[bytes]) -> list[tuple[int, int, int, float]]:
        template = self.words[number]
        length = len(template)
        starts = {at - k for at in probes for k, w in enumerate(template) if w == words[at]}
        return [(number, s, s + length, 1.0) for s in sorted(starts) if s >= 0 and words[s : s + length] == template]

    def _blocks(self, number: int, probes: list[int], words: list[bytes]) -> list[tuple[int, int, int, float]]:
        """Matching blocks; those that overlap are one place."""
        wanted, need, length = self.sets[number], self.need[number], len(self.words[number])
        spots = [at for at, word in enumerate(words) if word in wanted]
        runs: list[list] = []
        inside: Counter = Counter()
        held = low = high = 0  # the spots low .. high - 1 are in the block, and held different words
        after = 0
        for probe in probes:
            for start in range(max(after, probe - length + 1), probe + 1):
                # A block that begins before the text is the same as its first.
                begin = max(0, start)
                end = min(len(words), start + length) if start >= 0 else min(len(words), length)
                self.looked_at += 1
                while high < len(spots) and spots[high] < end:
                    word = words[spots[high]]
                    inside[word] += 1
                    held += inside[word] == 1
                    high += 1
                while low < high and spots[low] < begin:
                    word = words[spots[low]]
                    inside[word] -= 1
                    held -= inside[word] == 0
                    low += 1
                if high - low < need or end - begin < need:
                    continue
                self.verified += 1
                if held >= need:
                    share = held / len(wanted)
                    if runs and begin <= runs[-1][1]:
                        runs[-1][1], runs[-1][2] = end, max(runs[-1][2], share)
                    else:
                        runs.append([begin, end, share])
            after = max(after, probe + 1)
        return [(number, *run) for run in runs]


def license_places(documents: DataFrame, templates: tuple[Template, ...] = PHRASES + NOTICES, text: str = "text") -> Column:
    """A column with ``n_words``, ``score`` and the ``places`` of each text.

    Blocks of one notice that overlap are one place.
    """
    shared = documents.sparkSession.sparkContext.broadcast(word_counts(documents, templates, text))
    ready: list[TemplateIndex] = []

    @F.arrow_udf(FOUND)
    def scan(texts: pa.Array) -> pa.Array:
        if not ready:
            ready.append(TemplateIndex(templates, shared.value))
        rows = []
        for value in values(texts):
            words = words_of(value)
            score, places = ready[0].scan(words)
            rows.append(
                {
                    "n_words": len(words),
                    "score": score,
                    "places": [dict(zip(("template", "word", "after", "share"), p, strict=True)) for p in places],
                }
            )
        return pa.array(rows, _ARROW_FOUND)

    return scan(utf8(text))


def scan_documents(
    documents: DataFrame, phrases: tuple[Template, ...] = PHRASES, notices: tuple[Template, ...] = NOTICES, id_column: str = "doc_id", text: str = "text"
) -> DataFrame:
    """One row per document: words, phrase places, labels of phrases and of all templates, score and places."""
    found = documents.select(F.col(id_column), license_places(documents, phrases + notices, text).alias("f"))
    names = F.array(*(F.lit(t.label) for t in phrases + notices))
    base = F.filter("f.places", lambda p: p.template < len(phrases))
    label = lambda places: F.array_join(F.array_sort(F.array_distinct(F.transform(places, lambda p: F.get(names, p.template)))), ",")
    starts = F.transform(base, lambda p: p.word)
    return found.select(
        F.col(id_column),
        F.col("f.n_words").alias("n_words"),
        F.size(base).cast("long").alias("n_base"),
        F.array_min(starts).alias("first_word"),
        F.array_max(starts).alias("last_word"),
        label(base).alias("base_labels"),
        label(F.col("f.places")).alias("labels"),
        F.col("f.score").alias("score"),
        F.col("f.places").alias("places"),
    )
