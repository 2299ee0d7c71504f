"""License notices by an exact set-similarity join, in DataFrame functions only.

A template is a set of words; a text is cut into overlapping blocks of twice a template's words, one
starting at every multiple of its length, so that a notice of that length lies whole in a block. A
block matches if it holds at least ``threshold`` of the template's distinct words (containment) and all
of its distinguishing words: those, if any are named, without which a short notice is one of another license.

The join is exact and never compares all blocks. The words of all templates are put in one global order,
rarest first, by how many documents they occur in; words of no template come before them. A block that
matches shares at least one of the template's ``m - need + 1`` rarest words (prefix filter), so only blocks
around such words are looked at. Of those, blocks of fewer than ``need`` words go (length filter); then blocks
with fewer than ``need`` different words from their rarest shared prefix word on, in the global order and
whatever template the words are of (positional filter). Words in common are counted for the rest alone.

The counts are one row per template word, whatever the input: they go to the driver. All the rest is
one narrow pass over the documents, without any shuffle, so no key or group can gather in a task.

Null texts count as empty: no words, no hits. Empty tables give no rows. Equal texts give equal hits;
hits are ordered by template and block. Word order within a block, ties and repeats do not matter,
as blocks are sets. All columns stay as they are; where there is a column ``found`` already, the new
one is named ``found_`` (with as many underscores as it takes).
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

THRESHOLD = 0.8
_SEPARATORS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"

# Phrases with their labels, public notices, and the words without which a notice is another one.
PHRASES = {"mit license": "mit", "apache license": "apache", "general public license": "gpl"}
TEMPLATES = {
    "apache": "licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license you may obtain a copy of the license at",
    "apache-notice": "licensed under the apache license version 2 0",
    "boost": "permission is hereby granted free of charge to any person or organization obtaining a copy of the software and accompanying documentation covered by this license to use reproduce display distribute execute and transmit the software",
    "bsd": "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met",
    "cc-by-nc": "licensed under cc by nc 4 0",
    "gpl": "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation",
    "gpl-notice": "this work is licensed under the gnu general public license version 3",
    "isc": "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies",
    "mit": "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions",
    "mit-notice": "released under the mit license",
    "mpl": "this source code form is subject to the terms of the mozilla public license v 2 0 if a copy of the mpl was not distributed with this file you can obtain one at",
    "unlicense": "this is free and unencumbered software released into the public domain anyone is free to copy modify publish use compile sell or distribute this software either in source code form or as a compiled binary for any purpose commercial or non commercial and by any means",
    "zlib": "this software is provided as is without any express or implied warranty in no event will the authors be held liable for any damages arising from the use of this software",
}
DISTINGUISHING = {"apache": "apache", "apache-notice": "apache", "cc-by-nc": "cc nc", "gpl": "gnu", "gpl-notice": "gnu", "mit-notice": "mit license", "mpl": "mozilla"}


def words(text: str | Column) -> Column:
    """The words of a text, A-Z lower-cased; null has none."""
    text = F.col(text) if isinstance(text, str) else text
    lowered = F.translate(F.coalesce(text, F.lit("")), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    return F.array_remove(F.split(lowered, _SEPARATORS), "")


def once(value: Column, use) -> Column:
    """``use(value)`` with the value computed once a row."""
    return F.element_at(F.transform(F.array(value), use), 1)


def _strings(values) -> Column:
    """A literal array, parsed at once: a call for every element would take the driver seconds."""
    return F.expr("array({})".format(", ".join("'" + v.replace("\\", "\\\\").replace("'", "\\'") + "'" for v in values))).cast("array<string>")


def _ints(values) -> Column:
    return F.expr(f"array({', '.join(map(str, values))})").cast("array<int>")


def word_counts(docs: DataFrame, vocabulary: list[str], text: str = "text") -> dict[str, int]:
    """In how many of all documents each word of a short list occurs."""
    rows = docs.select(F.explode(F.array_intersect(words(text), _strings(vocabulary))).alias("word")).groupBy("word").agg(F.count("*").alias("n"))
    found = {r["word"]: r["n"] for r in rows.collect()}  # a row per template word
    return {w: found.get(w, 0) for w in vocabulary}


def _phrase_places(ws: Column, phrase: list[str]) -> Column:
    last = F.size(ws) - F.lit(len(phrase))
    at = F.when(last >= 0, F.sequence(F.lit(0), last)).otherwise(F.array().cast("array<int>"))

    def here(i):
        out = F.get(ws, i) == phrase[0]
        for j, word in enumerate(phrase[1:], 1):
            out = out & (F.get(ws, i + F.lit(j)) == word)
        return out

    return F.filter(at, here)


def _labelled(places: Column, label: str) -> Column:
    return F.transform(places, lambda i: F.struct(F.lit(label).alias("label"), i.alias("first_word")))


def _stages(ws: Column, label: str, template: list[str], required: list[str], order: list[str], threshold: float) -> dict[str, Column]:
    """The blocks that each filter leaves, in turn; those left last are the hits.

    order: the words of all templates, rarest first. hits: array<struct<label, first_word, words, containment>>.
    """
    place = {w: i for i, w in enumerate(order)}
    distinct = sorted(set(template), key=place.__getitem__)
    stride, m = len(template), len(distinct)
    need = math.ceil(threshold * m - 1e-9)
    prefix = distinct[: m - need + 1]
    own = _ints([place[w] for w in distinct])
    near = F.filter(F.transform(ws, lambda w, i: F.when(F.array_contains(_strings(prefix), w), i)), lambda i: i.isNotNull())
    blocks = F.array_sort(F.array_distinct(F.flatten(F.transform(near, lambda i: F.array(F.greatest((i / stride).cast("int") - 1, F.lit(0)), (i / stride).cast("int"))))))
    sized = F.transform(blocks, lambda b: F.struct((b * stride).alias("first_word"), F.least(F.lit(2 * stride), F.size(ws) - b * stride).alias("words")))
    long = F.filter(sized, lambda b: b["words"] >= need)
    placed = F.transform(
        long,
        lambda b: F.struct(
            b["first_word"].alias("first_word"),
            b["words"].alias("words"),
            F.array_sort(F.array_remove(F.transform(F.array_distinct(F.slice(ws, b["first_word"] + 1, b["words"])), lambda w: F.array_position(_strings(order), w).cast("int") - 1), -1)).alias("places"),
        ),
    )
    rarest = lambda b: F.array_min(F.array_intersect(b["places"], _ints([place[w] for w in prefix])))
    far = F.filter(placed, lambda b: F.size(b["places"]) - F.array_position(b["places"], rarest(b)).cast("int") + 1 >= need)
    counted = F.transform(
        far,
        lambda b: F.struct(
            F.lit(label).alias("label"),
            b["first_word"].alias("first_word"),
            b["words"].alias("words"),
            (F.size(F.array_intersect(b["places"], own)).cast("double") / F.lit(float(m))).alias("containment"),
            F.forall(_ints([place[w] for w in required]), lambda w: F.array_contains(b["places"], w)).alias("told") if required else F.lit(True).alias("told"),
        ),
    )
    hits = F.filter(counted, lambda c: c["told"] & (c["containment"] >= F.lit(need / m - 1e-9)))
    hits = F.transform(hits, lambda c: F.struct(c["label"].alias("label"), c["first_word"].alias("first_word"), c["words"].alias("words"), c["containment"].alias("containment")))
    return {"prefix": sized, "length": long, "positional": far, "hits": hits}


def _global_order(docs: DataFrame, text: str, templates: dict[str, list[str]]) -> list[str]:
    """The words of all templates, rarest in the documents first."""
    vocabulary = sorted({w for t in templates.values() for w in t})
    counts = word_counts(docs, vocabulary, text) if vocabulary else {}
    return sorted(vocabulary, key=lambda w: (counts[w], w))


def _prefixes(templates: dict[str, list[str]], order: list[str], threshold: float) -> list[str]:
    out: set[str] = set()
    for t in templates.values():
        distinct = sorted(set(t), key=order.index)
        out |= set(distinct[: len(distinct) - math.ceil(threshold * len(distinct) - 1e-9) + 1])
    return sorted(out)


def _given(templates, distinguishing) -> tuple[dict[str, list[str]], dict[str, list[str]]]:
    """Templates and distinguishing words as word lists; words that a template lacks cannot distinguish it."""
    if templates is None and distinguishing is None:
        distinguishing = DISTINGUISHING
    held = {k: v.split() for k, v in (TEMPLATES if templates is None else templates).items()}
    return held, {k: [w for w in (distinguishing or {}).get(k, "").split() if w in t] for k, t in held.items()}


def filter_counts(docs: DataFrame, text: str = "text", templates: dict[str, str] | None = None, threshold: float = THRESHOLD, distinguishing: dict[str, str] | None = None) -> DataFrame:
    """(label, prefix, length, positional, hits): how many blocks each filter leaves, over all documents."""
    held, told = _given(templates, distinguishing)
    order = _global_order(docs, text, held)
    rows = None
    for label, t in held.items():
        sizes = F.struct(*[F.size(c).alias(k) for k, c in _stages(F.col("ws"), label, t, told[label], order, threshold).items()])
        one = docs.select(words(text).alias("ws")).select(sizes.alias("n")).agg(*[F.coalesce(F.sum(f"n.{k}"), F.lit(0)).alias(k) for k in ("prefix", "length", "positional", "hits")])
        one = one.select(F.lit(label).alias("label"), "*")
        rows = one if rows is None else rows.unionByName(one)
    return rows


def scan(docs: DataFrame, text: str = "text", phrases: dict[str, str] | None = None, templates: dict[str, str] | None = None, threshold: float = THRESHOLD, distinguishing: dict[str, str] | None = None) -> DataFrame:
    """Every row with ``found``: n_words, places (of phrases, by label) and hits (of templates).

    found is struct<n_words int, places array<struct<label, first_word>>, hits array<struct<label,
    first_word, words, containment>>>; first_word counts from 0.
    """
    phrases = PHRASES if phrases is None else phrases
    held, told = _given(templates, distinguishing)
    order = _global_order(docs, text, held)
    prefixes = _prefixes(held, order, threshold)
    no_hits = F.array().cast("array<struct<label: string, first_word: int, words: int, containment: double>>")
    no_places = F.array().cast("array<struct<label: string, first_word: int>>")

    def look(ws: Column) -> Column:
        places = [_labelled(_phrase_places(ws, p.split()), label) for p, label in phrases.items()]
        hits = [_stages(ws, label, t, told[label], order, threshold)["hits"] for label, t in held.items()]
        last = sorted({p.split()[-1] for p in phrases})
        return F.struct(
            F.size(ws).alias("n_words"),
            (F.when(F.arrays_overlap(ws, _strings(last)), F.concat(*places)).otherwise(no_places) if places else no_places).alias("places"),
            (F.when(F.arrays_overlap(ws, _strings(prefixes)), F.concat(*hits)).otherwise(no_hits) if hits else no_hits).alias("hits"),
        )

    name = "found"
    while name.lower() in (c.lower() for c in docs.columns):
        name += "_"
    return docs.withColumn(name, once(words(text), look))
