"""Licence scans with a positional index of rare licence words (DataFrame functions only).

Templates are indexed by word position. A template counts only if its mandatory key phrases stand in
the file. For each such template those of its words that have the highest inverse document frequency
and stand in the file are looked up; their postings vote for a relative position (place in the file
minus place in the template). Where they give no placement enough votes, all words of the template
vote, so that neither other notices nor rare words elsewhere in the file hide a notice.

Scale: one pass counts in how many files each template word stands (a map-side aggregation to as
many rows as templates have words). A second pass works within each row with array functions, so
nothing is shuffled, no file can make another wait, and texts are read whole. The template index is
broadcast as literals; it is a parameter of the caller and does not grow with the data.
"""

from __future__ import annotations

import math
import re

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import WORD_CLASS, ascii_lower, two_columns

#: Phrases that are always counted, with their labels.
BASE_PHRASES = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}

#: label -> (opening words of the licence notice, phrases that must stand in the file)
TEMPLATES: dict[str, tuple[str, tuple[str, ...]]] = {
    "mit": ("released under the mit license permission is hereby granted free of charge to any person obtaining a copy of this software", ("mit license",)),
    "apache-2.0": ("licensed under the apache license version 2 0 you may not use this file except in compliance with the license", ("apache license",)),
    "gpl": ("this work is licensed under the gnu general public license version 3 as published by the free software foundation", ("general public license",)),
    "lgpl": ("licensed under the gnu lesser general public license as published by the free software foundation", ("lesser general public license",)),
    "mpl-2.0": ("this source code form is subject to the terms of the mozilla public license v 2 0", ("mozilla public license",)),
    "bsd": ("redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met", ("redistribution and use",)),
    "cc-by": ("licensed under cc by 4 0 this work is licensed under a creative commons attribution international license", ("cc by",)),
    "cc-by-nc": ("licensed under cc by nc 4 0 creative commons attribution noncommercial", ("cc by nc",)),
    "cc-by-sa": ("licensed under cc by sa 4 0 creative commons attribution sharealike", ("cc by sa",)),
    "unlicense": ("this is free and unencumbered software released into the public domain", ("unencumbered software",)),
    "reserved": ("copyright c all rights reserved", ("all rights reserved",)),
}


def words_of(text: str) -> list[str]:
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", text.translate({i: i + 32 for i in range(65, 91)}))


def _strings(values: list[str]) -> str:
    return "array(" + ", ".join("'" + v.replace("\\", "\\\\").replace("'", "\\'") + "'" for v in values) + ")" if values else "cast(array() as array<string>)"


def _stands(phrase: list[str], places: str = "places") -> str:
    """SQL: starts of a phrase among the licence words ``places`` (array of struct(at, w)) of a row.

    The words that follow are looked up by place, as every word of a phrase is kept in ``places``.
    """
    test = f"p.w = '{phrase[0]}'"
    for k, w in enumerate(phrase[1:], 1):
        test += f" AND get({places}, i + {k}).w = '{w}' AND get({places}, i + {k}).at = p.at + {k}"
    return f"transform(filter({places}, (p, i) -> {test}), p -> p.at)"


_NO_PLACES = "cast(array() AS array<struct<at: bigint, w: string>>)"


def _places(have: str) -> str:
    """SQL: array of struct(at, w) of the words of a row that are in the array ``have``."""
    return f"filter(transform(words, (w, i) -> IF(array_contains({have}, w), struct(cast(i AS bigint) AS at, w AS w), null)), x -> x IS NOT NULL)"


def _best_votes(template: str, own: str) -> str:
    """SQL: votes of the best placement of ``template`` (a struct with ``at``) by its words ``own``: the longest run of one relative position."""
    deltas = f"sort_array(flatten(transform(filter(places_own, p -> array_contains({own}, p.w)), p -> transform(element_at({template}.at, p.w), q -> p.at - q))))"
    run = "IF(a.last <=> d, a.n + 1, 1)"
    return f"aggregate({deltas}, named_struct('last', cast(null AS bigint), 'n', 0, 'best', 0), (a, d) -> named_struct('last', d, 'n', {run}, 'best', greatest(a.best, {run})), a -> a.best)"


def template_document_counts(words: Column, vocabulary: list[str], docs: DataFrame) -> dict[str, int]:
    """In how many rows of ``docs`` each template word stands: at most one row a template word comes back."""
    seen = docs.select(F.explode(F.array_intersect(words, F.expr(_strings(vocabulary)))).alias("w"))
    return {r["w"]: r["n"] for r in seen.groupBy("w").agg(F.count(F.lit(1)).alias("n")).collect()}


def license_scan(
    docs: DataFrame,
    key: str = "doc_id",
    text: str = "text",
    templates: dict[str, tuple[str, tuple[str, ...]]] | None = None,
    rare_words: int = 6,
    votes_needed: int = 3,
) -> DataFrame:
    """One row per input row: doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, placements.

    n_base counts every place of every base phrase; first_word and last_word are the smallest and the
    largest start. ``labels`` has the base labels and those whose template found a placement with
    ``votes_needed`` votes (or as many as the template has words in this corpus, at most ``rare_words``, if
    fewer) and whose key phrases stand in the file. Votes come from the ``rare_words`` rarest words of the
    template that the file has, and from all its words if those are too few. ``score`` is 1 - 2^-(base places + votes of accepted templates), so 0
    without any licence. Null and empty texts have no words, empty labels, score 0. Ties between rare
    words go to the alphabetically first. Repeated rows are scanned alike, an empty table gives none.
    """
    templates = TEMPLATES if templates is None else templates
    index: dict[str, list[tuple[int, int]]] = {}
    labels = sorted(templates)
    for t, label in enumerate(labels):
        for at, w in enumerate(words_of(templates[label][0])):
            index.setdefault(w, []).append((t, at))
    phrases = [words_of(p) for p in BASE_PHRASES]
    keys = {label: [words_of(p) for p in templates[label][1]] for label in labels}
    vocabulary = sorted(set(index) | {w for p in phrases for w in p} | {w for ps in keys.values() for p in ps for w in p})
    base = two_columns(docs, key, text)
    words = F.regexp_extract_all(ascii_lower(F.col("text")), F.lit(WORD_CLASS), F.lit(0))
    total = base.count()
    found = template_document_counts(words, vocabulary, base) if total else {}
    idf = {w: math.log((1 + total) / (1 + found.get(w, 0))) for w in index}
    # The words of each template that the corpus has at all, in order of falling IDF.
    ranked = [sorted({w for w in words_of(templates[label][0]) if found.get(w)}, key=lambda w: (-idf[w], w)) for label in labels]
    needed = sorted({w for p in phrases for w in p} | {w for ps in keys.values() for p in ps for w in p})
    rows = base.select("doc_id", words.alias("words"))
    rows = rows.select("doc_id", F.size("words").cast("long").alias("n_words"), F.col("words"), F.expr(f"array_intersect({_strings(needed)}, words)").alias("have"))
    rows = rows.withColumn("places", F.expr(f"IF(size(have) > 0, {_places('have')}, {_NO_PLACES})"))
    rows = rows.select("*", *[F.expr(_stands(p)).alias(f"b{k}") for k, p in enumerate(phrases)])
    starts = F.concat(*[f"b{k}" for k in range(len(phrases))])
    rows = rows.select("*", starts.alias("starts"))
    # Templates whose key phrases stand in the file: (label, votes needed, words by rarity, places of each word).
    keyed = []
    for t, label in enumerate(labels):
        if ranked[t]:
            must = " AND ".join(f"size({_stands(p)}) > 0" for p in keys[label]) or "true"
            need = max(1, min(votes_needed, rare_words, len(ranked[t])))
            at = ", ".join(f"'{w}', array({', '.join(f'cast({x} AS bigint)' for u, x in index[w] if u == t)})" for w in ranked[t])
            keyed.append(F.expr(f"IF({must}, struct('{label}' AS label, {need} AS need, {_strings(ranked[t])} AS own, map({at}) AS at), null)"))
    if keyed:
        rows = rows.withColumn("keyed", F.array_compact(F.array(*keyed)))
        rows = rows.withColumn("have_own", F.expr("array_intersect(array_distinct(flatten(transform(keyed, t -> t.own))), words)"))
        rows = rows.withColumn("places_own", F.expr(f"IF(size(have_own) > 0, {_places('have_own')}, {_NO_PLACES})"))
        # First the rarest words that the file has of each template; where they do not place it, all its words.
        rare = f"slice(filter(t.own, w -> array_contains(have_own, w)), 1, {rare_words})"
        rows = rows.withColumn("rare", F.expr(f"transform(keyed, t -> struct(t AS t, {_best_votes('t', rare)} AS votes))"))
        all_words = _best_votes("x.t", "x.t.own")
        rows = rows.withColumn("tried", F.expr(f"transform(rare, x -> struct(x.t.label AS label, x.t.need AS need, IF(x.votes >= x.t.need, x.votes, {all_words}) AS votes))"))
        rows = rows.withColumn("placed", F.expr("transform(filter(tried, x -> x.votes >= x.need), x -> struct(x.label AS label, x.votes AS votes))"))
    else:
        rows = rows.withColumn("placed", F.expr("cast(array() AS array<struct<label: string, votes: int>>)"))
    base_labels = F.array_compact(F.array(*[F.when(F.size(f"b{k}") > 0, F.lit(label)) for k, label in enumerate(BASE_PHRASES.values())]))
    power = F.size("starts") + F.aggregate("placed", F.lit(0), lambda a, p: a + p["votes"])
    return rows.select(
        "doc_id",
        "n_words",
        F.size("starts").cast("long").alias("n_base"),
        F.array_min("starts").cast("long").alias("first_word"),
        F.array_max("starts").cast("long").alias("last_word"),
        F.concat_ws(",", F.array_sort(F.array_distinct(base_labels))).alias("base_labels"),
        F.concat_ws(",", F.array_sort(F.array_distinct(F.concat(base_labels, F.expr("transform(placed, p -> p.label)"))))).alias("labels"),
        (F.lit(1.0) - F.pow(F.lit(2.0), -power)).alias("score"),
        F.col("placed").alias("placements"),
    )
