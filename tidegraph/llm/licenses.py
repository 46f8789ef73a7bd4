"""License scans: exact set-similarity join of text blocks with notice templates, in Spark expressions alone.

A block is a run of consecutive words, as long as a template may be with a fifth of foreign words in it, so that neither
line ends nor comment marks matter. It matches a template if it contains enough of the template's distinct words. Words
are ordered by how often the corpus holds them, rarest first. A block can only reach the threshold if it holds a word of
the template's prefix in that order, so places of prefix words are equality-joined; length and position filters drop most
candidates before the overlap is counted.
"""

from __future__ import annotations

import math
import re
from collections.abc import Mapping

from pyspark.sql import Column, DataFrame, functions as F

from tidegraph.runtime import materialize

#: Notices by label. Texts of common license notices.
TEMPLATES: dict[str, tuple[str, ...]] = {
    "apache": (
        "Licensed under the Apache License, Version 2.0.",
        "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at",
        "Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.",
    ),
    "boost": ("Distributed under the Boost Software License, Version 1.0.",),
    "bsd": (
        "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met",
        "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.",
        "Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.",
    ),
    "cc-by": ("This work is licensed under a Creative Commons Attribution 4.0 International License.",),
    "cc-by-nc": ("Licensed under CC BY-NC 4.0.", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    "cc-by-sa": ("This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.",),
    "gpl": (
        "This work is licensed under the GNU General Public License, version 3.",
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    ),
    "isc": ("Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",),
    "mit": (
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions",
        "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.",
    ),
    "mpl": ("This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",),
    "unlicense": ("This is free and unencumbered software released into the public domain.",),
}
#: Phrases whose places count as base mentions. Fixed values.
PHRASES: dict[str, tuple[str, ...]] = {
    "mit": ("mit", "license"),
    "apache": ("apache", "license"),
    "gpl": ("general", "public", "license"),
}
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: What stands between words: ASCII other than letters and digits.
_BETWEEN = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def _lowered(text: Column) -> Column:
    """Lower case, for comparison with words of ASCII letters: of other letters only the Kelvin sign turns into one, so it is put out of the way."""
    text = F.coalesce(text, F.lit(""))
    return F.lower(F.when(F.contains(text, F.lit("\u212a")), F.replace(text, F.lit("\u212a"), F.lit("\u0138"))).otherwise(text))


def template_words(text: str) -> list[str]:
    """A template's words in order, A-Z lower-cased."""
    return [w for w in re.split(_BETWEEN, text.translate(str.maketrans(_UPPER, _LOWER))) if w]


def span_of(words: list[str], threshold: float) -> int:
    """Words of a block for a template of these words."""
    return math.ceil(len(words) / threshold - 1e-9)


def least_of(words: list[str], threshold: float) -> int:
    """Distinct words of the template that a block must hold."""
    return max(1, math.ceil(threshold * len(set(words)) - 1e-9))


def word_places(docs: DataFrame, vocabulary: list[str], id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, n_words, hits)`` of every document with an id: its words are made once, and those of ``vocabulary`` kept with their positions."""

    def kept(words: Column) -> Column:
        own = F.transform(words, lambda w, i: F.when(w.isin(*vocabulary), F.struct(i.alias("at"), w.alias("w"))))
        return F.struct(F.size(words).cast("long").alias("n_words"), F.filter(own, lambda x: x.isNotNull()).alias("hits"))

    words = F.filter(F.split(_lowered(F.col(text_col)), _BETWEEN), lambda w: w != "")
    made = F.element_at(F.transform(F.array(words), kept), 1)  # the words are bound as a lambda argument
    return docs.where(F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("doc_id"), made.alias("m")).select("doc_id", "m.*")


def template_matches(places: DataFrame, templates: Mapping[str, tuple[str, ...]] = TEMPLATES, threshold: float = 0.8) -> DataFrame:
    """``(doc_id, label, containment)``: the best containment of a template with this label in any block of the document, at least ``threshold``.

    ``places`` are those of ``word_places`` for a vocabulary that has all words of the templates. Each place of a prefix
    word takes the hits around it along, at most two blocks of them, so no row grows with its text.
    """
    spark = places.sparkSession
    entries = [(label, template_words(text)) for label, texts in sorted(templates.items()) for text in texts]
    vocabulary = {w for _, words in entries for w in words}
    counted = places.select(F.explode("hits.w").alias("w")).groupBy("w").agg(F.count(F.lit(1)).alias("n"))
    counts = {r["w"]: r["n"] for r in counted.collect()}  # a row for each template word
    rank = {w: i for i, w in enumerate(sorted(vocabulary, key=lambda w: (counts.get(w, 0), w)))}
    probes = []
    for label, words in entries:
        ordered, least = sorted(set(words), key=rank.__getitem__), least_of(words, threshold)
        probes += [(label, w, ordered[at:], len(ordered), least, span_of(words, threshold)) for at, w in enumerate(ordered[: len(ordered) - least + 1])]
    if not probes:
        return spark.createDataFrame([], "doc_id long, label string, containment double")
    index = F.broadcast(spark.createDataFrame(probes, "label string, token string, rest array<string>, size int, least int, span int"))  # as large as the templates
    tokens, reach = sorted({p[1] for p in probes}), max(p[5] for p in probes)

    def around(hits: Column) -> Column:
        near = lambda k: F.slice(hits, F.greatest(k + 1 - reach, F.lit(1)), 2 * reach)
        return F.filter(F.transform(hits, lambda x, k: F.when(x["w"].isin(*tokens), F.struct(x["at"].alias("at"), x["w"].alias("token"), near(k).alias("near")))), lambda x: x.isNotNull())

    probing = places.select("doc_id", F.explode(around(F.col("hits"))).alias("p")).select("doc_id", "p.*").join(index, "token")
    # Positional filter: of the template's words only those from the probing one on count, as rarer ones probe for themselves.
    own = F.filter("near", lambda x: (F.abs(x["at"] - F.col("at")) < F.col("span")) & F.array_contains("rest", x["w"]))
    candidates = probing.withColumn("own", own).where(F.size("own") >= F.col("least"))
    starts = F.filter("own", lambda x: x["at"] <= F.col("at"))
    held = lambda a: F.size(F.array_distinct(F.transform(F.filter("own", lambda y: (y["at"] >= a) & (y["at"] < a + F.col("span"))), lambda y: y["w"])))
    overlaps = candidates.withColumn("both", F.array_max(F.transform(starts, lambda x: held(x["at"])))).where("both >= least")
    return overlaps.groupBy("doc_id", "label").agg(F.max(F.col("both") / F.col("size")).alias("containment"))


def phrase_places(hits: Column, phrase: tuple[str, ...]) -> Column:
    """Positions (from 0) at which the phrase's words stand one after another. Neighbouring words of the vocabulary are neighbouring hits."""

    def follows(k: Column) -> Column:
        out = F.lit(True)
        for j, w in enumerate(phrase):
            x = F.get(hits, k + j)
            out = out & F.coalesce((x["w"] == w) & (x["at"] == F.get(hits, k)["at"] + j), F.lit(False))
        return out

    found = F.filter(F.transform(hits, lambda x, k: F.when((x["w"] == phrase[0]) & follows(k), x["at"])), lambda x: x.isNotNull())
    return F.transform(found, lambda i: i.cast("long"))


def scan(docs: DataFrame, templates: Mapping[str, tuple[str, ...]] = TEMPLATES, threshold: float = 0.8, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score`` of every document with an id.

    Base labels come from the places of PHRASES; ``labels`` adds those of matching templates. ``score`` is 1 with a base
    mention, else the best containment, else 0. Empty and null texts have no words and no labels; an empty table gives an
    empty result, and rows with a null id are not in it.
    """
    words = {w for texts in templates.values() for t in texts for w in template_words(t)} | {w for p in PHRASES.values() for w in p}
    places = materialize(word_places(docs, sorted(words), id_col, text_col), "places").df
    named = places.select("doc_id", "n_words", *[phrase_places(F.col("hits"), phrase).alias(f"at_{k}") for k, phrase in PHRASES.items()])
    every = F.flatten(F.array(*[F.col(f"at_{k}") for k in PHRASES]))
    base = F.filter(F.array(*[F.when(F.size(f"at_{k}") > 0, F.lit(k)) for k in sorted(PHRASES)]), lambda x: x.isNotNull())
    based = named.select("doc_id", "n_words", F.size(every).cast("long").alias("n_base"), F.array_min(every).alias("first_word"), F.array_max(every).alias("last_word"), base.alias("base"))
    found = template_matches(places, templates, threshold).groupBy("doc_id").agg(F.collect_set("label").alias("found"), F.max("containment").alias("best"))
    none = F.array().cast("array<string>")
    return based.join(found, "doc_id", "left").select(
        "doc_id", "n_words", "n_base", "first_word", "last_word",
        F.array_join("base", ",").alias("base_labels"),
        F.array_join(F.array_sort(F.array_union("base", F.coalesce("found", none))), ",").alias("labels"),
        F.when(F.col("n_base") > 0, 1.0).otherwise(F.coalesce("best", F.lit(0.0))).alias("score"),
    )
