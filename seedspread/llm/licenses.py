"""License scan: phrase labels plus an exact set-similarity join of text blocks against license templates.

A template has a sentence, the words that make it that license (``marks``) and words that make it another one
(``bars``). A block is a window of words around a place where one of the template's anchors stands: its first mark
and so many of its longest words that whatever meets the threshold holds one of them. It has as many words on
either side as the sentence has, across line breaks. A template is met where a block holds all marks, no bar and at
least ``threshold`` of the sentence's distinct words (containment). Marks are names; a sentence that is told by its
wording alone has none.

Template words are put in one global order, rarest first, by the number of documents of the scanned corpus that
hold them. A block that meets n words at threshold t misses at most ``n - ceil(t n)`` of them, so it holds one of
the first ``n - ceil(t n) + 1`` (prefix filter); it has at least ``ceil(t n)`` distinct words (length filter); and
from its own first prefix word on, in the global order, it holds at least ``ceil(t n)`` words that the sentence could
share (positional filter: before that word the two share nothing). Survivors are verified, so the join is exact.

One pass over the texts counts, finds places and cuts blocks, which are rare; it is written, so that the words'
counts and the join read no text again. DataFrame functions only; templates are a parameter with a checked size.

Cases: null and empty texts have no words, no places and no labels; repeated rows give repeated results; an
empty table gives an empty result; places that overlap all count.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from seedspread.llm.text import words
from seedspread.runtime import materialize

# Phrases of the base scan and their labels.
PHRASES = {
    "gnu general public license": "gpl",
    "apache license": "apache",
    "cc by": "cc-by",
    "mit license": "mit",
}

# Sentences of common license notices by label, with their marks and bars.
TEMPLATES = [
    ("gpl", "this work is licensed under the gnu general public license version 3", "gnu general", "lesser"),
    ("gpl", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation", "gnu general", "lesser"),
    ("lgpl", "this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation", "lesser gnu", ""),
    ("apache", "licensed under the apache license version 2 0", "apache", ""),
    ("apache", "licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license", "apache", ""),
    ("mit", "released under the mit license", "mit", ""),
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files to deal in the software without restriction", "", ""),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met", "", ""),
    ("mpl", "this source code form is subject to the terms of the mozilla public license v 2 0", "mozilla", ""),
    ("cc-by", "this work is licensed under a creative commons attribution 4 0 international license", "creative commons attribution", "noncommercial sharealike"),
    ("cc-by-nc", "licensed under cc by nc 4 0", "nc cc by", ""),
    ("cc-by-sa", "licensed under cc by sa 4 0", "sa cc by", ""),
    ("unlicense", "this is free and unencumbered software released into the public domain", "unencumbered", ""),
]

#: Hundredths of a sentence's distinct words that a block must hold.
PERCENT = 80
MAX_TEMPLATE_WORDS = 20_000


def _starts(w: Column, phrase: str) -> Column:
    """All positions at which the words of ``phrase`` stand one after another."""
    parts = phrase.split(" ")
    here = lambda i: F.forall(F.array(*[F.struct(F.lit(p).alias("p"), F.lit(k).alias("k")) for k, p in enumerate(parts)]), lambda x: F.get(w, i + x["k"]) == x["p"])
    return F.filter(F.transform(w, lambda x, i: F.when(x == parts[0], i)), lambda i: i.isNotNull() & here(i))


def word_ranks(present: DataFrame, vocabulary: list[str]) -> dict[str, int]:
    """Rank of each template word, rarest first, by document frequency; ``present(vocabulary)`` lists a row's template words.

    Only words of the vocabulary are counted, so the result has at most that many rows.
    """
    seen = present.select(F.explode("vocabulary").alias("word"))
    counts = {r["word"]: r["n"] for r in seen.groupBy("word").agg(F.count("*").alias("n")).collect()}
    return {word: i for i, word in enumerate(sorted(vocabulary, key=lambda x: (counts.get(x, 0), x)))}


def _texts(found: list[str]) -> Column:
    return F.array(*map(F.lit, found)) if found else F.array().cast("array<string>")


def _split(words_: str) -> list[str]:
    return words_.split(" ") if words_ else []


def needed(n: int, percent: int) -> int:
    """Smallest number of n words that meets the threshold."""
    return -(-percent * n // 100)


def anchors(template: tuple[str, str, str, str], percent: int = PERCENT) -> list[str]:
    """Words of which every block that meets the template holds one: at least ``n - need + 1`` of its n distinct words."""
    _, sentence, marks, _ = template
    own = sorted(set(sentence.split(" ")), key=lambda x: (-len(x), x))
    return sorted({*_split(marks)[:1], *own[: len(own) - needed(len(own), percent) + 1]})


def cut_blocks(template: tuple[str, str, str, str], percent: int = PERCENT) -> Column:
    """Distinct words of every block of the columns ``w`` and ``joined`` for one template."""
    reach, around = len(template[1].split(" ")), anchors(template, percent)
    at = F.filter(F.transform("w", lambda x, i: F.when(x.isin(around), i)), lambda i: i.isNotNull())
    block = lambda i: F.array_distinct(F.slice("w", F.greatest(i - reach, F.lit(0)) + 1, i + reach + 1 - F.greatest(i - reach, F.lit(0))))
    stands = F.lit(False)
    for x in around:
        stands = stands | F.contains("joined", F.lit(x))
    for x in _split(template[2]):
        stands = stands & F.contains("joined", F.lit(x))
    return F.when(stands, F.transform(at, block)).otherwise(F.array().cast("array<array<string>>"))


def met(blocks: Column, template: tuple[str, str, str, str], ranks: dict[str, int], percent: int) -> Column:
    """Containments of the blocks that meet the template, by marks, prefix, length and position, then exactly."""
    _, sentence, marks, bars = template
    ordered = sorted(set(sentence.split(" ")), key=ranks.__getitem__)
    need = needed(len(ordered), percent)
    prefix, whole = ordered[: len(ordered) - need + 1], _texts(ordered)
    shared = lambda b: F.size(F.array_intersect(whole, b))
    # the block's words from its first prefix word on, for each word that can be the first
    later = lambda b: F.coalesce(*[F.when(F.array_contains(b, p), F.size(F.array_intersect(b, _texts(ordered[k:])))) for k, p in enumerate(prefix)], F.lit(0))
    good = lambda b: (
        (F.size(F.array_intersect(b, _texts(_split(marks)))) == len(_split(marks))) & ~F.arrays_overlap(b, _texts(_split(bars)))
        & (F.size(b) >= need) & F.arrays_overlap(b, _texts(prefix)) & (later(b) >= need) & (shared(b) >= need)
    )
    return F.transform(F.filter(blocks, good), lambda b: shared(b) / F.lit(float(len(ordered))))


def license_scan(docs: DataFrame, templates: list[tuple[str, str, str, str]] | None = None, percent: int = PERCENT) -> DataFrame:
    """``docs(doc_id, text)`` → one row per document: words, phrase places, labels and the best containment.

    ``score`` is 1 where a phrase stands, else the best containment of a template that was met, else 0;
    ``n_templates`` counts the templates met.
    """
    templates = TEMPLATES if templates is None else templates
    vocabulary = sorted({x for t in templates for x in t[1].split(" ")})
    if len(vocabulary) > MAX_TEMPLATE_WORDS:
        raise ValueError(f"templates have {len(vocabulary)} words; at most {MAX_TEMPLATE_WORDS} may be inlined")
    marked = docs.select("doc_id", words(F.col("text")).alias("w")).withColumn("joined", F.array_join("w", " "))
    places = {p: F.when(F.contains("joined", F.lit(p)), _starts(F.col("w"), p)).otherwise(F.array().cast("array<int>")) for p in PHRASES}
    found = marked.withColumn("p", F.struct(*[e.alias(f"p{k}") for k, e in enumerate(places.values())]))
    every = F.concat(*[F.col(f"p.p{k}") for k in range(len(PHRASES))])
    labels = F.array_compact(F.array(*[F.when(F.size(f"p.p{k}") > 0, F.lit(label)) for k, label in enumerate(PHRASES.values())]))
    pass_ = materialize(found.select(
        "doc_id", F.size("w").cast("long").alias("n_words"), F.size(every).cast("long").alias("n_base"),
        F.array_min(every).cast("long").alias("first_word"), F.array_max(every).cast("long").alias("last_word"), F.array_sort(F.array_distinct(labels)).alias("base"),
        F.array_intersect("w", _texts(vocabulary)).alias("vocabulary"), *[cut_blocks(t, percent).alias(f"b{k}") for k, t in enumerate(templates)],
    ), "licenses")
    ranks = word_ranks(pass_, vocabulary)
    hits = F.array(*[F.struct(F.lit(t[0]).alias("label"), F.array_max(met(F.col(f"b{k}"), t, ranks, percent)).alias("best")) for k, t in enumerate(templates)])
    any_block = F.lit(False)
    for k in range(len(templates)):
        any_block = any_block | (F.size(f"b{k}") > 0)
    none = F.array().cast("array<struct<label:string,best:double>>")
    held = pass_.withColumn("hits", F.when(any_block, F.filter(hits, lambda h: h["best"].isNotNull())).otherwise(none))
    more = F.transform("hits", lambda h: h["label"])
    return held.select(
        "doc_id", "n_words", "n_base", "first_word", "last_word", F.array_join("base", ",").alias("base_labels"),
        F.array_join(F.array_sort(F.array_distinct(F.concat("base", more))), ",").alias("labels"),
        F.when(F.col("n_base") > 0, F.lit(1.0)).otherwise(F.coalesce(F.array_max(F.transform("hits", lambda h: h["best"])), F.lit(0.0))).alias("score"),
        F.size("hits").cast("long").alias("n_templates"),
    )
