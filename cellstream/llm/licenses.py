"""License scan: exact set-similarity join of text blocks with licence templates, by DataFrame functions alone.

A block is one line of a text; its set is its distinct words. A template meets a block when at least
`THRESHOLD` of the template's distinct words are in the block (containment of the template). Words are put
in one global order, the rarest in the corpus first. For a template of size s, need = ceil(THRESHOLD * s):

* length filter: a block with fewer than `need` template-vocabulary words cannot meet it;
* prefix filter: a pair that meets it shares a word among the first (size - need + 1) of both sides;
* positional filter: from the first shared word on, at least `need` words must be left on both sides;
* what is left is verified on the full sets.

The filters only skip pairs that cannot meet the threshold, so the result does not depend on the order.
Templates are a fixed list, so they travel as a literal; texts are never shuffled. The one exchange is the
count of template words over the corpus, at most one row per template word and task.

Defined results: null and empty texts have no word and no label; repeated rows each get their own row;
columns beyond doc_id and text are not read.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import lower_ascii

SEPARATORS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
THRESHOLD = 0.9

# The phrases that count as places, and their labels.
PHRASES = {
    "gnu general public license": "gpl",
    "apache license": "apache",
    "cc by": "cc-by",
    "mit license": "mit",
}

# The notices that public licences ask for, and our labels of them.
TEMPLATES = [
    ("gpl-notice", "this work is licensed under the gnu general public license"),
    ("gpl-notice", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation"),
    ("lgpl-notice", "this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation"),
    ("apache-notice", "licensed under the apache license version 2 0"),
    ("apache-notice", "you may not use this file except in compliance with the license you may obtain a copy of the license at http www apache org licenses license 2 0"),
    ("mit-notice", "released under the mit license"),
    ("mit-notice", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files"),
    ("bsd-notice", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met"),
    ("cc-by-nc-notice", "licensed under cc by nc 4 0"),
    ("cc-by-sa-notice", "licensed under cc by sa 4 0"),
    ("cc-by-notice", "this work is licensed under a creative commons attribution 4 0 international license"),
    ("mpl-notice", "this source code form is subject to the terms of the mozilla public license v 2 0"),
    ("isc-notice", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted"),
    ("public-domain-notice", "this is free and unencumbered software released into the public domain"),
]


def words(lowered: Column) -> Column:
    return F.array_remove(F.split(lowered, SEPARATORS), "")


def need(size: int, threshold: float = THRESHOLD) -> int:
    return max(1, math.ceil(threshold * size - 1e-9))


def word_order(docs: DataFrame, vocabulary: list[str]) -> list[str]:
    """The vocabulary, rarest first; frequency is the number of documents that hold the word."""
    lowered = lower_ascii(F.col("text"))
    found = docs.select(F.explode(F.array_intersect(words(lowered), F.array(*map(F.lit, vocabulary)))).alias("w"))
    counts = dict(found.groupBy("w").count().collect())  # one row per template word at most
    return sorted(vocabulary, key=lambda w: (counts.get(w, 0), w))


def places(w: Column, phrase: list[str]) -> Column:
    """Start positions of the phrase in the word array w, from 0."""
    k = len(phrase)
    rare = F.lit("cc" if "cc" in phrase else "license")
    match = lambda i: F.get(w, i) == phrase[0]

    def whole(i):
        out = match(i)
        for j in range(1, k):
            out = out & (F.get(w, i + j) == phrase[j])
        return out

    empty = F.array().cast("array<int>")
    return F.when(F.array_contains(w, rare) & (F.size(w) >= k), F.filter(F.sequence(F.lit(0), F.size(w) - k), whole)).otherwise(empty)


def scan(docs: DataFrame, templates=TEMPLATES, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score for every row of docs.

    score is 1 where a base phrase stands, else the largest containment of a template that meets the
    threshold, else 0. labels also names the templates met.
    """
    docs = docs.select("doc_id", "text")
    sets = [(label, sorted(set(text.split()))) for label, text in templates]
    order = word_order(docs, sorted({w for _, s in sets for w in s}))
    rank = {w: i for i, w in enumerate(order)}
    sets = [(label, sorted(s, key=rank.get)) for label, s in sets]
    prefix = lambda s: s[: len(s) - need(len(s), threshold) + 1]
    strings = lambda s: F.array(*map(F.lit, s))
    probe = strings(sorted({w for _, s in sets for w in prefix(s)}))
    known = strings(order)
    index = F.array(*[F.struct(F.lit(label).alias("label"), strings(s).alias("words"), strings(prefix(s)).alias("prefix"), F.lit(need(len(s), threshold)).alias("need")) for label, s in sets])

    def meets(block: Column, t: Column) -> Column:
        shared = F.array_intersect(F.slice(block, F.lit(1), F.greatest(F.size(block) - t["need"] + 1, F.lit(0))), t["prefix"])
        first = F.get(shared, 0)
        left = F.least(F.size(block) - F.array_position(block, first), F.size(t["words"]) - F.array_position(t["words"], first))
        return (F.size(block) >= t["need"]) & (F.size(shared) > 0) & (left + 1 >= t["need"]) & (F.size(F.array_intersect(block, t["words"])) >= t["need"])

    def hits(block: Column) -> Column:
        return F.transform(F.filter(index, lambda t: meets(block, t)), lambda t: F.struct(t["label"].alias("label"), (F.size(F.array_intersect(block, t["words"])) / F.size(t["words"])).alias("share")))

    low = docs.select("doc_id", lower_ascii(F.col("text")).alias("low"))
    w = low.select("doc_id", "low", words(F.col("low")).alias("w"))
    empty = F.array().cast("array<struct<label:string,share:double>>")
    blocks = F.filter(F.transform(F.split(F.col("low"), "\n", -1), words), lambda b: F.arrays_overlap(b, probe))
    joined = F.flatten(F.transform(blocks, lambda b: hits(F.array_intersect(known, b))))
    found = w.select(
        "doc_id",
        F.size("w").cast("long").alias("n_words"),
        *[places(F.col("w"), p.split()).alias(f"at{i}") for i, p in enumerate(PHRASES)],
        F.when(F.arrays_overlap("w", probe), joined).otherwise(empty).alias("hits"),
    )
    at = F.concat(*[F.col(f"at{i}") for i in range(len(PHRASES))])
    base = F.filter(F.array(*[F.when(F.size(f"at{i}") > 0, F.lit(label)) for i, label in enumerate(PHRASES.values())]), lambda x: x.isNotNull())
    return found.select(
        "doc_id",
        "n_words",
        F.size(at).cast("long").alias("n_base"),
        F.array_min(at).cast("long").alias("first_word"),
        F.array_max(at).cast("long").alias("last_word"),
        F.array_join(F.array_sort(F.array_distinct(base)), ",").alias("base_labels"),
        F.array_join(F.array_sort(F.array_union(base, F.transform("hits", lambda h: h["label"]))), ",").alias("labels"),
        F.when(F.size(at) > 0, F.lit(1.0)).otherwise(F.coalesce(F.array_max(F.transform("hits", lambda h: h["share"])), F.lit(0.0))).alias("score"),
    )


def oracle(templates=TEMPLATES, threshold: float = THRESHOLD) -> str:
    """The same rows by comparing every line with every template."""
    pattern = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
    quoted = lambda s: "[" + ", ".join(f"'{w}'" for w in s) + "]"
    rows = ",\n".join(f"('{label}', {quoted(s)}, {need(len(s), threshold)})" for label, s in [(a, sorted(set(b.split()))) for a, b in templates])
    place = lambda p: "list_filter(range(len(w)), lambda i: " + " AND ".join(f"w[i + {j + 1}] = '{x}'" for j, x in enumerate(p.split())) + ")"
    cases = ", ".join(f"{place(p)} AS p{i}" for i, p in enumerate(PHRASES))
    base = ", ".join(f"CASE WHEN len(p{i}) > 0 THEN '{label}' END" for i, label in enumerate(PHRASES.values()))
    allp = "p0 || p1 || p2 || p3"
    return f"""
WITH low AS (SELECT row_number() OVER () AS r, doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS t FROM documents),
templates(label, s, need) AS (VALUES {rows}),
words AS (SELECT r, doc_id, regexp_extract_all(t, '{pattern}') AS w FROM low),
placed AS (SELECT r, doc_id, len(w) AS n_words, {cases} FROM words),
lines AS (SELECT r, list_distinct(regexp_extract_all(line, '{pattern}')) AS b FROM (SELECT r, unnest(string_split(t, chr(10))) AS line FROM low)),
hits AS (SELECT r, list(label) AS met, max(len(list_intersect(b, s)) / len(s)) AS share FROM lines JOIN templates ON len(list_intersect(b, s)) >= need GROUP BY r)
SELECT doc_id, n_words, len({allp}) AS n_base, list_min({allp}) AS first_word, list_max({allp}) AS last_word,
  array_to_string(list_sort(list_distinct([{base}])), ',') AS base_labels,
  array_to_string(list_sort(list_distinct([{base}] || coalesce(met, []))), ',') AS labels,
  CASE WHEN len({allp}) > 0 THEN 1.0::DOUBLE ELSE coalesce(share, 0.0)::DOUBLE END AS score
FROM placed LEFT JOIN hits USING (r)
"""
