"""License scans: an exact set-similarity join of text blocks with license templates.

A block is a line, or up to `WRAPPED` lines in a row that are wrapped (none blank, none
longer than `WRAP` characters), so that a notice broken over lines is one block. A
template is found in a block that holds at least `threshold` of its distinct words. The
join is exact: words are ordered by the number of documents that hold them, rarest
first. A document whose words can't reach any template's threshold is left out at once.
Of each template only the prefix is indexed, which every block that meets the threshold
must touch; blocks with fewer template words than any template asks for are left out
(length filter), and a touched word's place in both orders bounds the overlap that can
still come (positional filter). What is left is intersected.

Beside it stand the plain phrases: places where a phrase's words stand in a row.
Everything is DataFrame operations; templates and phrases are parameters of fixed size.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathsieve.llm.shared import cut, own_columns
from pathsieve.llm.words import words, words_for_ascii

THRESHOLD = 0.9
#: Lines in one block, where each has at most so many characters.
WRAPPED, WRAP = 4, 120

# Phrases and their labels.
PHRASES = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}

# Short public license notices and their labels.
TEMPLATES = {
    "apache-2.0": "Licensed under the Apache License, Version 2.0",
    "apache-2.0-header": "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License",
    "bsd": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met",
    "cc-by-4.0": "This work is licensed under a Creative Commons Attribution 4.0 International License",
    "cc-by-nc-4.0": "Licensed under CC BY-NC 4.0",
    "cc-by-sa-4.0": "Licensed under CC BY-SA 4.0",
    "cc0-1.0": "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work",
    "gpl-3.0": "This work is licensed under the GNU General Public License, version 3",
    "gpl-header": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation",
    "lgpl": "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License",
    "mit": "Released under the MIT License",
    "mit-permission": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files",
    "mpl-2.0": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0",
    "reserved-notice": "Copyright, all rights reserved",
}


def keyed(docs: DataFrame) -> DataFrame:
    """(doc_id, text, key): rows of one doc_id and one text share a key, and get equal results."""
    return own_columns(docs, "doc_id", "text").withColumn("key", F.concat_ws(":", F.coalesce(F.col("doc_id").cast("string"), F.lit("null")), F.hex(F.xxhash64(F.coalesce("text", F.lit(""))))))


def words_against(text: Column, sought: list[str]) -> Column:
    """Words of the text, exact as far as it matters for the words sought."""
    return words_for_ascii(text) if all(w.isascii() for w in sought) else words(text)


def template_sets(spark, templates: dict[str, str]) -> DataFrame:
    """(label, terms): distinct words."""
    rows = spark.createDataFrame(sorted(templates.items()), "label string, text string")
    return rows.select("label", F.array_distinct(words(F.col("text"))).alias("terms")).where(F.size("terms") > 0)


def blocks_of(lines: Column) -> Column:
    """Array of the blocks of a text, given as a column of its lines: its lines, then every row of 2 to WRAPPED wrapped lines that can't be longer by a line after it (shorter rows hold no more words)."""
    fits = lambda x: (F.char_length(x) <= WRAP) & (F.trim(x) != "")
    row = lambda k: F.slice(lines, k + 1, WRAPPED)
    # a row ends before its first line that doesn't fit
    length = lambda r: F.aggregate(r, F.struct(F.lit(0).alias("n"), F.lit(True).alias("on")), lambda a, x: F.struct(F.when(a["on"] & fits(x), a["n"] + 1).otherwise(a["n"]).alias("n"), (a["on"] & fits(x)).alias("on")), lambda a: a["n"])
    rows = F.transform(F.sequence(F.lit(0), F.size(lines) - 1), lambda k: F.array_join(F.slice(row(k), 1, F.when(length(row(k)) > 1, length(row(k))).otherwise(0)), "\n"))
    return F.concat(lines, F.filter(rows, lambda x: x != ""))


def similar_blocks(docs: DataFrame, templates: dict[str, str] = TEMPLATES, threshold: float = THRESHOLD) -> DataFrame:
    """(key, block, label, containment): every block that holds at least `threshold` of a template's distinct words. docs: (key, text); rows of one key are one text. Lines are counted from 0, rows of wrapped lines after them."""
    spark = docs.sparkSession
    sets = {r["label"]: r["terms"] for r in template_sets(spark, templates).collect()}  # the templates given
    if not sets:
        return docs.select("key", F.lit(0).alias("block"), F.lit("").alias("label"), F.lit(0.0).alias("containment")).limit(0)
    vocabulary = sorted({w for terms in sets.values() for w in terms})
    needs = {label: max(1, math.ceil(threshold * len(terms) - 1e-9)) for label, terms in sets.items()}
    words_held = lambda text: F.array_intersect(words_against(text, vocabulary), F.array(*map(F.lit, vocabulary)))
    several = docs.select(words_held(F.col("text")).alias("held"))
    order = {r["term"]: r["n"] for r in several.select(F.explode_outer("held").alias("term")).where("term IS NOT NULL").groupBy("term").agg(F.count(F.lit(1)).alias("n")).collect()}  # words of the templates only
    rank = {w: k for k, w in enumerate(sorted(vocabulary, key=lambda w: (order.get(w, 0), w)))}
    prefixes = []
    for label, terms in sets.items():
        ordered = sorted(terms, key=rank.__getitem__)
        prefixes += [(w, label, k, len(terms), needs[label]) for k, w in enumerate(ordered[: len(terms) - needs[label] + 1])]
    reach = F.lit(False)
    for label, terms in sets.items():
        reach = reach | (F.size(F.array_intersect("held", F.array(*map(F.lit, terms)))) >= needs[label])
    # arrays of one element are exploded so that the engine evaluates words and lines once a text, not at every use in a filter or lambda
    some = docs.select("key", "text", F.explode(F.array(words_held(F.col("text")))).alias("held")).where(reach)
    some = some.select("key", F.explode(F.array(F.split(F.coalesce("text", F.lit("")), "\n"))).alias("lines"))
    blocks = some.select("key", F.posexplode_outer(blocks_of(F.col("lines"))).alias("block", "line")).select("key", "block", words_against(F.col("line"), vocabulary).alias("w"))
    touching = blocks.where(F.arrays_overlap("w", F.array(*[F.lit(w) for w in sorted({p[0] for p in prefixes})])))  # prefix filter
    held = touching.select("key", "block", F.array_intersect("w", F.array(*map(F.lit, vocabulary))).alias("held"))
    index = spark.createDataFrame(prefixes, "term string, label string, template_place int, template_size int, need int")
    ranks = spark.createDataFrame(list(rank.items()), "term string, rank int")
    full = spark.createDataFrame(list(sets.items()), "label string, terms array<string>")
    kept = held.where(F.size("held") >= min(needs.values()))  # length filter
    # a set: rows of one key, and so of one text, count once
    ranked = kept.select("key", "block", "held", F.explode("held").alias("term")).join(F.broadcast(ranks), "term").groupBy("key", "block").agg(F.first("held").alias("held"), F.array_sort(F.collect_set(F.struct("rank", "term"))).alias("ordered"))
    touched = ranked.select("key", "block", "held", F.posexplode("ordered").alias("block_place", "o")).select("key", "block", "held", "block_place", F.col("o.term").alias("term")).join(F.broadcast(index), "term")
    may = F.least(F.col("template_size") - F.col("template_place"), F.size("held") - F.col("block_place"))  # positional filter: the first word in common and what follows it
    maybe = touched.where((F.size("held") >= F.col("need"))).groupBy("key", "block", "label", "template_size", "need").agg(F.first("held").alias("held"), F.max(may).alias("most")).where("most >= need")
    common = F.size(F.array_intersect("held", "terms"))
    return maybe.join(F.broadcast(full), "label").withColumn("common", common).where("common >= need").select("key", "block", "label", (F.col("common") / F.col("template_size")).alias("containment"))


def phrase_starts(w: Column, phrase: str) -> Column:
    """Word indexes, from 0, where the phrase's words stand in a row; only arrays that hold all its words are searched."""
    parts = phrase.split()
    holds = F.lit(True)
    for p in parts:
        holds = holds & F.array_contains(w, p)
    at = F.filter(F.sequence(F.lit(0), F.greatest(F.size(w) - len(parts), F.lit(0))), lambda k: F.slice(w, k + 1, len(parts)) == F.array(*map(F.lit, parts)))
    return F.when(holds & (F.size(w) >= len(parts)), at).otherwise(F.array().cast("array<int>"))


def scan(docs: DataFrame, phrases: dict[str, str] = PHRASES, templates: dict[str, str] = TEMPLATES, threshold: float = THRESHOLD) -> DataFrame:
    """A row for each row of docs: (doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score).

    score: the largest containment of a template in a block of the document, 1 where a
    phrase stands; 0 if neither. Null and empty texts have no words, no labels, score 0;
    repeated rows give equal rows. Other columns of docs are not read.
    """
    docs = keyed(docs)
    similar = cut(similar_blocks(docs, templates, threshold).groupBy("key").agg(F.collect_set("label").alias("similar"), F.max("containment").alias("containment")))
    w = docs.select("doc_id", "key", words_against(F.col("text"), list(phrases)).alias("w"))
    base = w.select("doc_id", "key", F.size("w").cast("long").alias("n_words"), *[phrase_starts(F.col("w"), p).alias(f"at{k}") for k, p in enumerate(phrases)])
    places = F.concat(*[F.col(f"at{k}") for k in range(len(phrases))])
    labels = F.filter(F.array(*[F.when(F.size(f"at{k}") > 0, F.lit(label)) for k, label in enumerate(phrases.values())]), lambda x: x.isNotNull())
    rows = base.select("doc_id", "key", "n_words", places.alias("places"), F.array_sort(F.array_distinct(labels)).alias("base")).join(similar, "key", "left")
    every = F.array_sort(F.array_distinct(F.concat("base", F.coalesce("similar", F.array().cast("array<string>")))))
    return rows.select(
        "doc_id", "n_words", F.size("places").cast("long").alias("n_base"), F.array_min("places").cast("long").alias("first_word"), F.array_max("places").cast("long").alias("last_word"),
        F.array_join("base", ",").alias("base_labels"), F.array_join(every, ",").alias("labels"), F.when(F.size("places") > 0, F.lit(1.0)).otherwise(F.coalesce("containment", F.lit(0.0))).alias("score"),
    )
