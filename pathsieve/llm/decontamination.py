"""Benchmark decontamination over a distributed positional inverted index.

Terms are words; a window is ten consecutive words of a benchmark item (all of them
where an item has fewer). The index holds the postings (document, position) of the
terms that windows are looked up by: of each window the two rarest, by their counts over
all training documents. A posting, moved back by the term's place in the window, names a
start; a start that the lists of both terms name is a candidate, and the document's own
words confirm it.

Everything is DataFrame operations. Terms of the benchmark are broadcast only while
there are few (`SMALL` windows); beyond that the same joins shuffle, and the largest
keys are split by the engine.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathsieve.llm.shared import cut, masked, own_columns, sha256_hex
from pathsieve.llm.words import lower_word, with_words, words, words_as_written

WINDOW, SMALL = 10, 100_000


def keyed(docs: DataFrame) -> DataFrame:
    """(doc_id, text, key): rows of one doc_id and one text share a key, others don't."""
    return own_columns(docs, "doc_id", "text").withColumn("key", F.concat_ws(":", F.coalesce(F.col("doc_id").cast("string"), F.lit("null")), F.hex(F.xxhash64(F.coalesce("text", F.lit(""))))))


def windows(benchmark: DataFrame, size: int = WINDOW) -> DataFrame:
    """(window_id, words, items): each distinct window with the ids of the items that hold it. An item without words has none; a null item_id is the id ''."""
    items = own_columns(benchmark, "item_id", "text").select(F.coalesce(F.col("item_id").cast("string"), F.lit("")).alias("item"), words(F.col("text")).alias("w")).where(F.size("w") > 0)
    starts = F.sequence(F.lit(1), F.greatest(F.size("w") - F.lit(size - 1), F.lit(1)))
    each = items.select("item", F.explode(F.transform(starts, lambda k: F.slice("w", k, size))).alias("words"))
    return each.groupBy("words").agg(F.array_sort(F.collect_set("item")).alias("items")).withColumn("window_id", F.xxhash64("words"))


def _perhaps_broadcast(df: DataFrame, few: bool) -> DataFrame:
    return F.broadcast(df) if few else df


def anchors(docs: DataFrame, found: DataFrame, few: bool, per_window: int = 2) -> DataFrame:
    """(window_id, term, place, nth, needed): the rarest terms of each window, rarest first; place counts from 0."""
    terms = found.select("window_id", F.posexplode("words").alias("place", "term"))
    vocabulary = terms.select("term").distinct()
    seen = with_words(docs, [], F.coalesce("text", F.lit(""))).select(F.explode_outer("w").alias("word")).select(lower_word(F.col("word")).alias("term")).join(_perhaps_broadcast(vocabulary, few), "term", "left_semi").groupBy("term").agg(F.count(F.lit(1)).alias("n"))
    ranked = terms.join(seen, "term", "left").groupBy("window_id", "term").agg(F.min("place").alias("place"), F.min(F.coalesce("n", F.lit(0))).alias("n"))
    best = ranked.groupBy("window_id").agg(F.slice(F.array_sort(F.collect_list(F.struct("n", "term", "place"))), 1, per_window).alias("best"))  # a window has ten terms at most
    return best.select("window_id", F.size("best").alias("needed"), F.posexplode("best").alias("nth", "b")).select("window_id", "needed", "nth", "b.term", "b.place", "b.n")


def postings(docs: DataFrame, terms: DataFrame, few: bool) -> DataFrame:
    """(key, term, position) of the given terms, positions from 0, over whole texts."""
    return with_words(docs, ["key"], F.coalesce("text", F.lit(""))).select("key", F.posexplode_outer("w").alias("position", "word")).select("key", "position", lower_word(F.col("word")).alias("term")).join(_perhaps_broadcast(terms.select("term").distinct(), few), "term", "left_semi")


def candidates(index: DataFrame, chosen: DataFrame, few: bool) -> DataFrame:
    """(key, window_id, start) where the offset-adjusted lists of all chosen terms of a window meet."""
    placed = index.join(_perhaps_broadcast(chosen.select("window_id", "term", "place", "nth", "needed"), few), "term").select("key", "window_id", (F.col("position") - F.col("place")).alias("start"), "nth", "needed").where("start >= 0")
    return placed.groupBy("key", "window_id", "start").agg(F.expr("bit_or(shiftleft(1, nth)) AS named"), F.max("needed").alias("needed")).where("named = shiftleft(1, needed) - 1").select("key", "window_id", "start")


def exact_hits(docs: DataFrame, benchmark: DataFrame, size: int = WINDOW) -> DataFrame:
    """Each row of docs as (doc_id, key, n_words, hits): hits is an array of (start, stop, items), empty for most."""
    docs = keyed(docs)
    found = cut(windows(benchmark, size))
    few = found.count() <= SMALL
    chosen = cut(anchors(docs, found, few))
    at = candidates(postings(docs, chosen, few), chosen, few).join(_perhaps_broadcast(found, few), "window_id")
    at = at.groupBy("key").agg(F.collect_list(F.struct("start", "words", "items")).alias("maybe"))
    joined = docs.join(at, "key", "left").select("doc_id", "key", words_as_written(F.col("text")).alias("w"), "maybe")
    real = F.filter("maybe", lambda c: F.transform(F.slice("w", c["start"] + 1, F.size(c["words"])), lower_word) == c["words"])
    hits = F.transform(real, lambda c: F.struct(c["start"].alias("start"), (c["start"] + F.size(c["words"])).alias("stop"), c["items"].alias("items")))
    return joined.select("doc_id", "key", F.size("w").cast("long").alias("n_words"), F.when(F.col("maybe").isNotNull(), hits).alias("hits"))


def covered(hits: Column) -> Column:
    """Words inside any hit."""
    zero = F.struct(F.lit(0).alias("end"), F.lit(0).cast("long").alias("total"))
    step = lambda acc, h: F.struct(F.greatest(acc["end"], h["stop"]).alias("end"), (acc["total"] + F.greatest(h["stop"] - F.greatest(h["start"], acc["end"]), F.lit(0))).alias("total"))
    return F.aggregate(F.array_sort(hits), zero, step, lambda acc: acc["total"])


def contamination(docs: DataFrame, benchmark: DataFrame, size: int = WINDOW) -> DataFrame:
    """A row for each row of docs: (doc_id, n_words, n_hit, n_items, items_sha256, contaminated).

    A null or empty text has no words and no hits; repeated rows give equal rows; an empty
    benchmark contaminates nothing. Columns other than doc_id, text and item_id are not read.
    """
    rows = exact_hits(docs, benchmark, size)
    items = F.coalesce(F.array_sort(F.array_distinct(F.flatten(F.transform("hits", lambda h: h["items"])))), F.array().cast("array<string>"))
    rows = rows.select("doc_id", "n_words", F.coalesce(F.when(F.size("hits") > 0, covered(F.col("hits"))), F.lit(0)).cast("long").alias("n_hit"), items.alias("items"))
    return rows.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), sha256_hex(F.array_join("items", ",")).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))


def without_contaminated(docs: DataFrame, benchmark: DataFrame, size: int = WINDOW) -> DataFrame:
    """The rows of docs, all columns, that hold no window of the benchmark. Null and empty texts hold none; repeated rows stay or go together."""
    docs, named = masked(docs, "doc_id", "text")
    hit = exact_hits(docs, benchmark, size).where(F.size("hits") > 0).select(F.col("key").alias("hit_key")).distinct()
    key = F.concat_ws(":", F.coalesce(F.col("doc_id").cast("string"), F.lit("null")), F.hex(F.xxhash64(F.coalesce("text", F.lit("")))))
    return named(docs.join(hit, key == F.col("hit_key"), "left_anti"))


def proximity_matches(docs: DataFrame, phrases: DataFrame, distance: int) -> DataFrame:
    """(doc_id, item, first, last): places where the two rarest terms of an item stand at most `distance` words apart, in any order; an item of one term matches each place of it.

    phrases: (item_id, text). The pairs of a document are those of positions within the
    distance: both lists are cut into stripes of that width, and only equal and adjacent
    stripes meet.
    """
    docs = keyed(docs)
    items = own_columns(phrases, "item_id", "text").select(F.coalesce(F.col("item_id").cast("string"), F.lit("")).alias("window_id"), words(F.col("text")).alias("words")).where(F.size("words") > 0)
    few = items.count() <= SMALL
    chosen = cut(anchors(docs, items, few))
    index = postings(docs, chosen, few).join(_perhaps_broadcast(chosen, few), "term").select("key", "window_id", "nth", "needed", "position", F.expr(f"position div {distance + 1}").alias("stripe"))
    one = index.where("needed = 1").select("key", "window_id", F.col("position").alias("first"), F.col("position").alias("last"))
    left = index.where("needed = 2 AND nth = 0").select("key", "window_id", "position", F.explode(F.array([F.col("stripe") + k for k in (-1, 0, 1)])).alias("stripe"))
    right = index.where("needed = 2 AND nth = 1").select("key", "window_id", F.col("position").alias("other"), "stripe")
    two = left.join(right, ["key", "window_id", "stripe"]).where(F.abs(F.col("position") - F.col("other")) <= distance).select("key", "window_id", F.least("position", "other").alias("first"), F.greatest("position", "other").alias("last"))
    found = one.unionByName(two)
    return found.join(docs.select("key", "doc_id").distinct(), "key").select("doc_id", F.col("window_id").alias("item"), "first", "last")
