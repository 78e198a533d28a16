"""Document fingerprints: SimHash of weighted term hashes, and permuted block tables.

A term is a pair of neighbouring words (the word itself in a text of one); each
occurrence votes once, so that a term weighs as often as it stands. Every term has a
128-bit hash; a fingerprint bit is set where the votes for it outweigh those against.

Votes are counted in lanes: a long holds eight counters of eight bits, so that 16 plain
sums count all 128 bits over up to 127 terms of a text; those counts are then added up
in lanes of 32 bits. The text is never shuffled by term.

Fingerprints within a Hamming radius r agree on one of r + 1 blocks of their bits at
least, so r + 1 tables, each led by another block, hold every such pair.

Everything is DataFrame operations.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pathsieve.llm.shared import cut, own_columns, sha256_hex
from pathsieve.llm.words import plain_lower, with_words

BITS, RADIUS, ROWS_A_BLOCK, MOST_BLOCKS = 128, 3, 500, 1 << 16
#: Terms that a lane of eight bits can count; the lowest bit of each of eight lanes; the low eight bits of both halves.
_RUN, _OCTETS, _PAIR = 127, 0x0101010101010101, 0x000000FF000000FF


def term_hashes(texts: DataFrame, keys: list[str]) -> DataFrame:
    """(*keys, hashes): an array with the hash of every pair of neighbouring words, or of the only word. All letters are lower-cased."""
    w = with_words(texts, keys, plain_lower(F.col("text")))
    pairs = F.transform(F.slice("w", 1, F.greatest(F.size("w") - 1, F.lit(1))), lambda a, k: F.xxhash64(a, F.get("w", k + 1)))
    return w.select(*keys, F.when(F.size("w") > 0, pairs).otherwise(F.array().cast("array<bigint>")).alias("hashes"))


def fingerprints(texts: DataFrame, keys: list[str]) -> DataFrame:
    """(*keys, high, low) of texts (*keys, text). Rows of equal keys count as one text; a text without words, or null, has fingerprint 0."""
    each = term_hashes(texts, keys).select(*keys, F.posexplode_outer("hashes").alias("at", "h0"))  # outer: the engine would put the whole expression into a filter else
    each = each.select(*keys, F.coalesce(F.expr(f"at div {_RUN}"), F.lit(0)).alias("run"), F.coalesce("h0", F.lit(0)).alias("h0"), F.when(F.col("h0").isNull(), F.lit(0)).otherwise(F.xxhash64("h0")).alias("h1"), F.col("h0").isNotNull().cast("long").alias("one"))
    octets = [F.sum(F.shiftrightunsigned(f"h{k}", b).bitwiseAND(F.lit(_OCTETS))).alias(f"o{k}_{b}") for k in (0, 1) for b in range(8)]
    runs = each.groupBy(*keys, "run").agg(F.sum("one").alias("n"), *octets)
    pairs = [F.sum(F.shiftrightunsigned(f"o{k}_{b}", 8 * j).bitwiseAND(F.lit(_PAIR))).alias(f"s{k}_{b + 8 * j}") for k in (0, 1) for b in range(8) for j in range(4)]
    votes = runs.groupBy(*keys).agg(F.sum("n").alias("n"), *pairs)

    def half(k: int) -> Column:
        parts = []
        for b in range(32):
            low, high = F.col(f"s{k}_{b}").bitwiseAND(F.lit((1 << 32) - 1)), F.shiftrightunsigned(f"s{k}_{b}", 32)
            parts += [F.when(2 * count > F.col("n"), F.lit(1 << at if at < 63 else -(1 << 63))).otherwise(F.lit(0).cast("long")) for count, at in ((low, b), (high, b + 32))]
        return sum(parts[1:], parts[0])  # of different bits

    return votes.select(*keys, half(0).alias("high"), half(1).alias("low"))


def as_text(high: Column, low: Column) -> Column:
    """32 lower-case hex digits."""
    return F.lower(F.concat(*[F.lpad(F.hex(x), 16, "0") for x in (high, low)]))


def likeness(a: tuple[Column, Column], b: tuple[Column, Column]) -> Column:
    """Share of equal bits, 0 to 1."""
    return 1.0 - (F.bit_count(a[0].bitwiseXOR(b[0])) + F.bit_count(a[1].bitwiseXOR(b[1]))) / float(BITS)


def block(high: Column, low: Column, first: int, size: int) -> Column:
    """Bits first .. first + size - 1, counted from the low end; size < 64."""
    mask = F.lit((1 << size) - 1)
    if first + size <= 64:
        return F.shiftrightunsigned(low, first).bitwiseAND(mask)
    if first >= 64:
        return F.shiftrightunsigned(high, first - 64).bitwiseAND(mask)
    return F.shiftrightunsigned(low, first).bitwiseOR(F.shiftleft(high, 64 - first)).bitwiseAND(mask)


def near_pairs(prints: DataFrame, radius: int = RADIUS) -> DataFrame:
    """(high, low, other_high, other_low, distance): every unordered pair of different fingerprints within the radius, once. prints: (high, low), any rows; nulls are left out."""
    if not 1 <= radius < BITS // 2:
        raise ValueError("a radius of 1 to 63")
    edges = [round(k * BITS / (radius + 1)) for k in range(radius + 2)]
    spans = [(a, min(b - a, 62)) for a, b in zip(edges, edges[1:], strict=False)]
    distinct = own_columns(prints, "high", "low").where("high IS NOT NULL AND low IS NOT NULL").distinct()
    lead = F.array(*[F.struct(F.lit(k).alias("led_by"), block(F.col("high"), F.col("low"), *span).alias("lead")) for k, span in enumerate(spans)])
    led = distinct.select("high", "low", F.explode(lead).alias("x")).select("high", "low", "x.led_by", "x.lead")
    other = led.select(F.col("high").alias("other_high"), F.col("low").alias("other_low"), "led_by", "lead")
    apart = F.bit_count(F.col("high").bitwiseXOR(F.col("other_high"))) + F.bit_count(F.col("low").bitwiseXOR(F.col("other_low")))
    agreed = F.lit(False)
    for k, span in enumerate(spans[:-1]):  # a pair counts in the first table that it shares
        same = block(F.col("high"), F.col("low"), *span) == block(F.col("other_high"), F.col("other_low"), *span)
        agreed = agreed | ((F.col("led_by") > k) & same)
    ordered = (F.col("high") < F.col("other_high")) | ((F.col("high") == F.col("other_high")) & (F.col("low") < F.col("other_low")))
    pairs = led.join(other, ["led_by", "lead"]).where(ordered & (apart <= radius) & ~agreed)
    return pairs.select("high", "low", "other_high", "other_low", apart.alias("distance"))


def near_counts(prints: DataFrame, radius: int = RADIUS) -> DataFrame:
    """(high, low, n_near) of every fingerprint that has others within the radius: how many. prints: (high, low), any rows."""
    pairs = near_pairs(cut(own_columns(prints, "high", "low").distinct()), radius)  # written, so that hot blocks can be split
    ends = pairs.select(F.explode(F.array(F.struct("high", "low"), F.struct(F.col("other_high").alias("high"), F.col("other_low").alias("low")))).alias("x"))
    return cut(ends.groupBy("x.high", "x.low").agg(F.count(F.lit(1)).alias("n_near")))


def in_order(docs: DataFrame) -> DataFrame:
    """docs (doc_id, text) with (block, place, next_text): the text of the next row in descending doc_id, the first row's after the last.

    Blocks are equal stretches of doc_id; the first row of each is dealt to the block
    before as well, so that one shuffle of the texts is enough. Null ids come last, rows
    of one id by text.
    """
    docs = own_columns(docs, "doc_id", "text").withColumn("text", F.coalesce("text", F.lit("")))
    low, high, n = docs.agg(F.min("doc_id"), F.max("doc_id"), F.count(F.lit(1))).first()
    low, high = (0, 0) if low is None else (low, high)
    blocks = max(1, min(MOST_BLOCKS, -(-n // ROWS_A_BLOCK)))
    width = (high - low) // blocks + 1
    dealt = docs.withColumn("block", F.expr(f"cast(({high} - coalesce(doc_id, {low})) div {width} as int)"))
    heads = dealt.groupBy("block").agg(F.max("doc_id").alias("head"))  # MOST_BLOCKS rows at most
    ring = Window.orderBy("block")
    heads = heads.withColumn("before", F.coalesce(F.lag("block").over(ring), F.max("block").over(Window.partitionBy())))
    with_heads = dealt.join(F.broadcast(heads), "block", "left")
    ghost = F.when(F.col("doc_id").eqNullSafe(F.col("head")), F.array(F.struct("block", F.lit(0).alias("ghost")), F.struct(F.col("before").alias("block"), F.lit(1).alias("ghost")))).otherwise(F.array(F.struct("block", F.lit(0).alias("ghost"))))
    twice = with_heads.select("doc_id", "text", F.explode(ghost).alias("x")).select("doc_id", "text", "x.block", "x.ghost")
    order = Window.partitionBy("block").orderBy("ghost", F.col("doc_id").desc_nulls_last(), "text")
    return twice.select("*", F.row_number().over(order).alias("place"), F.lead("text").over(order).alias("next_text")).where("ghost = 0").drop("ghost")


def edited_fingerprints(docs: DataFrame) -> DataFrame:
    """A row for each row of docs: (doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next, n_near).

    The edited text has its last floor(n_chars / 2) code points replaced by the first as
    many, or all, of the next document in descending doc_id (the first after the last).
    Null texts are empty; a lone document is its own next. Repeated rows get rows each.
    """
    placed = in_order(docs)
    n, half = F.char_length("text"), F.expr("cast(char_length(text) div 2 as int)")
    placed = placed.select("block", "place", "doc_id", "text", n.cast("long").alias("n_chars"), F.concat(F.expr("substring(text, 1, cast(char_length(text) - char_length(text) div 2 as int))"), F.substring("next_text", 1, half)).alias("edited"))
    placed = placed.withColumn("edited_sha256", F.unhex(sha256_hex(F.col("edited"))))
    keys = ["block", "place", "doc_id", "n_chars", "edited_sha256"]
    both = placed.select(*keys, F.explode(F.array(F.struct(F.lit(0).alias("kind"), "text"), F.struct(F.lit(1).alias("kind"), F.col("edited").alias("text")))).alias("x")).select(*keys, "x.kind", "x.text")
    prints = fingerprints(both, [*keys, "kind"])
    pick = lambda kind, c: F.max(F.when(F.col("kind") == kind, F.col(c))).alias(f"{c}_{kind}")
    rows = cut(prints.groupBy(*keys).agg(*[pick(k, c) for k in (0, 1) for c in ("high", "low")]))
    near = near_counts(rows.select(F.col("high_0").alias("high"), F.col("low_0").alias("low")))
    sizes = rows.groupBy("block").agg(F.max("place").alias("size"))  # MOST_BLOCKS rows at most
    sizes = sizes.withColumn("after", F.coalesce(F.lead("block").over(Window.orderBy("block")), F.min("block").over(Window.partitionBy())))
    rows = rows.join(F.broadcast(sizes), "block")
    last = F.col("place") == F.col("size")
    mine = rows.withColumn("next_block", F.when(last, F.col("after")).otherwise(F.col("block"))).withColumn("next_place", F.when(last, 1).otherwise(F.col("place") + 1))
    theirs = rows.select(F.col("block").alias("next_block"), F.col("place").alias("next_place"), F.col("high_0").alias("next_high"), F.col("low_0").alias("next_low"))
    own, edit, following = (F.col("high_0"), F.col("low_0")), (F.col("high_1"), F.col("low_1")), (F.col("next_high"), F.col("next_low"))
    found = mine.join(theirs, ["next_block", "next_place"]).join(near.withColumnsRenamed({"high": "high_0", "low": "low_0"}), ["high_0", "low_0"], "left")
    return found.select("doc_id", "n_chars", F.lower(F.hex("edited_sha256")).alias("edited_sha256"), as_text(*own).alias("fingerprint"), as_text(*edit).alias("edited_fingerprint"), likeness(own, edit).alias("near_edited"), likeness(own, following).alias("near_next"), F.coalesce("n_near", F.lit(0)).alias("n_near"))
