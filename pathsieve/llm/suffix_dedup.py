"""Exact removal of repeated 200-byte strings: suffixes sorted bucket by bucket, with a difference cover.

Buckets. A suffix counts by its first `LENGTH` bytes, its window. Of the GRAM-byte
strings in a window the one of least hash (the leftmost of those) is its anchor, and the
anchor's hash names the bucket: equal windows have equal anchors at equal places, so
that they meet in one bucket. Neighbouring windows of one anchor travel together as one
span; spans are about LENGTH / 3 windows long, so that a bucket entry stands for many
suffixes. Buckets of one span, and most bytes with them, are never sorted. In a bucket
whose spans are all equal every window is repeated. What is left, each different span
once, is sorted.

Sorting. A block of whole buckets is laid out with every anchor at place 0 modulo
PERIOD. Suffixes at the places of a difference cover modulo PERIOD are ranked first: by
their first PERIOD bytes, then by doubling, rank of here and rank of PERIOD further on.
All windows are then sorted by their first 32 bytes; ties are resolved by the rank at
the next cover place, however long they are. Neighbours that agree on LENGTH bytes are
repeats. A task holds one block of bounded size.

Large buckets. A bucket whose different spans exceed `_BLOCK` bytes is cut before it is
sorted: equal windows hold their anchor at the same place, so each span is cut into
stretches of such places, PARTS at a time, and the bytes common to all windows of a
stretch name its bucket together with those places. Stretches alone in their bucket are
settled, and so are buckets of equal stretches; what is still too large is cut again, at
last to single windows, whose buckets are equal ones. A passage in many contexts thus
costs a few rows a context in each round, and every bucket that needs an order is sorted.

Equal spans and stretches are told by 64-bit hashes within a bucket, sorted ones by their bytes.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator
from functools import cache

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathsieve.llm.shared import forget_tokenizers, fresh_path, masked, own_columns, text_slices, trim

LENGTH, GRAM, PERIOD, PARTS = 200, 32, 31, 4
_GRAMS = LENGTH - GRAM + 1
_PLACE_BITS = 21
_PIECE = 1 << 18
_BLOCK = 1 << 20
ANCHORS = "h long, span long, doc_id long, mark long, first int, n int, rel int"


@cache
def difference_cover(period: int = PERIOD) -> tuple[int, ...]:
    """Residues such that every difference modulo the period is one of two of them: the least set that a search in order finds."""
    from itertools import combinations

    for size in range(2, period + 1):
        for rest in combinations(range(1, period), size - 1):
            some = (0, *rest)
            if len({(a - b) % period for a in some for b in some}) == period:
                return some
    return tuple(range(period))


@cache
def _random() -> tuple[np.ndarray, list[np.uint64]]:
    rng = np.random.default_rng(20240229)
    return rng.integers(0, 2**64, 256, dtype=np.uint64), [np.uint64(x | 1) for x in rng.integers(0, 2**63, 8, dtype=np.uint64).tolist()]


def _gram_hashes(raw: np.ndarray) -> np.ndarray:
    """Hash of the GRAM bytes (a power of two) from each place, by doubling."""
    table, factors = _random()
    h, m = table[raw], 1
    while m < GRAM:
        h = h[:-m] * factors[m.bit_length() - 1] + h[m:]
        m *= 2
    h ^= h >> np.uint64(29)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    return h ^ (h >> np.uint64(32))


def _least(a: np.ndarray, width: int) -> np.ndarray:
    """Minimum of each stretch of `width`, by doubling."""
    m = 1
    while 2 * m <= width:
        a = np.minimum(a[:-m], a[m:])
        m *= 2
    rest = width - m
    return np.minimum(a[: len(a) - rest], a[rest:]) if rest else a


def anchor_spans(raws: list[bytes]) -> tuple[np.ndarray, ...]:
    """(text number, first window, windows, anchor - first window, anchor hash, span hash) of every span, over texts of any length."""
    out: list[tuple[np.ndarray, ...]] = []
    sizes = np.array([len(r) for r in raws], np.int64)
    joined = b"".join(raws)
    raw = np.frombuffer(joined, np.uint8)
    ends = np.cumsum(sizes)
    keep = np.uint64(2**64 - 2**_PLACE_BITS)
    for at in range(0, len(raw), _PIECE):  # windows from `at` on, with what they reach over
        part = raw[at : at + _PIECE + LENGTH - 1]
        if len(part) < LENGTH:
            break
        h = _gram_hashes(part)
        least = _least((h & keep) | np.arange(len(h), dtype=np.uint64), _GRAMS)
        place = (least & np.uint64(2**_PLACE_BITS - 1)).astype(np.int64)
        starts = np.arange(at, at + len(place))
        doc = np.searchsorted(ends, starts, "right")
        good = starts + LENGTH <= ends[np.minimum(doc, len(ends) - 1)]
        starts, doc, place = starts[good], doc[good], place[good]
        if not len(starts):
            continue
        cut = np.flatnonzero(np.r_[True, (place[1:] != place[:-1]) | (doc[1:] != doc[:-1])])
        n = np.diff(np.r_[cut, len(starts)])
        first = starts[cut]
        rel = place[cut] + at - first
        spans = np.array([xxhash.xxh3_64_intdigest(joined[f : f + k + LENGTH - 1], r) for f, k, r in zip(first.tolist(), n.tolist(), rel.tolist(), strict=True)], np.uint64)
        out.append((doc[cut], first - (ends - sizes)[doc[cut]], n, rel, h[place[cut]].view(np.int64), spans.view(np.int64)))
    return tuple(np.concatenate(x) for x in zip(*out, strict=True)) if out else tuple(np.zeros(0, np.int64) for _ in range(6))


def repeated_windows(spans: list[bytes], rels: list[int]) -> list[np.ndarray]:
    """For each span, which of its windows stand in another span too (or twice). Suffix order with a difference cover."""
    v, cover = PERIOD, difference_cover()
    sizes = np.array([len(s) for s in spans], np.int64)
    rel = np.array(rels, np.int64)
    lead = (-rel) % v  # so that the anchor stands at place 0 modulo v
    slots = -(-(lead + sizes) // v) * v
    at = np.cumsum(slots) - slots + lead
    text = np.zeros(int(slots.sum()) + 9 * v, np.uint8)
    flat = np.repeat(at - (np.cumsum(sizes) - sizes), sizes) + np.arange(int(sizes.sum()))
    text[flat] = np.frombuffer(b"".join(spans), np.uint8)
    words = np.zeros(len(text), np.uint64)  # the 8 bytes from each place, big-endian
    for k in range(8):
        words[: len(text) - k] |= text[k:].astype(np.uint64) << np.uint64(56 - 8 * k)
    # ranks of the cover's places, to a depth of 8 periods
    residues = np.array(cover)
    places = (np.arange(len(text) // v - 8)[:, None] * v + residues).ravel()
    padded = np.r_[words, np.zeros(v + 8, np.uint64)]
    keys = [padded[places + 8 * k] for k in range(4)]
    keys[3] = keys[3] & np.uint64(2**64 - 2**8)  # 31 bytes
    rank = np.zeros(len(text) + 8 * v, np.int64)
    order = np.lexsort(keys[::-1])
    fresh = np.zeros(len(order), bool)
    for key in keys:
        fresh[1:] |= key[order][1:] != key[order][:-1]
    rank[places[order]] = np.cumsum(fresh) + 1
    depth = v
    while depth < LENGTH:
        both = rank[places].astype(np.uint64) << np.uint64(32) | rank[places + depth].astype(np.uint64)
        order = np.argsort(both, kind="stable")
        ordered = both[order]
        rank[places[order]] = np.cumsum(np.r_[False, ordered[1:] != ordered[:-1]]) + 1
        depth *= 2
    # all windows
    n = sizes - LENGTH + 1
    owner = np.repeat(np.arange(len(spans)), n)
    offset = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
    start = at[owner] + offset
    step = np.array([min((c - r) % v for c in cover) for r in range(v)])
    residue = start % v
    tie = residue.astype(np.uint64) << np.uint64(40) | rank[start + step[residue]].astype(np.uint64)
    keys = [words[start + 8 * k] for k in range(4)] + [tie]
    order = np.lexsort(keys[::-1])
    ordered = start[order]
    same = np.ones(max(len(order) - 1, 0), bool)
    for k in range(LENGTH // 8):
        live = np.flatnonzero(same)
        same[live] = words[ordered[live] + 8 * k] == words[ordered[live + 1] + 8 * k]
    flag = np.zeros(len(order), bool)
    flag[order[1:][same]] = True
    flag[order[:-1][same]] = True
    return np.split(flag, np.cumsum(n)[:-1])


def _runs(flags: np.ndarray) -> list[tuple[int, int]]:
    edges = np.flatnonzero(np.diff(np.r_[False, flags, False].astype(np.int8)))
    return list(zip(edges[::2].tolist(), (edges[1::2] - edges[::2]).tolist(), strict=True))


def _mark() -> Column:
    return F.xxhash64(F.coalesce("text", F.lit("")), F.coalesce(F.octet_length("text"), F.lit(0))).alias("mark")


def _marked(docs: DataFrame) -> DataFrame:
    """(doc_id, mark, text): id and mark name a row, or rows of one id and one text (texts of one id are told apart by 64 bits)."""
    docs = own_columns(docs, "doc_id", "text")
    return docs.select("doc_id", _mark(), "text")


def _anchors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    forget_tokenizers()
    for whole in batches:
        for batch in text_slices(whole, "text", 1 << 20):
            raws = [(t or "").encode() for t in batch.column("text").to_pylist()]
            doc, first, n, rel, h, span = anchor_spans(raws)
            at = pa.array(doc, pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(h), pa.array(span), batch.column("doc_id").take(at), batch.column("mark").take(at), *(pa.array(x, pa.int32()) for x in (first, n, rel))], ["h", "span", "doc_id", "mark", "first", "n", "rel"])


def _span_bytes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (text, wanted: h, span, first, n, rel) to the spans' bytes."""
    for whole in batches:
        for batch in text_slices(whole, "text", 1 << 20):
            out: dict[str, list] = {c: [] for c in ("h", "span", "rel", "bytes")}
            for text, wanted in zip(batch.column("text").to_pylist(), batch.column("wanted").to_pylist(), strict=True):
                raw = text.encode()
                for w in wanted:
                    for c, x in zip(out, (w["h"], w["span"], w["rel"], raw[w["first"] : w["first"] + w["n"] + LENGTH - 1]), strict=True):
                        out[c].append(x)
            yield pa.RecordBatch.from_arrays([pa.array(out["h"], pa.int64()), pa.array(out["span"], pa.int64()), pa.array(out["rel"], pa.int32()), pa.array(out["bytes"], pa.binary())], list(out))


def stretches(raw: bytes, rel: int, width: int) -> Iterator[tuple[int, int, bytes]]:
    """(first window, windows, common bytes) of a span's stretches: their anchors stand at places [k * width, (k + 1) * width) of the windows. rel: place of the anchor in the span."""
    n, at = len(raw) - LENGTH + 1, 0
    while at < n:
        place = rel - at  # of the anchor, in window `at`; one less in the next
        low = place // width * width
        size = min(place - low + 1, n - at)
        # what windows with the anchor at `low` .. `low + width - 1` share, around the anchor
        begin, end = rel - low, rel - low - width + 1 + LENGTH
        yield at, size, raw[max(begin, 0) : end]
        at += size


def _cut_spans(width: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Rows (h, span, off, key, rel, bytes) to those of their stretches, each with the key of its smaller bucket and a hash of its bytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: dict[str, list] = {c: [] for c in ("h", "span", "off", "key", "piece", "rel", "bytes")}
            for h, span, off, key, rel, raw in zip(*(batch.column(c).to_pylist() for c in ("h", "span", "off", "key", "rel", "bytes")), strict=True):
                for at, size, common in stretches(raw, rel, width):
                    part = raw[at : at + size + LENGTH - 1]
                    bucket = xxhash.xxh3_64_intdigest(common, (key ^ (rel - at) // width * 0x9E3779B97F4A7C15) % 2**64)
                    for c, x in zip(out, (h, span, off + at, bucket - 2**63, xxhash.xxh3_64_intdigest(part, rel - at) - 2**63, rel - at, part), strict=True):
                        out[c].append(x)
            kinds = {"off": pa.int32(), "rel": pa.int32(), "bytes": pa.binary()}
            yield pa.RecordBatch.from_arrays([pa.array(v, kinds.get(c, pa.int64())) for c, v in out.items()], list(out))

    return run


def _sorted_blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows sorted by h: whole buckets are gathered to blocks and sorted."""
    held: list[tuple[int, int, int, bytes]] = []
    size = 0

    def solve() -> pa.RecordBatch:
        out: dict[str, list] = {c: [] for c in ("h", "span", "off", "len")}
        if held:
            for (h, span, _, _), flags in zip(held, repeated_windows([x[3] for x in held], [x[2] for x in held]), strict=True):
                for off, n in _runs(flags):
                    for c, x in zip(out, (h, span, off, n), strict=True):
                        out[c].append(x)
        return pa.RecordBatch.from_arrays([pa.array(out["h"], pa.int64()), pa.array(out["span"], pa.int64()), pa.array(out["off"], pa.int32()), pa.array(out["len"], pa.int32())], list(out))

    for batch in batches:
        for h, span, rel, raw in zip(*(batch.column(c).to_pylist() for c in ("h", "span", "rel", "bytes")), strict=True):
            if size > _BLOCK and held[-1][0] != h:
                yield solve()
                held, size = [], 0
                trim()
            held.append((h, span, rel, raw))
            size += len(raw)
    yield solve()


def _settled(pieces: DataFrame, path: str) -> tuple[DataFrame, DataFrame]:
    """(found, large) of pieces (h, span, off, key, piece, rel, bytes), a written table: stretches (h, span, off, len) that repeat, and the pieces of buckets that exceed a block."""
    spark = pieces.sparkSession
    same = pieces.groupBy("key", "piece").agg(F.count(F.lit(1)).alias("times"), F.max(F.octet_length("bytes")).alias("size"))
    groups = same.groupBy("key").agg(F.sum("times").alias("times"), F.sum("size").alias("size"), F.count(F.lit(1)).alias("kinds")).where("times > 1").select("key", "kinds", (F.col("size") > _BLOCK).alias("large"))
    groups.write.parquet(f"{path}/groups")
    groups = spark.read.schema("key long, kinds long, large boolean").parquet(f"{path}/groups")
    pieces.join(groups, "key").write.parquet(f"{path}/grouped")
    grouped = spark.read.schema(f"{PIECES}, kinds long, large boolean").parquet(f"{path}/grouped")
    windows = F.octet_length("bytes") - F.lit(LENGTH - 1)
    equal = grouped.where("kinds = 1").select("h", "span", "off", windows.alias("len"))
    small = grouped.where("kinds > 1 AND NOT large")
    one = small.groupBy("key", "piece").agg(F.count(F.lit(1)).alias("times"), F.first("rel").alias("rel"), F.first("bytes").alias("bytes"))
    one.write.parquet(f"{path}/different")
    one = spark.read.schema("key long, piece long, times long, rel int, bytes binary").parquet(f"{path}/different")
    ordered = one.select(F.col("key").alias("h"), F.col("piece").alias("span"), "rel", "bytes").repartition("h").sortWithinPartitions("h", "span").mapInArrow(_sorted_blocks, "h long, span long, off int, len int")
    repeated = ordered.select(F.col("h").alias("key"), F.col("span").alias("piece"), F.col("off").alias("at"), F.col("len"))
    repeated = repeated.unionByName(one.where("times > 1").select("key", "piece", F.lit(0).alias("at"), windows.alias("len")))
    repeated.write.parquet(f"{path}/repeated")
    repeated = spark.read.schema("key long, piece long, at int, len int").parquet(f"{path}/repeated")
    sorted_ones = small.select("h", "span", "off", "key", "piece").join(repeated, ["key", "piece"]).select("h", "span", (F.col("off") + F.col("at")).alias("off"), "len")
    return equal.unionByName(sorted_ones), grouped.where("kinds > 1 AND large").drop("kinds", "large", "piece")


PIECES = "h long, span long, off int, key long, piece long, rel int, bytes binary"


def _in_large_buckets(spans: DataFrame, path: str) -> DataFrame:
    """(h, span, off, len) of the repeated windows in spans (h, span, rel, bytes) of buckets above a block."""
    spark = spans.sparkSession
    now, found, width, step = spans.select("h", "span", F.lit(0).alias("off"), F.col("h").alias("key"), "rel", "bytes"), None, _GRAMS, 0
    while width > 1 and not now.isEmpty():
        width, step = -(-width // PARTS), step + 1
        # dealt by span, since one file may hold most of a large bucket
        now.repartition("h", "span").mapInArrow(_cut_spans(width), PIECES).write.parquet(f"{path}/pieces-{step}")
        some, now = _settled(spark.read.schema(PIECES).parquet(f"{path}/pieces-{step}"), f"{path}/round-{step}")
        found = some if found is None else found.unionByName(some)
    return found if found is not None else spark.createDataFrame([], "h long, span long, off int, len int")


def repeats(docs: DataFrame) -> DataFrame:
    """(doc_id, mark, text, runs) of each row of docs: runs is an array of (start, len), stretches of windows that stand elsewhere too; null if there are none. Null texts are null.

    What is gathered into one row (spans or runs of one text) is smaller than that text.
    """
    spark = docs.sparkSession
    marked = _marked(docs)
    path = fresh_path(spark, "repeats")
    marked.where(F.octet_length("text") >= LENGTH).mapInArrow(_anchors, ANCHORS).write.parquet(f"{path}/anchors")  # written: they are read twice
    anchors = spark.read.schema(ANCHORS).parquet(f"{path}/anchors")
    buckets = anchors.groupBy("h").agg(F.count(F.lit(1)).alias("times"), F.min("span").alias("a"), F.max("span").alias("b")).where("times > 1").select("h", (F.col("a") != F.col("b")).alias("mixed"))
    # written first: a join with an aggregate would take over its partitions, in which the engine can't split a large bucket
    buckets.write.parquet(f"{path}/buckets")
    buckets = spark.read.schema("h long, mixed boolean").parquet(f"{path}/buckets")
    anchors.join(buckets, "h").write.parquet(f"{path}/flagged")
    flagged = spark.read.schema(ANCHORS + ", mixed boolean").parquet(f"{path}/flagged")
    plain = flagged.where("NOT mixed").select("doc_id", "mark", "first", "n")
    mixed = flagged.where("mixed").drop("mixed")
    spans = mixed.groupBy("h", "span").agg(F.count(F.lit(1)).alias("times"), F.min(F.struct("doc_id", "mark", "first", "n", "rel")).alias("one"))
    spans.write.parquet(f"{path}/spans")
    spans = spark.read.schema("h long, span long, times long, one struct<doc_id: long, mark: long, first: int, n: int, rel: int>").parquet(f"{path}/spans")
    wanted = spans.select("h", "span", "one.*").groupBy("doc_id", "mark").agg(F.collect_list(F.struct("h", "span", "first", "n", "rel")).alias("wanted"))  # spans of one text
    sources = marked.join(wanted.withColumnsRenamed({"doc_id": "d", "mark": "m"}), F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("mark") == F.col("m"))).select("doc_id", "mark", "text", "wanted").dropDuplicates(["doc_id", "mark"])
    sources.mapInArrow(_span_bytes, "h long, span long, rel int, bytes binary").write.parquet(f"{path}/bytes")
    held = spark.read.schema("h long, span long, rel int, bytes binary").parquet(f"{path}/bytes")
    heavy = spans.groupBy("h").agg(F.sum(F.col("one.n") + F.lit(LENGTH - 1)).alias("size")).where(F.col("size") > _BLOCK).select("h")
    heavy.write.parquet(f"{path}/heavy")
    heavy = spark.read.schema("h long").parquet(f"{path}/heavy")
    found = held.join(heavy, "h", "left_anti").repartition("h").sortWithinPartitions("h", "span").mapInArrow(_sorted_blocks, "h long, span long, off int, len int")
    found = found.unionByName(_in_large_buckets(held.join(heavy, "h", "left_semi"), path))
    parts = found.groupBy("h", "span").agg(F.collect_set(F.struct("off", "len")).alias("part"))  # of one span
    whole = F.array(F.struct(F.lit(0).alias("off"), F.col("one.n").alias("len")))
    decided = spans.join(parts, ["h", "span"], "left").select("h", "span", F.when(F.col("times") > 1, whole).otherwise(F.col("part")).alias("part")).where("part IS NOT NULL")
    decided.write.parquet(f"{path}/decided")
    decided = spark.read.schema("h long, span long, part array<struct<off: int, len: int>>").parquet(f"{path}/decided")
    of_mixed = mixed.join(decided, ["h", "span"]).select("doc_id", "mark", "first", F.explode("part").alias("x")).select("doc_id", "mark", (F.col("first") + F.col("x.off")).alias("first"), F.col("x.len").alias("n"))
    runs = plain.unionByName(of_mixed).groupBy("doc_id", "mark").agg(F.collect_set(F.struct(F.col("first").alias("start"), F.col("n").alias("len"))).alias("runs"))  # of one text
    return marked.join(runs.withColumnsRenamed({"doc_id": "d", "mark": "m"}), F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("mark") == F.col("m")), "left").select("doc_id", "mark", "text", "runs")


def cut_out(raw: bytes, runs: list[dict] | None) -> tuple[bytes, int]:
    """What stays, and the number of stretches that went."""
    stretches: list[list[int]] = []
    for a, b in sorted((r["start"], r["start"] + r["len"] - 1 + LENGTH) for r in runs or ()):
        if stretches and a <= stretches[-1][1]:
            stretches[-1][1] = max(stretches[-1][1], b)
        else:
            stretches.append([a, b])
    kept, at = [], 0
    for a, b in stretches:
        kept.append(raw[at:a])
        at = b
    return b"".join([*kept, raw[at:]]), len(stretches)


def remove_repeats(docs: DataFrame) -> DataFrame:
    """A row for each row of docs: (doc_id, n_bytes, n_removed, n_spans, kept_sha256, kept_text).

    Null texts are empty. Repeated rows are repeats of each other. kept_text is what
    stays; bytes of a character that was cut in two are left out of it (not of the hash).
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in text_slices(whole, "text"):
                out: dict[str, list] = {c: [] for c in ("n_bytes", "n_removed", "n_spans", "kept_sha256", "kept_text")}
                for text, runs in zip(batch.column("text").to_pylist(), batch.column("runs").to_pylist(), strict=True):
                    raw = (text or "").encode()
                    kept, n = cut_out(raw, runs)
                    for c, x in zip(out, (len(raw), len(raw) - len(kept), n, hashlib.sha256(kept).hexdigest(), kept.decode(errors="ignore")), strict=True):
                        out[c].append(x)
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array(v, pa.string() if c[0] == "k" else pa.int64()) for c, v in out.items())], ["doc_id", *out])

    return repeats(docs).select("doc_id", "text", "runs").mapInArrow(run, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept_text string")


def with_repeats_removed(docs: DataFrame) -> DataFrame:
    """The rows of docs, all columns: text without its repeats, n_chars (where there is one) counted anew. Rows of which nothing is left go; rows without repeats, null and empty texts stay as they are."""
    rows, named = masked(docs, "doc_id", "text", "n_chars")
    columns, schema = rows.columns, rows.schema
    found = repeats(rows).where("runs IS NOT NULL").select(F.col("doc_id").alias("run_id"), F.col("mark").alias("run_mark"), "runs").dropDuplicates(["run_id", "run_mark"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in text_slices(whole, "text"):
                texts = [t if runs is None else cut_out(t.encode(), runs)[0].decode(errors="ignore") for t, runs in zip(batch.column("text").to_pylist(), batch.column("runs").to_pylist(), strict=True)]
                gone = [runs is not None and not t for t, runs in zip(texts, batch.column("runs").to_pylist(), strict=True)]
                new = {"text": pa.array(texts, pa.string())}
                if "n_chars" in columns:
                    new["n_chars"] = pa.array([n if runs is None else len(t) for n, t, runs in zip(batch.column("n_chars").to_pylist(), texts, batch.column("runs").to_pylist(), strict=True)], batch.schema.field("n_chars").type)
                out = pa.RecordBatch.from_arrays([new.get(c, batch.column(c)) for c in columns], columns)
                yield out.filter(pa.array([not g for g in gone]))

    joined = rows.withColumn("mark", _mark()).join(found, F.col("doc_id").eqNullSafe(F.col("run_id")) & (F.col("mark") == F.col("run_mark")), "left")
    return named(joined.select(*[F.col(f"`{c}`") for c in columns], "runs").mapInArrow(run, schema))
