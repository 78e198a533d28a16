"""Best-fit packing of documents into sequences, planned over a histogram of lengths.

1. Every document becomes pieces of at most `capacity` ids (only longer ones are cut).
2. The histogram of piece lengths (at most `capacity` rows, whatever the input) goes to
   the driver, where best-fit decreasing runs over counts: bins of equal room are one
   entry, so that the plan takes a number of steps that depends on `capacity` alone.
3. Each piece gets its rank within its length and takes the planned slot of that rank
   by a join. Ranks are counted within (length, salt), so that no length, however
   common, meets in one task.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, insort
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pathsieve.llm.shared import cut, own_columns, text_slices
from pathsieve.llm.tokens import encoder

CAPACITY, END_ID, SALTS = 4096, 1, 1024
VOCABULARY = "word_bpe_49k.json"
PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"
SLOTS = "length long, rank_from long, rank_to long, each long, first_bin long, first_offset long"


def pieces(docs: DataFrame, vocabulary: str = VOCABULARY, end_id: int = END_ID, capacity: int = CAPACITY) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32) of every document; a null text is empty and has the end id alone. Repeated rows give repeated pieces."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        end = np.array([end_id], "<u4").tobytes()
        for batch in (part for whole in batches for part in text_slices(whole, "text", 1 << 22)):
            out = defaultdict(list)
            texts = encoder(vocabulary, False).encode(batch.column("text").to_pylist())
            for doc, ids in zip(batch.column("doc_id").to_pylist(), texts, strict=True):
                ids += end
                for k, at in enumerate(range(0, len(ids), 4 * capacity)):
                    part = ids[at : at + 4 * capacity]
                    for name, value in zip(("doc_id", "piece", "start", "length", "ids_crc32"), (doc, k, at // 4, len(part) // 4, zlib.crc32(part)), strict=True):
                        out[name].append(value)
            if out:
                yield pa.RecordBatch.from_pydict({k: pa.array(v, pa.int32() if k == "piece" else pa.int64()) for k, v in out.items()})

    return own_columns(docs, "doc_id", "text").mapInArrow(run, PIECES)


def plan(histogram: dict[int, int], capacity: int = CAPACITY) -> list[tuple[int, int, int, int, int, int]]:
    """Slots (length, rank_from, rank_to, each, first_bin, first_offset): the piece of rank r goes to bin first_bin + (r - rank_from) // each.

    Best fit decreasing: the longest pieces first, each into the fullest bin that has room.
    Bins of equal room are kept as ranges of bin numbers.
    """
    rooms: list[int] = []
    bins: dict[int, list[tuple[int, int]]] = defaultdict(list)  # room -> ranges (first bin, count)
    slots, made = [], 0

    def put(room: int, first: int, n: int) -> None:
        if room and n:
            if not bins[room]:
                insort(rooms, room)
            bins[room].append((first, n))

    for length in sorted(histogram, reverse=True):
        if not 0 < length <= capacity:
            raise ValueError(f"length {length} doesn't fit {capacity}")
        rank, left = 0, histogram[length]
        while left:
            k = bisect_left(rooms, length)
            if k < len(rooms):
                room = rooms[k]
                first, n = bins[room].pop()
                if not bins[room]:
                    rooms.pop(k)
            else:
                room, first, n = capacity, made, -(-left // (capacity // length))
                made += n
            each = min(room // length, left)
            full = min(n, left // each)
            slots.append((length, rank, rank + full * each, each, first, capacity - room))
            put(room - each * length, first, full)
            rank, left = rank + full * each, left - full * each
            rest = n - full
            if rest and left and left < each:  # the last bin takes what is left
                slots.append((length, rank, rank + left, left, first + full, capacity - room))
                put(room - left * length, first + full, 1)
                full, rest, rank, left = full + 1, rest - 1, rank + left, 0
            put(room, first + full, rest)
    return slots


def pack(found: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """pieces() with (sequence_id, offset). No row leaves or joins; an empty input gives no rows."""
    spark = found.sparkSession
    found = cut(found)
    histogram = {r["length"]: r["n"] for r in found.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}  # at most `capacity` rows
    slots = spark.createDataFrame(plan(histogram, capacity), SLOTS)
    salted = found.withColumn("salt", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(SALTS)).cast("int"))
    before = salted.groupBy("length", "salt").agg(F.count(F.lit(1)).alias("n")).withColumn("before", F.sum("n").over(Window.partitionBy("length").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1)))  # at most SALTS rows of a length
    ranked = salted.withColumn("nth", F.row_number().over(Window.partitionBy("length", "salt").orderBy("doc_id", "piece", "ids_crc32")))
    ranked = ranked.join(before.select("length", "salt", F.coalesce("before", F.lit(0)).alias("before")), ["length", "salt"]).withColumn("rank", F.col("before") + F.col("nth") - 1)
    placed = ranked.join(F.broadcast(slots), "length").where("rank >= rank_from AND rank < rank_to")  # the plan's size depends on capacity alone
    return placed.select("doc_id", "piece", "start", "length", "ids_crc32", F.expr("first_bin + (rank - rank_from) div each").alias("sequence_id"), F.expr("first_offset + ((rank - rank_from) % each) * length").alias("offset"))
