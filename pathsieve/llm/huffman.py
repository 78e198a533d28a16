"""Token ids in files: canonical length-limited Huffman codes with bit-offset checkpoints.

A file set is a folder of Parquet data sets, so that any store that Spark reads can hold
it: `plain` (the tokenizer's ids before coding, which may be deleted), `codebook` (id, bits: code lengths, from which the canonical codes follow)
and `shards`. A shard holds whole documents in ascending doc_id order: their ids and
lengths, the coded payload, and the bit offset of every block of BLOCK ids. Blocks can
be decoded alone; the decoder walks all blocks of a shard in step, one table look-up for
each id.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pathsieve.llm.shared import own_columns, text_slices
from pathsieve.llm.tokens import encoder

VOCABULARY, END_ID = "byte_bpe_50k.json", 2
LONGEST_CODE, BLOCK, SHARD_IDS = 20, 512, 1 << 20
SHARDS = "part int, shard int, ids_before long, n_ids long, doc_ids array<long>, doc_lengths array<long>, checkpoints array<long>, payload binary"
PLAIN = "part int, shard int, ids_before long, n_ids long, doc_ids array<long>, doc_lengths array<long>, seen array<long>, times array<long>, ids binary"


def code_lengths(counts: np.ndarray, longest: int = LONGEST_CODE) -> np.ndarray:
    """Bits of each symbol's code, 0 where its count is 0: the least total length under the limit, by package-merge."""
    used = np.flatnonzero(counts)
    out = np.zeros(len(counts), np.uint8)
    if len(used) > 1 << longest:
        raise ValueError("more symbols than codes")
    if len(used) < 2:
        out[used] = 1
        return out
    order = used[np.argsort(counts[used], kind="stable")]
    weight = counts[order].astype(np.int64)
    current, leaf_flags = weight, [np.ones(len(weight), bool)]
    for _ in range(longest - 1):
        pairs = current[: len(current) // 2 * 2].reshape(-1, 2).sum(1)
        both = np.concatenate([weight, pairs])
        order_here = np.argsort(both, kind="stable")
        current = both[order_here]
        leaf_flags.append(order_here < len(weight))
    take = 2 * len(used) - 2
    for flags in reversed(leaf_flags):
        leaves = int(flags[:take].sum())
        out[order[:leaves]] += 1
        take = 2 * (take - leaves)
    return out


class Codebook:
    """Canonical codes: shorter first, then by id."""

    def __init__(self, bits: np.ndarray) -> None:
        self.bits = bits.astype(np.int64)
        self.codes = np.zeros(len(bits), np.uint64)
        order = np.lexsort((np.arange(len(bits)), bits))
        order = order[bits[order] > 0]
        lengths = self.bits[order]
        steps = np.left_shift(np.int64(1), LONGEST_CODE - lengths)
        at = np.concatenate([[0], np.cumsum(steps)])
        self.codes[order] = (at[:-1] >> (LONGEST_CODE - lengths)).astype(np.uint64)
        self.symbol = np.zeros(1 << LONGEST_CODE, np.uint32)
        self.size = np.ones(1 << LONGEST_CODE, np.int64)
        self.symbol[: at[-1]] = np.repeat(order, steps)
        self.size[: at[-1]] = np.repeat(lengths, steps)

    def encode(self, ids: np.ndarray) -> tuple[bytes, np.ndarray]:
        """Payload, and the bit offset of each block."""
        bits = self.bits[ids]
        ends = np.cumsum(bits)
        starts = ends - bits
        word, shift = starts >> 5, 64 - (starts & 31) - bits
        value = self.codes[ids] << shift.astype(np.uint64)
        words = np.zeros(int(ends[-1] >> 5) + 3 if len(ids) else 2, np.uint64)
        if len(ids):
            first = np.flatnonzero(np.diff(word, prepend=-1))
            whole = np.add.reduceat(value, first)  # codes in one word have no bit in common
            words[word[first]] += whole >> np.uint64(32)
            words[word[first] + 1] += whole & np.uint64(0xFFFFFFFF)
        return words.astype(">u4").tobytes(), starts[::BLOCK]

    def decode(self, payload: bytes, checkpoints: np.ndarray, n: int) -> np.ndarray:
        raw = np.frombuffer(payload + bytes(8 + BLOCK * LONGEST_CODE // 8), np.uint8).astype(np.uint32)
        peeks = raw[:-3] << 24 | raw[1:-2] << 16 | raw[2:-1] << 8 | raw[3:]
        at, out = np.array(checkpoints, np.int64), np.empty((min(BLOCK, n) if n else 0, len(checkpoints)), np.uint32)
        for k in range(len(out)):
            seen = (peeks[at >> 3] >> (32 - LONGEST_CODE - (at & 7)).astype(np.uint32)) & np.uint32((1 << LONGEST_CODE) - 1)
            out[k] = self.symbol[seen]
            at += self.size[seen]
        return out.T.reshape(-1)[:n]


def write_ids(docs: DataFrame, path: str, vocabulary: str, end_id: int) -> None:
    """Tokenizes once, in doc_id order: shards of plain ids, each with the counts of its ids."""
    kind = np.dtype("<u2" if end_id < 1 << 16 and vocabulary == VOCABULARY else "<u4")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, shard, before, size = TaskContext.get().partitionId(), 0, 0, 0
        end = np.array([end_id], "<u4").tobytes()
        held: list[tuple[int | None, bytes]] = []

        def row() -> pa.RecordBatch:
            ids = np.frombuffer(b"".join(b for _, b in held), "<u4")
            counts = np.bincount(ids)
            used = np.flatnonzero(counts)
            values = [part, shard, before, len(ids), [d for d, _ in held], [len(b) // 4 for _, b in held], used.tolist(), counts[used].tolist(), ids.astype(kind).tobytes()]
            kinds = [pa.int32(), pa.int32(), pa.int64(), pa.int64(), *[pa.list_(pa.int64())] * 4, pa.binary()]
            return pa.RecordBatch.from_arrays([pa.array([v], k) for v, k in zip(values, kinds, strict=True)], [x.split()[0] for x in PLAIN.split(", ")])

        for batch in (part for whole in batches for part in text_slices(whole, "text", 1 << 22)):
            for doc, ids in zip(batch.column("doc_id").to_pylist(), encoder(vocabulary, True).encode(batch.column("text").to_pylist()), strict=True):
                held.append((doc, ids + end))
                size += len(ids) // 4 + 1
                if size >= SHARD_IDS:
                    yield row()
                    shard, before, held, size = shard + 1, before + size, [], 0
        if held:
            yield row()

    docs.repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text").mapInArrow(run, PLAIN).write.option("compression", "zstd").parquet(path)


def write_tokens(docs: DataFrame, path: str, vocabulary: str = VOCABULARY, end_id: int = END_ID) -> None:
    """Writes the file set of docs (doc_id, text) to path. Null texts are empty; rows of one doc_id follow each other by text; null ids come first."""
    spark = docs.sparkSession
    write_ids(own_columns(docs, "doc_id", "text"), f"{path}/plain", vocabulary, end_id)
    plain = spark.read.parquet(f"{path}/plain")
    counted = plain.select(F.explode(F.arrays_zip("seen", "times")).alias("x")).groupBy("x.seen").agg(F.sum("x.times").alias("n")).toPandas()  # a row for each id of the vocabulary at most
    counts = np.zeros(int(counted["seen"].max()) + 1 if len(counted) else 1, np.int64)
    counts[counted["seen"].to_numpy(np.int64)] = counted["n"]
    bits = code_lengths(counts)
    spark.createDataFrame([(int(i), int(bits[i])) for i in np.flatnonzero(bits)], "id long, bits int").coalesce(1).write.parquet(f"{path}/codebook")
    lengths = bits.tobytes()  # of the vocabulary's size
    names = [x.split()[0] for x in SHARDS.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        book = Codebook(np.frombuffer(lengths, np.uint8))
        for batch in batches:
            for k in range(batch.num_rows):
                one = batch.slice(k, 1)
                raw, n = one.column("ids")[0].as_py(), one.column("n_ids")[0].as_py()
                payload, marks = book.encode(np.frombuffer(raw, f"<u{len(raw) // max(n, 1)}" if n else "<u4"))
                yield pa.RecordBatch.from_arrays([*(one.column(c) for c in names[:6]), pa.array([marks], pa.list_(pa.int64())), pa.array([payload], pa.binary())], names)

    plain.drop("seen", "times").mapInArrow(run, SHARDS).write.option("compression", "uncompressed").parquet(f"{path}/shards")


def read_tokens(spark: SparkSession, path: str, with_ids: bool = False) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32[, ids]) of every document in a file set."""
    book = spark.read.parquet(f"{path}/codebook").toPandas()  # of the vocabulary's size
    bits = np.zeros(int(book["id"].max()) + 1 if len(book) else 1, np.uint8)
    bits[book["id"].to_numpy(np.int64)] = book["bits"]
    lengths = bits.tobytes()
    shards = spark.read.parquet(f"{path}/shards")
    totals = shards.groupBy("part").agg(F.sum("n_ids").alias("n"))  # a row for each range partition
    totals = totals.select("part", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("part_start"))
    schema = "doc_id long, start long, n_tokens long, ids_crc32 long" + ", ids array<long>" * with_ids

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codes = Codebook(np.frombuffer(lengths, np.uint8))
        for batch in batches:
            for k in range(batch.num_rows):
                row = {name: batch.column(name)[k] for name in batch.schema.names}
                n = row["n_ids"].as_py()
                ids = codes.decode(row["payload"].as_py(), row["checkpoints"].values.to_numpy(), n).astype("<u4")
                sizes = row["doc_lengths"].values.to_numpy()
                ends = np.cumsum(sizes)
                first = row["part_start"].as_py() + row["ids_before"].as_py()
                raw = memoryview(ids.tobytes())
                out = {
                    "doc_id": row["doc_ids"].values,
                    "start": pa.array(first + ends - sizes, pa.int64()),
                    "n_tokens": pa.array(sizes, pa.int64()),
                    "ids_crc32": pa.array([zlib.crc32(raw[4 * (e - s) : 4 * e]) for s, e in zip(sizes, ends, strict=True)], pa.int64()),
                }
                if with_ids:
                    out["ids"] = pa.array([ids[e - s : e].astype(np.int64) for s, e in zip(sizes, ends, strict=True)], pa.list_(pa.int64()))
                yield pa.RecordBatch.from_pydict(out)

    return shards.join(F.broadcast(totals), "part").mapInArrow(run, schema)  # totals: as many rows as the write had partitions
