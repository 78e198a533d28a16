"""Language-model scores from tries of word trigrams, sharded by context.

Every distinct token is a symbol: the most frequent ones by their rank, all others by 62
bits of a hash. Each token starts one entry (itself and the two after it); entries go,
packed by thousands, to shards by their first two symbols (by the first alone where that
is rare). A shard numbers its symbols, builds an Elias-Fano trie of what training texts
sent, and settles all entries in one pass: those of training by the nodes that they are,
the others by a search in the mapped trie.

    P(w | u, v) = c(u v w) / (c(u v) + KEPT)  if training has u v w,  else KEPT / (c(u v) + KEPT) x P(w | v)
    P(w | v)    = c(v w) / (c(v) + KEPT)      if training has v w,    else KEPT / (c(v) + KEPT) x P(w)
    P(w)        = (c(w) + 1) / (N + V + 1)

A text starts with two symbols of its own and ends with an end token. The levels keep
probabilities and back-off weights as 16-bit codes; counts of tokens are exact.

No task holds the whole model. Two things go to every task, both of bounded size: the
MOST_FREQUENT tokens with their counts, and nothing that grows with the texts. Entries
whose first two symbols are both among the HOT most frequent are dealt to SALTS shards by
their third; their pairs' counts go to each of those.
"""

from __future__ import annotations

import math
import pickle
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
import zstandard
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pathsieve.llm.elias_fano import LOWEST, TOP, Trie, coded, decoded
from pathsieve.llm.shared import LOWER, UPPER, forget_tokenizers, fresh_path, own_columns, text_slices, trim

MOST_FREQUENT, HOT, SALTS, KEPT = 400_000, 16, 16, 1.0
#: Bytes of text in a slice, and for each shard.
SLICE, SHARD = 1 << 22, 1 << 22
#: Symbols: after the end, two and one before the start, the end; frequent tokens follow, all others have the bit RARE.
PAD, START2, START1, END, FIRST = 0, 1, 2, 3, 4
RARE = 1 << 62
_SPACES = b"\t\n\x0b\x0c\r"
_PLAIN = bytes.maketrans(UPPER.encode() + _SPACES, LOWER.encode() + b" " * len(_SPACES))


def held_out(doc_id: Column, folds: int = 7, fold: int = 2) -> Column:
    """crc32 of the id as text, modulo folds; a null id counts as ''."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % folds == fold


def _tokens(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray, list[bytes]]:
    """(distinct number of each word, text number of each word, distinct words)."""
    raws = pa.array([(t or "").encode().translate(_PLAIN) for t in texts], pa.large_binary())
    lists = pc.split_pattern(raws, b" ")
    each = lists.values.dictionary_encode()
    words = each.dictionary.to_pylist()
    index = each.indices.to_numpy()
    owner = np.repeat(np.arange(len(texts)), np.diff(lists.offsets.to_numpy()))
    if b"" in words:
        keep = index != words.index(b"")
        index, owner = index[keep], owner[keep]
    return index, owner, words


def token_counts(texts: DataFrame) -> DataFrame:
    """(word binary, n) over all texts, without end tokens."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in text_slices(whole, "text", 1 << 21):
                index, _, words = _tokens(batch.column("text").to_pylist())
                n = np.bincount(index, minlength=len(words))
                used = np.flatnonzero(n)
                yield pa.RecordBatch.from_arrays([pa.array([words[k] for k in used], pa.binary()), pa.array(n[used], pa.int64())], ["word", "n"])

    return texts.select("text").mapInArrow(run, "word binary, n long").groupBy("word").agg(F.sum("n").alias("n"))


def _packed(*values: object) -> bytes:
    """Arrays of eight bytes a number are laid out by the rank of their bytes, which packs small and repeated numbers well."""
    flat = [(v.dtype.str, v.view(np.uint8).reshape(-1, 8).T.tobytes()) if isinstance(v, np.ndarray) and v.itemsize == 8 else v for v in values]
    return zstandard.compress(pickle.dumps(flat, 5), 1)


def _unpacked(raw: bytes) -> list:
    flat = pickle.loads(zstandard.decompress(raw))
    return [np.frombuffer(v[1], np.uint8).reshape(8, -1).T.copy().view(v[0]).ravel() if isinstance(v, tuple) else v for v in flat]


def _mixed(x: np.ndarray) -> np.ndarray:
    x = x.astype(np.uint64)
    x = (x ^ x >> np.uint64(31)) * np.uint64(0x9E3779B97F4A7C15)
    return x ^ x >> np.uint64(29)


def shard_of(u: np.ndarray, v: np.ndarray, w: np.ndarray, shards: int) -> np.ndarray:
    """By the first symbol if that is rare, else by the first two, and by a share of the third where both are hot."""
    both, hot = _mixed(u) ^ np.where(u < RARE, _mixed(_mixed(v)), 0).astype(np.uint64), (u < FIRST + HOT) & (v < FIRST + HOT)
    salt = np.where(hot, _mixed(w) % np.uint64(SALTS) + np.uint64(1), 0).astype(np.uint64)
    return (_mixed(_mixed(both + salt)) % np.uint64(shards)).astype(np.int64)


def entries(symbols: np.ndarray, owner: np.ndarray, texts: int) -> tuple[np.ndarray, ...]:
    """(u, v, w, text number): the entries of texts given as the symbols of their tokens; of n tokens n + 2, the first two start before the text."""
    n = np.bincount(owner, minlength=texts)
    slots = n + 4  # two starts, the tokens, end, pad
    at = np.cumsum(slots) - slots
    laid = np.zeros(int(slots.sum()), np.int64)
    laid[at], laid[at + 1], laid[at + slots - 2] = START2, START1, END
    laid[np.repeat(at + 2 - (np.cumsum(n) - n), n) + np.arange(len(symbols))] = symbols
    each = n + 2
    first = np.repeat(at - (np.cumsum(each) - each), each) + np.arange(int(each.sum()))
    return laid[first], laid[first + 1], laid[first + 2], np.repeat(np.arange(texts), each)


def _hot_pairs(u: np.ndarray, v: np.ndarray, shards: int) -> dict[int, tuple[np.ndarray, ...]]:
    """shard -> (u, v, count) of the hot pairs whose entries may go there."""
    size = FIRST + HOT
    hot = (u < size) & (v < size)
    if not hot.any():
        return {}
    pair, n = np.unique(u[hot] * size + v[hot], return_counts=True)
    a, b, c = (np.repeat(x, SALTS) for x in (pair // size, pair % size, n))
    both = _mixed(a) ^ _mixed(_mixed(b))
    to = (_mixed(_mixed(both + np.tile(np.arange(1, SALTS + 1, dtype=np.uint64), len(pair)))) % np.uint64(shards)).astype(np.int64)
    _, keep = np.unique(to * size * size + a * size + b, return_index=True)
    a, b, c, to = a[keep], b[keep], c[keep], to[keep]  # ascending by shard
    cuts = np.flatnonzero(np.r_[True, to[1:] != to[:-1]])
    return {int(to[i]): (a[i:j], b[i:j], c[i:j]) for i, j in zip(cuts, [*cuts[1:], len(to)], strict=True)}


class Shard:
    """The trie of one shard's training entries, and the answers to all its entries."""

    def __init__(self, u: np.ndarray, v: np.ndarray, w: np.ndarray, pairs: tuple[np.ndarray, ...], frequent: np.ndarray, texts: int) -> None:
        """Entries of training; pairs: (u, v, count) of hot ones; frequent: counts by symbol - FIRST."""
        self.frequent = np.r_[0, texts, texts, texts, frequent].astype(np.int64)
        symbols, number = np.unique(np.concatenate([u, v, w, *pairs[:2]]), return_inverse=True)
        a, b, c, hot_a, hot_b = np.split(number, np.cumsum([len(u), len(v), len(w), len(pairs[0])]))
        size = max(len(symbols), 1)
        pair, of = np.unique(np.r_[a * size + b, hot_a * size + hot_b], return_inverse=True)
        mine, hot = of[: len(a)], of[len(a) :]
        c2 = np.bincount(mine, minlength=len(pair))
        c2[hot] = 0
        np.add.at(c2, hot, pairs[2])
        triple, self.own, c3 = np.unique(mine * size + c, return_inverse=True, return_counts=True)
        first = np.unique(pair // size)
        known = symbols[first]
        c1 = np.where(known < RARE, self._frequent(known), np.bincount(a, minlength=size)[first])
        parent = np.searchsorted(first, pair // size)
        likely = [coded(np.log10(np.maximum(c2, 1) / (c1[parent] + KEPT))), coded(np.log10(c3 / (c2[triple // size] + KEPT)))]
        trie = Trie.build(symbols, first, parent * size + pair % size, triple, c1, likely, coded(np.log10(KEPT / (c2 + KEPT))))
        self.trie = Trie.mapped(trie.dump())

    def _frequent(self, symbols: np.ndarray) -> np.ndarray:
        return self.frequent[np.where(symbols < RARE, symbols, 0)]

    def answers(self, u: np.ndarray, v: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """For entries: code of P(w | u, v), or -1 - code of the weight left; the same of P(v | u); count of u."""
        one, two, three = self.trie.walk(u, v, w)
        count = np.where(u < RARE, self._frequent(u), np.where(one >= 0, self.trie.counts[one], 0) if len(self.trie.counts) else 0)
        left = -1 - coded(np.log10(KEPT / (count + KEPT))).astype(np.int32)
        if not len(self.trie.counts):
            return np.full(len(u), -1, np.int32), left, count
        second, third = self.trie.likely
        p3 = np.where(three >= 0, third[three].astype(np.int32) if len(third) else -1, np.where(two >= 0, -1 - self.trie.backoff[two].astype(np.int32), -1))
        return p3, np.where(two >= 0, second[two].astype(np.int32), left), count


def score(docs: DataFrame, learn: Column) -> DataFrame:
    """A row for each row of docs (doc_id, text): (doc_id, learnt, n_tokens, n_known, train_tokens, base_score, score).

    learn: which rows the model learns from, over columns of docs (null: not). Null texts
    are empty: their end is their one token. Repeated rows count as often as they stand,
    and get a row each. base_score: log10 of (c + 1) / (N + V + 1), summed over tokens.
    """
    spark: SparkSession = docs.sparkSession
    path = fresh_path(spark, "model")
    docs = docs.select("doc_id", "text", F.coalesce(learn, F.lit(False)).alias("learnt"))
    texts, size = docs.agg(F.count_if("learnt"), F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()
    shards = -(-size // SHARD) or 1
    token_counts(docs.where("learnt")).write.parquet(f"{path}/counts")
    counts = spark.read.schema("word binary, n long").parquet(f"{path}/counts")
    words, kinds = counts.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count(F.lit(1))).first()
    steps = counts.groupBy(F.floor(F.log2("n") * 8).alias("b")).agg(F.count(F.lit(1)).alias("k"), F.min("n").alias("least")).orderBy(F.desc("b")).collect()  # a few hundred rows at most
    floor, taken = 1 << 62, 0
    for r in steps:
        taken += r["k"]
        if taken > MOST_FREQUENT:
            break
        floor = r["least"]
    top = counts.where(F.col("n") >= floor).toArrow().sort_by([("n", "descending"), ("word", "ascending")])  # MOST_FREQUENT rows at most
    head = spark.sparkContext.broadcast((top.column("word").to_pylist(), top.column("n").to_numpy()))
    tokens, distinct = words + texts, kinds + (texts > 0)
    unit = math.log10(tokens + distinct + 1)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Each slice's entries by shard; and one row with what is known of the slice, which passes through some shard."""
        forget_tokenizers()
        frequent, n_of = head.value
        place = {w: FIRST + k for k, w in enumerate(frequent)}
        known = np.log10(np.r_[0, 0, 0, texts, n_of] + 1.0)  # by symbol
        turn = TaskContext.get().partitionId() << 32
        for whole in batches:
            for batch in text_slices(whole, "text", SLICE):
                rows, learnt = batch.num_rows, batch.column("learnt").to_numpy(zero_copy_only=False)
                index, owner, kinds_here = _tokens(batch.column("text").to_pylist())
                symbol = np.array([place.get(w) or RARE | xxhash.xxh3_64_intdigest(w) >> 2 for w in kinds_here], np.int64)[index]
                u, v, w, of = entries(symbol, owner, rows)
                to, train = shard_of(u, v, w, shards), learnt[of]
                pairs = _hot_pairs(u[train], v[train], shards)
                order = np.argsort(to, kind="stable")
                cuts = np.searchsorted(to[order], np.arange(shards + 1))
                some = symbol < RARE
                base = np.bincount(owner[some], known[symbol[some]], rows) + known[END]
                held = np.flatnonzero(~learnt[owner])
                p1 = np.where(symbol[held] < RARE, known[np.where(symbol[held] < RARE, symbol[held], 0)], np.nan)
                ids = batch.column("doc_id")
                facts = _packed(ids.is_null().to_numpy(zero_copy_only=False), ids.fill_null(0).to_numpy().astype(np.int64), learnt, np.bincount(owner, minlength=rows), np.bincount(owner[some], minlength=rows) + (texts > 0), base, to[~train], p1)
                out = [(turn % shards, turn, 0, facts)]
                for k in range(shards):
                    at = order[cuts[k] : cuts[k + 1]]
                    if len(at) or k in pairs:
                        out.append((k, turn, 1, _packed(u[at], v[at], w[at], of[at], train[at], *pairs.get(k, (np.zeros(0, np.int64),) * 3))))
                yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*out, strict=True), (pa.int64(), pa.int64(), pa.int32(), pa.binary()), strict=True)], ["shard", "slice", "kind", "payload"])
                turn += 1

    def settle(rows: list[tuple[int, bytes]]) -> Iterator[tuple[int, int, bytes]]:
        parts = [_unpacked(raw) for _, raw in rows]
        u, v, w, of, train = (np.concatenate([p[k] for p in parts]) for k in range(5))
        shard = Shard(u[train], v[train], w[train], tuple(np.concatenate([p[k] for p in parts]) for k in (5, 6, 7)), head.value[1], texts)
        code = np.where(w[train] == PAD, 0, shard.trie.likely[1][shard.own].astype(np.int64) if train.any() else 0)
        p3, p2, count = shard.answers(u[~train], v[~train], w[~train])
        rare = np.zeros(len(u), np.int64)
        rare[~train] = count
        known = train & (u >= RARE)
        if known.any():
            symbols, number, n = np.unique(u[known], return_inverse=True, return_counts=True)
            rare[known] = n[number]
        at = np.cumsum([0, *(len(p[0]) for p in parts)])
        taught, asked = np.cumsum(np.r_[0, train]), np.cumsum(np.r_[0, ~train])
        for (slice_id, _), i, j in zip(rows, at[:-1], at[1:], strict=True):
            mine = train[i:j]
            docs_here, inverse = np.unique(of[i:j][mine], return_inverse=True)
            sums = np.bincount(inverse, code[taught[i] : taught[j]], len(docs_here)).astype(np.int64)
            low = np.flatnonzero(known[i:j]) + i
            a, b = asked[i], asked[j]
            yield slice_id, 1, _packed(docs_here, sums, of[low], rare[low], p3[a:b], p2[a:b], count[a:b])

    def shard_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come sorted by shard."""
        names = ["shard", "slice", "kind", "payload"]
        now, held = None, []

        def ready(some: list) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([r[0] for r in some], pa.int64()), pa.array([r[1] for r in some], pa.int64()), pa.array([r[2] for r in some], pa.binary())], ["slice", "shard", "payload"])

        for batch in batches:
            for shard, slice_id, kind, raw in zip(*(batch.column(c).to_pylist() for c in names), strict=True):
                if shard != now and held:
                    yield ready([(s, now, x) for s, _, x in settle(held)])
                    held = []
                    trim()
                now = shard
                if kind:
                    held.append((slice_id, raw))
                else:
                    yield ready([(slice_id, -1, raw)])
        if held:
            yield ready([(s, now, x) for s, _, x in settle(held)])

    def sum_up(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come sorted by slice and shard, the slice's own row (shard -1) first."""
        now, facts, parts = None, None, []

        def ready() -> pa.RecordBatch:
            missing, ids, learnt, n, n_known, base, to, p1 = facts
            rows = len(ids)
            codes, answers = np.zeros(rows), np.zeros((3, len(to)), np.int64)
            for shard, raw in parts:
                docs_here, sums, of, count, *rest = _unpacked(raw)
                codes[docs_here] += sums
                base += np.bincount(of, np.log10(count + 1.0), rows)
                n_known += np.bincount(of, count > 0, rows).astype(np.int64)
                answers[:, to == shard] = rest
            total = codes * (-LOWEST / TOP)
            held = np.flatnonzero(~learnt)
            if len(held):
                p3, p2, count = answers
                size = n[held]
                start = np.cumsum(size + 2) - (size + 2)  # of a text's entries
                doc = np.repeat(np.arange(len(held)), size + 1)  # of each token, ends with them
                at = np.arange(int((size + 1).sum())) - np.repeat(np.cumsum(size + 1) - (size + 1), size + 1)
                entry = start[doc] + at
                word = at < size[doc]
                alone = np.full(len(doc), math.log10(texts + 1))
                of_word = count[np.minimum(entry + 2, len(count) - 1)][word]
                rare = np.isnan(p1)
                alone[word] = np.where(rare, np.log10(of_word + 1.0), p1)
                base += np.bincount(held[doc[word][rare]], np.log10(of_word[rare] + 1.0), rows)
                n_known += np.bincount(held[doc[word][rare]], of_word[rare] > 0, rows).astype(np.int64)
                three, two = p3[entry], p2[entry + 1]
                shorter = np.where(two >= 0, decoded(two), decoded(-1 - two) + alone - unit)
                total += np.bincount(held[doc], np.where(three >= 0, decoded(three), decoded(-1 - three) + shorter), rows)
            n = n + 1
            return pa.RecordBatch.from_arrays([pa.array(ids, pa.int64(), mask=missing), pa.array(learnt), pa.array(n, pa.int64()), pa.array(n_known, pa.int64()), pa.array(np.full(rows, tokens), pa.int64()), pa.array(base - n * unit), pa.array(total)], [x.split()[0] for x in SCORES.split(", ")])

        for batch in batches:
            for slice_id, shard, raw in zip(*(batch.column(c).to_pylist() for c in ("slice", "shard", "payload")), strict=True):
                if slice_id != now:
                    if facts is not None:
                        yield ready()
                    now, facts, parts = slice_id, _unpacked(raw), []
                else:
                    parts.append((shard, raw))
        if facts is not None:
            yield ready()

    dealt = docs.mapInArrow(deal, "shard long, slice long, kind int, payload binary")
    answered = dealt.repartition(shards, "shard").sortWithinPartitions("shard", "slice", "kind").mapInArrow(shard_rows, "slice long, shard long, payload binary")
    return answered.repartition("slice").sortWithinPartitions("slice", "shard").mapInArrow(sum_up, SCORES)


SCORES = "doc_id long, learnt boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"
