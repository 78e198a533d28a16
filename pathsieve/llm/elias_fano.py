"""Elias-Fano sequences and an n-gram trie over them, in arrays that can be memory-mapped.

A monotone sequence keeps the low bits of each value packed and the high parts in unary,
about 2 bits each. A level of the trie is the sequence parent * symbols + symbol of its
nodes, so that the children of a node are a stretch of it, found by a sequence of
monotone pointers and searched for the symbol. Symbols are numbered within a trie, by
their place in a sorted list; the first level is a sorted list of such numbers, since its
one stretch is the whole level. Log probabilities and back-off weights are codes of 16 bits.
"""

from __future__ import annotations

import io
import json
import tempfile
from dataclasses import dataclass

import numpy as np

#: Codes stand for log10 values from 0 down to -LOWEST.
LOWEST, TOP = 12.0, (1 << 16) - 1


@dataclass(frozen=True)
class EliasFano:
    n: int
    low_bits: int
    low: np.ndarray  # uint64 words of packed low bits
    high: np.ndarray  # uint64 words, a one for each value
    ranks: np.ndarray  # ones before each word of high

    @classmethod
    def build(cls, values: np.ndarray, universe: int) -> EliasFano:
        n = len(values)
        low_bits = max(0, int(np.floor(np.log2(max(universe, 1) / max(n, 1))))) if n else 0
        values = values.astype(np.uint64)
        low = np.zeros(n * low_bits // 64 + 2, np.uint64)
        if low_bits and n:
            part, at = values & np.uint64((1 << low_bits) - 1), np.arange(n, dtype=np.uint64) * np.uint64(low_bits)
            np.bitwise_or.at(low, (at >> np.uint64(6)).astype(np.int64), part << (at & np.uint64(63)))
            spill = (at & np.uint64(63)) + np.uint64(low_bits) > 64
            np.bitwise_or.at(low, (at[spill] >> np.uint64(6)).astype(np.int64) + 1, part[spill] >> (np.uint64(64) - (at[spill] & np.uint64(63))))
        ones = (values >> np.uint64(low_bits)).astype(np.int64) + np.arange(n)
        high = np.zeros((int(ones[-1]) if n else 0) // 64 + 1, np.uint64)
        np.bitwise_or.at(high, ones >> 6, np.uint64(1) << (ones & 63).astype(np.uint64))
        ranks = np.r_[0, np.cumsum(np.bitwise_count(high))].astype(np.int64)
        return cls(n, low_bits, low, high, ranks)

    def get(self, index: np.ndarray) -> np.ndarray:
        """Values at places 0 .. n - 1."""
        word = np.searchsorted(self.ranks, index, "right") - 1
        left = index - self.ranks[word]
        bits, at = self.high[word].copy(), np.zeros(len(index), np.int64)
        for size in (32, 16, 8, 4, 2, 1):  # the place of the left-th one in the word
            count = np.bitwise_count(bits & np.uint64((1 << size) - 1)).astype(np.int64)
            over = left >= count
            left = np.where(over, left - count, left)
            bits = np.where(over, bits >> np.uint64(size), bits)
            at += np.where(over, size, 0)
        high = word * 64 + at - index
        if not self.low_bits:
            return high
        place = index.astype(np.uint64) * np.uint64(self.low_bits)
        k, shift = (place >> np.uint64(6)).astype(np.int64), place & np.uint64(63)
        low = self.low[k] >> shift
        low = np.where(shift + np.uint64(self.low_bits) > 64, low | self.low[k + 1] << ((np.uint64(64) - shift) & np.uint64(63)), low)
        return high << self.low_bits | (low & np.uint64((1 << self.low_bits) - 1)).astype(np.int64)

    def find(self, values: np.ndarray, begin: np.ndarray, end: np.ndarray) -> np.ndarray:
        """Place of each value in [begin, end), or -1: a successor search in each stretch."""
        low, high = begin.copy(), end.copy()
        while True:
            live = np.flatnonzero(low < high)
            if not len(live):
                break
            mid = (low[live] + high[live]) >> 1
            less = self.get(mid) < values[live]
            low[live[less]] = mid[less] + 1
            high[live[~less]] = mid[~less]
        inside = np.flatnonzero(low < end)
        out = np.full(len(values), -1, np.int64)
        hit = inside[self.get(low[inside]) == values[inside]]
        out[hit] = low[hit]
        return out


def coded(log10: np.ndarray) -> np.ndarray:
    """Codes of log10 values of 0 or less; the nearest step of LOWEST / TOP."""
    return np.rint(np.clip(-log10, 0, LOWEST) * (TOP / LOWEST)).astype(np.uint16)


def decoded(codes: np.ndarray) -> np.ndarray:
    return codes * (-LOWEST / TOP)


def _places(ordered: np.ndarray, values: np.ndarray) -> np.ndarray:
    """Places of values in an ascending list, -1 where they aren't in it."""
    if not len(ordered):
        return np.full(len(values), -1, np.int64)
    at = np.minimum(np.searchsorted(ordered, values), len(ordered) - 1)
    return np.where(ordered[at] == values, at, -1)


@dataclass
class Trie:
    """n-grams of up to three symbols; nodes and pointers are those of the second and third level. counts: of the first level's nodes; likely: codes of log10 probability of the second and third level's last symbol; backoff: codes of the weight that a second-level node leaves to shorter contexts."""

    symbols: np.ndarray
    firsts: np.ndarray
    nodes: list[EliasFano]
    pointers: list[EliasFano]
    counts: np.ndarray
    likely: list[np.ndarray]
    backoff: np.ndarray

    @classmethod
    def build(cls, symbols: np.ndarray, firsts: np.ndarray, pairs: np.ndarray, triples: np.ndarray, counts: np.ndarray, likely: list[np.ndarray], backoff: np.ndarray) -> Trie:
        """symbols: ascending; firsts: their numbers; pairs: (place in firsts) * symbols + number; triples: (place in pairs) * symbols + number; all ascending."""
        size = max(len(symbols), 1)
        nodes, pointers, parents = [], [], len(firsts)
        for level in (pairs, triples):
            nodes.append(EliasFano.build(level, max(parents, 1) * size))
            pointers.append(EliasFano.build(np.searchsorted(level, np.arange(parents + 1) * size), len(level) + 1))
            parents = len(level)
        return cls(symbols, firsts, nodes, pointers, counts, likely, backoff)

    def walk(self, u: np.ndarray, v: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Nodes along the n-grams of these symbols, level by level; -1 from where there is none. A node's children are searched in its stretch alone."""
        node = _places(self.firsts, _places(self.symbols, u))
        out = [node]
        for level, some in enumerate((v, w)):
            number = _places(self.symbols, some)
            ok = np.flatnonzero((node >= 0) & (number >= 0))
            asked, inverse = np.unique(node[ok] * max(len(self.symbols), 1) + number[ok], return_inverse=True)
            parent = asked // max(len(self.symbols), 1)
            node = np.full(len(node), -1, np.int64)
            node[ok] = self.nodes[level].find(asked, self.pointers[level].get(parent), self.pointers[level].get(parent + 1))[inverse]
            out.append(node)
        return tuple(out)

    # -- as one block of bytes ---------------------------------------------------------

    def dump(self) -> bytes:
        sequences = [e for k in range(2) for e in (self.nodes[k], self.pointers[k])]
        arrays = [a for e in sequences for a in (e.low, e.high, e.ranks)] + [self.symbols, self.firsts, self.counts, *self.likely, self.backoff]
        head = json.dumps({"plan": [[e.n, e.low_bits] for e in sequences], "arrays": [[a.dtype.str, len(a)] for a in arrays]}).encode()
        out = io.BytesIO()
        out.write(len(head).to_bytes(8, "little") + head)
        for a in arrays:
            out.write(bytes(-out.tell() % 8) + a.tobytes())
        return out.getvalue()

    @classmethod
    def mapped(cls, raw: bytes) -> Trie:
        """The block in a temporary file without a name, mapped into memory. The file is one task's own; a task that starts anew writes it anew."""
        held = tempfile.TemporaryFile()
        held.write(raw)
        held.flush()
        block = np.memmap(held, np.uint8, "r")
        size = int.from_bytes(block[:8].tobytes(), "little")
        head = json.loads(block[8 : 8 + size].tobytes())
        at, arrays = 8 + size, []
        for kind, n in head["arrays"]:
            at += -at % 8
            width = np.dtype(kind).itemsize
            arrays.append(block[at : at + n * width].view(kind))
            at += n * width
        levels = [EliasFano(*plan, *arrays[3 * k : 3 * k + 3]) for k, plan in enumerate(head["plan"])]
        symbols, firsts, counts, second, third, backoff = arrays[3 * len(levels) :]
        return cls(symbols, firsts, levels[::2], levels[1::2], counts, [second, third], backoff)
