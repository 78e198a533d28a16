"""SimHash near-duplicates by vantage-point trees.

Distances of random 64-bit fingerprints crowd around 32, so that a tree over whole
fingerprints prunes little at radius 4 (README has figures). The forest therefore starts
with projections: the bits are cut into blocks, and fingerprints at most r apart agree on
all but r of them, so that for some choice of the other blocks their distance in that
projection is 0. Each choice is a tree, each value of its bits a branch; there are as
many blocks as keep an average branch below `BRANCH`.

A branch is a vantage-point tree over full Hamming distances. The vantage point is the
point, of a few tried, whose distances spread most; the median distance parts the rest
into near and far. By the triangle bound a link can cross that boundary only between
points within r of it on either side; those two zones are parted again by vantage points
of their own until a block of pairs is small. A branch that is too large for one task is
parted first by distance shells around a vantage point, in joins: a point is a member of
its own shell, and a visitor of every other shell that its distance, r more or less,
reaches.

A branch hands on a spanning forest of its links, so that a cluster of n fingerprints
gives n - 1 rows, not n squared. Only different fingerprints take part: copies of one
text are one point however many there are.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathsieve.llm.components import components
from pathsieve.llm.shared import cut, forget_tokenizers, masked, own_columns, text_slices

RADIUS, SHINGLE, SEED = 4, 4, 42
#: Points of an average branch; of a branch that one task takes; of a block of a tree that isn't parted; pairs looked at in one step; width of a shell; vantage points tried.
BRANCH, LARGE, LEAF, PAIRS, SHELL, TRIED = 4096, 1 << 17, 64, 1 << 16, 8, 8


def _signed(x: int) -> int:
    return x - (1 << 64) if x >= 1 << 63 else x


def as_hex(fingerprint: Column) -> Column:
    """16 lower-case hex digits."""
    return F.lower(F.lpad(F.hex(fingerprint), 16, "0"))


def fingerprint_batch(texts: list[str | None], size: int = SHINGLE) -> np.ndarray:
    """64-bit fingerprints: a bit is set if it is in over half the shingles' XXH64."""
    hashes: list[int] = []
    counts = []
    digest = xxhash.xxh64_intdigest
    for text in texts:
        w = (text or "").encode().lower().split()  # bytes: A-Z and ASCII white space alone
        if len(w) > size:
            joined = b" ".join(w)
            ends = np.cumsum(np.fromiter(map(len, w), np.int64, len(w)) + 1)
            starts = (ends[: len(w) - size + 1] - np.fromiter(map(len, w[: len(w) - size + 1]), np.int64) - 1).tolist()
            hashes += [digest(joined[a:b], SEED) for a, b in zip(starts, (ends[size - 1 :] - 1).tolist(), strict=True)]
            counts.append(len(w) - size + 1)
        elif w:
            hashes.append(digest(b" ".join(w), SEED))
            counts.append(1)
        else:
            counts.append(0)
    n = np.array(counts, np.int64)
    out = np.zeros(len(n), np.uint64)
    if not hashes:
        return out
    raw = np.array(hashes, np.uint64).view(np.uint8).reshape(-1, 8)
    ends = np.cumsum(n)
    votes = np.zeros((len(n), 64), np.int64)
    for at in range(0, len(raw), 1 << 18):  # bounded, whatever a text's length
        bits = np.unpackbits(raw[at : at + (1 << 18)], axis=1, bitorder="little")
        first, last = np.searchsorted(ends, at, "right"), np.searchsorted(ends, at + len(bits) - 1, "right")
        docs = np.arange(first, last + 1)[n[first : last + 1] > 0]
        votes[docs] += np.add.reduceat(bits, np.maximum(ends[docs] - n[docs] - at, 0), axis=0, dtype=np.int64)
    return np.packbits(2 * votes > n[:, None], axis=1, bitorder="little").view(np.uint64).ravel()


def fingerprints(docs: DataFrame, columns: list[str] | None = None) -> DataFrame:
    """docs' columns (default doc_id) with `fingerprint` (64 bits in a signed long). A null or empty text has fingerprint 0."""
    keep = columns or ["doc_id"]
    rows = own_columns(docs, *keep, *([] if "text" in keep else ["text"]))
    fields = [rows.schema[c] for c in keep]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forget_tokenizers()
        for whole in batches:
            for batch in text_slices(whole, "text"):
                prints = fingerprint_batch(batch.column("text").to_pylist()).view(np.int64)
                yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), pa.array(prints)], [*keep, "fingerprint"])

    schema = type(rows.schema)(fields).add("fingerprint", "long")
    return rows.mapInArrow(run, schema)


def blocks_for(points: int, radius: int = RADIUS) -> int:
    """The least number of blocks at which an average branch has at most BRANCH points."""
    blocks = radius + 1
    while blocks < 16 and points > BRANCH << 64 * (blocks - radius) // blocks:
        blocks += 1
    return blocks


def projections(blocks: int, radius: int = RADIUS) -> list[int]:
    """The bits of each choice of blocks - radius blocks."""
    edges = [round(k * 64 / blocks) for k in range(blocks + 1)]
    masks = [((1 << b) - 1) ^ ((1 << a) - 1) for a, b in zip(edges, edges[1:], strict=False)]
    return [_signed(sum(masks[k] for k in some)) for some in combinations(range(blocks), blocks - radius)]


class Tree:
    """Links between points (different fingerprints) within the radius, as a forest over their places. examined: pairs whose distance was taken, vantage points' among them."""

    def __init__(self, points: np.ndarray, radius: int = RADIUS) -> None:
        self.points, self.radius, self.examined = points, radius, 0
        self.root = list(range(len(points)))
        self.forest: list[tuple[int, int]] = []

    def _find(self, x: int) -> int:
        while self.root[x] != x:
            self.root[x] = x = self.root[self.root[x]]
        return x

    def _join(self, x: int, y: int) -> None:
        a, b = self._find(x), self._find(y)
        if a != b:
            self.root[max(a, b)] = min(a, b)
            self.forest.append((x, y))

    def _vantage(self, at: np.ndarray) -> np.ndarray:
        """Distances of the points at these places to the vantage point."""
        tried = self.points[at[:: max(1, len(at) // TRIED)][:TRIED]]
        some = self.points[at[:: max(1, len(at) // 64)]]
        spread = np.bitwise_count(tried[:, None] ^ some[None, :]).var(1)
        self.examined += len(at)
        return np.bitwise_count(self.points[at] ^ tried[spread.argmax()]).astype(np.int64)

    def link(self, at: np.ndarray) -> None:
        """All links among the points at these places."""
        todo = [at]
        while todo:
            at = todo.pop()
            if len(at) <= LEAF:
                self._pairs(at, at)
                continue
            d = self._vantage(at)
            middle = int(np.median(d))
            near = d <= middle
            if near.all():
                near = d < middle
            if not near.any():
                self._pairs(at, at)
                continue
            edge = int(d[near].max())
            todo += [at[near], at[~near]]
            self.across(at[near & (d > edge - self.radius)], at[~near & (d <= edge + self.radius)])

    def across(self, a: np.ndarray, b: np.ndarray) -> None:
        """All links between two sets of places."""
        todo = [(a, b)]
        while todo:
            a, b = todo.pop()
            if not len(a) or not len(b):
                continue
            if len(a) * len(b) <= LEAF * LEAF:
                self._pairs(a, b)
                continue
            d = self._vantage(np.r_[a, b])
            x, y = d[: len(a)], d[len(a) :]
            middle = int(np.median(d))
            parts = [(a[x <= middle], b[y <= middle + self.radius]), (a[x > middle], b[y > middle - self.radius])]
            if sum(len(p) * len(q) for p, q in parts) > 0.9 * len(a) * len(b):  # the bound no longer prunes
                self._pairs(a, b)
            else:
                todo += parts

    def _pairs(self, a: np.ndarray, b: np.ndarray) -> None:
        rows = max(1, PAIRS // max(len(b), 1))
        for k in range(0, len(a), rows):
            some = a[k : k + rows]
            self.examined += len(some) * len(b)
            close = np.bitwise_count(self.points[some][:, None] ^ self.points[b][None, :]) <= self.radius
            if a is b:
                close[some[:, None] == b[None, :]] = False
            hit = np.flatnonzero(close.any(1))
            if not len(hit):
                continue
            # by representatives: a row's links are one star, and rows that share a point meet in it
            label = np.minimum.reduce(np.where(close[hit], b[None, :], len(self.points)), axis=1)
            for x, y in zip(some[hit].tolist(), label.tolist(), strict=True):
                self._join(x, y)
            first = np.array([self._find(x) for x in some[hit].tolist()])
            seen = close[hit]
            for j in np.flatnonzero(seen.any(0)).tolist():
                for r in np.unique(first[seen[:, j]]).tolist():
                    self._join(r, int(b[j]))


def _branches(radius: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Rows (branch, fingerprint, visits) sorted by branch, to links (a, b). Visitors are held against members, not against each other."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def solve(points: np.ndarray, visits: np.ndarray) -> list[tuple[int, int]]:
            if len(points) < 2:
                return []
            tree = Tree(points.view(np.uint64), radius)
            if not visits.any():
                tree.link(np.arange(len(points)))
            else:
                home, other = np.flatnonzero(~visits), np.flatnonzero(visits)
                tree.link(home)
                tree.across(home, other)
            return [(int(points[x]), int(points[y])) for x, y in tree.forest]

        rest: list[tuple[np.ndarray, ...]] = []
        for batch in batches:
            branch, points, visits = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("branch", "fingerprint", "visits"))
            rest.append((branch, points, visits))
            branch, points, visits = (np.concatenate([r[k] for r in rest]) for k in range(3))
            cuts = np.flatnonzero(np.diff(branch)) + 1  # the last branch may go on in the next batch
            found = [x for a, b in zip([0, *cuts[:-1]], cuts, strict=True) if b - a > 1 for x in solve(points[a:b], visits[a:b])] if len(cuts) else []
            last = cuts[-1] if len(cuts) else 0
            rest = [(branch[last:], points[last:], visits[last:])]
            yield _link_rows(found)
        if rest:
            yield _link_rows(solve(*(np.concatenate([r[k] for r in rest]) for k in (1, 2))))

    return run


def _link_rows(found: list[tuple[int, int]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([min(x) for x in found], pa.int64()), pa.array([max(x) for x in found], pa.int64())], ["a", "b"])


def _parted(rows: DataFrame, sizes: DataFrame, radius: int) -> DataFrame:
    """Large branches by shells around a point of each. rows: (branch, fingerprint, visits); sizes: (branch, vantage)."""
    d = F.bit_count(F.col("fingerprint").bitwiseXOR(F.col("vantage")))
    at = rows.join(sizes, "branch").select("branch", "fingerprint", "visits", d.alias("d"))
    shell = F.explode(F.sequence(F.expr(f"greatest(d - {radius}, 0) div {SHELL}"), F.expr(f"(d + {radius}) div {SHELL}"))).alias("shell")
    dealt = at.select("branch", "fingerprint", "visits", F.expr(f"d div {SHELL}").alias("own"), shell)
    # a member visits shells above its own; those below have their members visit it
    dealt = dealt.where("visits OR shell >= own")
    return dealt.select(F.xxhash64("branch", "shell").alias("branch"), "fingerprint", (F.col("visits") | (F.col("shell") > F.col("own"))).alias("visits")).distinct()


def links(prints: DataFrame, radius: int = RADIUS) -> DataFrame:
    """(a, b), a < b: links of different fingerprints at most `radius` apart; any two that are linked at all are joined by some of these. prints: (fingerprint), any rows."""
    distinct = cut(own_columns(prints, "fingerprint").where("fingerprint IS NOT NULL").distinct())
    masks = projections(blocks_for(distinct.count(), radius), radius)
    trees = F.explode(F.array(*[F.xxhash64(F.lit(k), F.col("fingerprint").bitwiseAND(F.lit(mask))) for k, mask in enumerate(masks)])).alias("branch")
    now = distinct.select(trees, "fingerprint", F.lit(False).alias("visits"))
    schema, found = "a long, b long", None
    for _ in range(64):
        sizes = now.groupBy("branch").agg(F.count(F.lit(1)).alias("n"), F.min(F.struct(F.xxhash64("fingerprint"), "fingerprint")).getField("fingerprint").alias("vantage")).where(F.col("n") > LARGE).select("branch", "n", "vantage")
        sizes = cut(sizes)
        large = not sizes.isEmpty()
        small = now.join(sizes, "branch", "left_anti") if large else now
        some = small.repartition("branch").sortWithinPartitions("branch", "fingerprint").mapInArrow(_branches(radius), schema)
        found = some if found is None else found.unionByName(some)
        if not large:
            break
        before = sizes.agg(F.max("n")).first()[0]
        now = cut(_parted(now.join(sizes, "branch", "left_semi"), sizes.select("branch", "vantage"), radius))
        if now.groupBy("branch").count().agg(F.max("count")).first()[0] >= before:  # points too close to be parted: at most as many as stand within a shell's width
            found = found.unionByName(now.repartition("branch").sortWithinPartitions("branch", "fingerprint").mapInArrow(_branches(radius), schema))
            break
    return found.distinct()


def groups(prints: DataFrame, radius: int = RADIUS) -> DataFrame:
    """(fingerprint, component) of every different fingerprint: the least fingerprint that links lead to."""
    distinct = own_columns(prints, "fingerprint").distinct()
    linked = components(links(prints, radius), "a", "b")
    return distinct.join(linked, distinct["fingerprint"] == linked["id"], "left").select("fingerprint", F.coalesce("component", "fingerprint").alias("component"))


def near_duplicates(docs: DataFrame, radius: int = RADIUS) -> DataFrame:
    """A row for each row of docs: (doc_id, fingerprint as 16 hex digits, component_id).

    component_id is the least doc_id among all documents that links lead to. Texts without
    words, and null ones, have fingerprint 0 and are linked as any other. A null doc_id is
    never the least; repeated rows get rows each.
    """
    prints = cut(fingerprints(docs))
    least = prints.groupBy("fingerprint").agg(F.min("doc_id").alias("least"))
    linked = components(links(prints, radius), "a", "b")
    classes = least.join(linked, least["fingerprint"] == linked["id"], "left").select("fingerprint", "least", F.coalesce("component", "fingerprint").alias("component"))
    roots = classes.groupBy("component").agg(F.min("least").alias("component_id"))
    classes = cut(classes.join(roots, "component").select("fingerprint", "component_id"))  # so that the last join's largest fingerprints can be split
    return prints.join(classes, "fingerprint").select("doc_id", as_hex(F.col("fingerprint")).alias("fingerprint"), "component_id")


def one_of_each(docs: DataFrame, radius: int = RADIUS) -> DataFrame:
    """The rows of docs, all columns, without near-duplicates: of each component the row of its component_id stays.

    Of repeated rows of that id and fingerprint one stays; another text that shares the id
    is a document of its own. Rows without an id stay, one for each fingerprint, unless a
    document with an id is in their component.
    """
    rows, named = masked(docs, "doc_id", "text")
    found = near_duplicates(rows, radius)
    keep = cut(found.where("doc_id = component_id OR component_id IS NULL").select(F.col("doc_id").alias("kept_id"), F.col("fingerprint").alias("kept_print")).distinct())
    marked = fingerprints(rows, rows.columns)
    stay = marked.join(keep, F.col("doc_id").eqNullSafe(F.col("kept_id")) & (as_hex(F.col("fingerprint")) == F.col("kept_print")), "left_semi")
    return named(stay.dropDuplicates(["doc_id", "fingerprint"]))
