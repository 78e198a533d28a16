"""Counting by classes: prefixes that a renaming of vertices turns into each other are one row with a count.

Where edges are halves, an edge is any two rows of a day and part. Vertices whose rows lie
in the same days and parts, equally often, can be exchanged, and so can a vertex's rows of
one day and part. A prefix is then told by its last vertex's class, its slots, and its
edges over names of their vertices and rows; a hop goes to a named one, or to an unnamed
one as often as the class has such. Checks stand at the hop, as in the level executor. No
path is left out: the counts are those of all paths. Edges that the hops left can't come
back to are forgotten.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathsieve.plans.spec import PathPlan
from pathsieve.sources.tables import shared_folder

_ROW = "STRUCT<p: BIGINT, k: INT, g: BIGINT, i: INT>"
_NO_EDGES = f"CAST(array() AS ARRAY<STRUCT<a: {_ROW}, b: {_ROW}, gs: ARRAY<BIGINT>>>)"
TIMES = "DECIMAL(38, 0)"
#: Rows of classes up to which they are sent to every task, so that a day and part of many prefixes is no task of its own.
SMALL = 100_000


def kept_slots(p: PathPlan) -> dict[str, str]:
    """Slots that need nothing of an edge's end, with their texts."""
    return {s: text for s, text in p.advance().items() if not re.search(r"\b(e_id|e_dst|w_\w+|to_state)\b", text)}


def applies(p: PathPlan, checks: list[str]) -> bool:
    """Whether checks (but the trail's), accept tests and slots need only what all edges of a day and part share. For plans whose ends are alike."""
    kept, known = kept_slots(p), {f"e_{c}" for c in p.query.graph.parts.shared}
    seeds = [s.seed for s in p.aggregate.slots if s.name in kept]
    return all(set(re.findall(r"\b(?:[ew]_\w+|v|start|to_state)\b", text)) <= known for text in [*checks, *p.aggregate.accept, *kept.values(), *seeds])


def window(p: PathPlan) -> tuple[str, str] | None:
    """(property, bound) that keeps all edges of a path within so much of the first one's."""
    found = [t.split(":")[1:] for t in sorted(p.aggregate.traits) if t.startswith("spread:")]
    return next(((f"e_{name}", bound) for name, bound in found if name in p.query.graph.parts.shared), None)


def _written(df: DataFrame, path: str) -> DataFrame:
    """Numbered rows have to be read back: they'd be numbered anew each time."""
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def classes(p: PathPlan) -> tuple[DataFrame, DataFrame]:
    """(classes, starts). Classes: a row for each class p and day and part g with rows of it, m for each of the `size` vertices, n ends for each; w is the first edge's property that bounds the others. Starts: (p, slots, times)."""
    begin, near = p.halves()[0], window(p)
    shared = [f"e_{c}" for c in p.edge_columns if c not in ("id", "src", "dst")]
    rows, anchors = begin.select("e_src", "e_day", "e_part", *shared), p.anchors()
    folder = shared_folder(begin.sparkSession, "classes")
    if near is None:
        rows = rows.withColumn("w", F.lit(0))
    else:
        name, bound = near
        cell = lambda c: F.floor(F.col(c) / F.lit(float(bound) or 1.0))
        first = rows.join(anchors.select(F.col("v").alias("e_src")), "e_src", "left_semi").where(F.col(name).isNotNull()).select(F.col(name).alias("w")).distinct()
        first = _written(first, f"{folder}/first").withColumn("cell", F.explode(F.sequence(cell("w") - 2, cell("w") + 2)))
        rows = rows.withColumn("cell", cell(name)).join(first, "cell").where(f"abs({name} - w) <= {bound}").drop("cell")
    rows = rows.groupBy("w", "e_src", "e_day", "e_part", *shared).agg(F.count(F.lit(1)).alias("m")).persist(StorageLevel.MEMORY_AND_DISK)
    groups = _written(rows.select("e_day", "e_part", *shared).distinct().withColumn("g", F.monotonically_increasing_id()), f"{folder}/groups")
    vertices = rows.drop(*shared).join(groups.select("e_day", "e_part", "g"), ["e_day", "e_part"]).groupBy("w", "e_src").agg(F.sort_array(F.collect_list(F.struct("g", "m"))).alias("rows"))
    vertices = _written(vertices, f"{folder}/vertices")
    rows.unpersist()
    kinds = _written(vertices.groupBy("w", "rows").agg(F.count(F.lit(1)).alias("size")).withColumn("p", F.monotonically_increasing_id()), f"{folder}/kinds")
    each = kinds.select("w", "p", "size", F.expr("transform(rows, x -> x.g) AS gs"), F.expr("inline(rows)"))
    ends = each.groupBy("w", "g").agg(F.sum(F.col("size") * F.col("m")).alias("all"))
    each = each.join(ends, ["w", "g"]).withColumn("n", F.col("all") - F.col("m")).drop("all").join(groups.drop("e_day", "e_part"), "g")
    kept = [f"s_{s.name}" for s in p.aggregate.slots if s.name in kept_slots(p)]
    starts = anchors.join(vertices, F.col("v") == F.col("e_src")).join(kinds, ["w", "rows"]).groupBy("p", *kept).agg(F.count(F.lit(1)).cast(TIMES).alias("times"))
    return each, starts


def _fresh(names: str) -> str:
    return f"array_min(array_except(sequence(0, size({names})), {names}))"


def _ways(named: str, many: str) -> str:
    """(i, times) of a vertex's rows of one day and part: the named ones, and an unnamed one as often as there are such."""
    return f"concat(transform({named}, i -> struct(i AS i, 1L AS times)), array(struct({_fresh(named)} AS i, {many} - size({named}) AS times)))"


def _named(p: str, k: str) -> str:
    return f"array_distinct(transform(filter(seen, o -> o.p = {p} AND o.k = {k} AND o.g = g), o -> o.i))"


def _from_own(begun: DataFrame) -> DataFrame:
    """Begun prefixes with each of their vertex's rows that the edge may begin with, named or not."""
    out = begun.withColumn("seen", F.expr("flatten(transform(hist, x -> array(x.a, x.b)))"))
    return out.withColumn("own", F.expr(_named("p", "k"))).withColumn("from", F.expr(f"explode(filter({_ways('own', 'm')}, y -> y.times > 0))")).withColumn("a", F.expr("struct(p, k, g, from.i AS i)"))


def _hop(begun: DataFrame, ends: DataFrame, trail: bool, left: int) -> DataFrame:
    """Begun prefixes with each class of ends, named or not; left: hops after this one, 2 at least."""
    out = _from_own(begun).join(ends, ["w", "g"]).withColumn("them", F.expr("array_distinct(concat(transform(filter(seen, o -> o.p = p2), o -> o.k), filter(array(k), x -> p2 = p)))"))
    known = f"flatten(transform(filter(them, c -> NOT (p2 = p AND c = k)), c -> transform({_ways(_named('p2', 'c'), 'm2')}, y -> struct(c AS k, y.i AS i, y.times AS times))))"
    out = out.withColumn("to", F.expr(f"explode(filter(concat({known}, array(struct({_fresh('them')} AS k, 0 AS i, (size2 - size(them)) * m2 AS times))), y -> y.times > 0))"))
    out = out.withColumn("b", F.expr("struct(p2 AS p, to.k AS k, g, to.i AS i)"))
    if trail:
        out = out.where("NOT exists(hist, x -> x.a = a AND x.b = b)").withColumn("hist", F.expr("array_append(hist, struct(a, b, gs))"))
        if left == 2:  # the last hop begins where the one before it ends, that one's end shares a day and part with its beginning
            out = out.withColumn("hist", F.expr("filter(hist, x -> arrays_overlap(x.gs, gs2))"))
    return out.withColumn("times", F.expr(f"CAST(times * from.times * to.times AS {TIMES})")).withColumn("hist", F.array_sort("hist")).drop("p", "k").withColumns({"p": F.col("p2"), "k": F.col("to.k")})


def _hop_before_last(begun: DataFrame, ends: DataFrame, state: list[str]) -> DataFrame:
    """_hop() before the last one, for sums by p, k, state and hist. The last hop can only repeat edges that begin where this one ends, so that an end which begins none needs no name.

    Prefixes that begin an edge in one day and part, with one state, are met with its ends together. Each takes
    back its own vertex and those that its edges single out, and meets the latter by name.
    """
    plain = lambda df, p, times: df.select(F.col(p).alias("p"), F.lit(0).alias("k"), *state, F.expr(_NO_EDGES).alias("hist"), F.expr(f"CAST({times} AS {TIMES})").alias("times"))
    together = begun.groupBy("w", "g", *state).agg(F.sum(F.expr(f"CAST(times * m AS {TIMES})")).alias("times")).join(ends, ["w", "g"])
    single = "concat(transform(filter(hist, x -> array_contains(x.gs, g)), x -> struct(x.a.p AS p2, x.a.k AS k2)), transform(filter(hist, x -> x.a.p = p AND x.a.k = k AND x.a.g = g), x -> struct(x.b.p AS p2, x.b.k AS k2)))"
    met = begun.withColumn("single", F.expr(f"filter(array_distinct({single}), y -> NOT (y.p2 = p AND y.k2 = k))")).where("size(single) > 0").select("*", F.expr("inline(single)")).join(ends, ["w", "g", "p2"])
    by_name = _from_own(met).withColumn("to", F.expr(f"explode(filter({_ways(_named('p2', 'k2'), 'm2')}, y -> y.times > 0))")).withColumn("b", F.expr("struct(p2 AS p, k2 AS k, g, to.i AS i)"))
    by_name = by_name.where("NOT exists(hist, x -> x.a = a AND x.b = b)").select(F.col("p2").alias("p"), F.col("k2").alias("k"), *state, F.expr("filter(hist, x -> x.a.p = p2 AND x.a.k = k2)").alias("hist"), F.expr(f"CAST(times * from.times * to.times AS {TIMES})").alias("times"))
    return plain(together, "p2", "times * size2 * m2").unionByName(plain(begun, "p", "-times * m * m")).unionByName(plain(met, "p2", "-times * m * m2")).unionByName(by_name)


def counts(p: PathPlan, checks: list[str], trail: bool, test: Column) -> Iterator[tuple[int, int]]:
    """(prefixes, answers) of length 1, 2, ... max_len, up to the first without prefixes."""
    kept, near, last = kept_slots(p), window(p), p.query.max_len
    each, now = classes(p)
    each = each.persist(StorageLevel.MEMORY_AND_DISK)
    ends = each.select("w", "g", F.col("p").alias("p2"), F.col("m").alias("m2"), F.col("size").alias("size2"), F.col("gs").alias("gs2"))
    ends = F.broadcast(ends) if each.count() <= SMALL else ends
    now = now.select("p", F.lit(0).alias("k"), F.lit(0).alias("q"), F.lit(0).alias("len"), *[f"s_{s}" for s in kept], F.expr(f"{_NO_EDGES} AS hist"), "times")
    held: list[DataFrame] = []
    try:
        for hop in range(1, last + 1):
            begun = now.join(each.drop("size"), "p")
            for text in [*checks, *([f"{near[0]} = w"] if near and hop == 1 else [])]:
                begun = begun.where(text)
            advanced = [F.expr(text).alias(f"s_{s}") for s, text in kept.items()]
            begun = begun.select("w", "p", "k", "g", "gs", "m", "n", "q", (F.col("len") + 1).alias("len"), *advanced, "hist", "times")
            state = ["q", "len", *[f"s_{s}" for s in kept]]
            if hop == last:
                out = begun.select(*state, F.expr("times * (m * n - size(filter(hist, x -> x.a.p = p AND x.a.k = k AND x.a.g = g)))").alias("times"))
            else:
                made = _hop_before_last(begun, ends, state) if hop == last - 1 else _hop(begun, ends, trail, last - hop)
                out = now = made.groupBy("p", "k", *state, "hist").agg(F.sum("times").alias("times")).where("times > 0").persist(StorageLevel.MEMORY_AND_DISK)
                held.append(now)
            total, n = out.agg(F.sum("times"), F.sum(F.when(test, F.col("times")))).first()
            while len(held) > 1:
                held.pop(0).unpersist()
            yield int(total or 0), int(n or 0)
            if not total:
                return
    finally:
        each.unpersist()
        for x in held:
            x.unpersist()
