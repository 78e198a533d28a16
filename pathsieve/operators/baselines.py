"""What engines do without early filtering: paths first, constraints on finished ones.

Each takes the same query and gives the same answers with more candidates. The
constraint is tested on lists collected along the path, by `replay` of the aggregate's
own functions over the finished list (or by the aggregate's final text, where it was
built for that). Where edges are two halves, finished lists that differ only in the end of
their last edge are one row, tested once and counted as often as it stands for (levels.ends_alike).
"""

from __future__ import annotations

import re
from dataclasses import replace

from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathsieve.operators import levels as native
from pathsieve.operators.recursive import answer_counts
from pathsieve.plans.graph import SHIFT
from pathsieve.plans.aggregate import Check, PruningAggregate, Slot
from pathsieve.plans.regex import glushkov, parse_regex, segments
from pathsieve.plans.spec import GuardedPathQuery, PathPlan, plan


def replay(p: PathPlan, hops: Column) -> Column:
    """replay_text as a column over `hops`."""
    return F.expr(replay_text(p))


def replay_text(p: PathPlan, hops: str = "hops") -> str:
    """Whether the aggregate admits a finished list of hops (structs of e_*, w_*, q, to_state), and accepts it: a fold over the list."""
    slots = p.aggregate.slots
    fields = [f"e_{c}" for c in p.edge_columns] + [f"w_{c}" for c in p.vertex_columns] + ["q", "to_state"]
    checks = [p.check_text(c) for c in p.aggregate.admit]

    def put(text: str) -> str:
        text = re.sub(r"\bs_(\w+)\b", r"acc.\1", text)
        text = re.sub(rf"(?<![.\w])({'|'.join(fields)})\b", r"hop.\1", text)
        return re.sub(r"(?<![.\w'])len\b", "acc.len", text)

    ok = " AND ".join(["acc.ok", *[f"coalesce(({put(c)}), false)" for c in checks]])
    body = ", ".join([f"'ok', {ok}", "'len', acc.len + 1", *[f"'{s.name}', CAST({put(t)} AS {s.dtype})" for s, t in zip(slots, p.advance().values(), strict=True)]])
    final = " AND ".join(["acc.ok", *[f"coalesce(({put(c)}), false)" for c in p.aggregate.accept]])
    seed = ", ".join(["'ok', true", "'len', 0", *[f"'{s.name}', CAST({s.seed} AS {s.dtype})" for s in slots]])
    return f"aggregate({hops}, named_struct({seed}), (acc, hop) -> named_struct({body}), acc -> {final})"


def _collecting(query: GuardedPathQuery, trail: bool) -> tuple[PathPlan, PathPlan]:
    """(plan that only walks and collects, plan whose constraint is replayed)."""
    full = plan(query.vary(rewrites=frozenset()))
    fields = [f"e_{c}" for c in full.edge_columns] + [f"w_{c}" for c in full.vertex_columns]
    types = dict(full.edges().dtypes)
    kind = "ARRAY<STRUCT<" + ", ".join([*[f"{f}: {types[f]}" for f in fields], "q: INT", "to_state: INT"]) + ">>"
    one = "named_struct(" + ", ".join([f"'{f}', {f}" for f in fields] + ["'q', q", "'to_state', to_state"]) + ")"
    checks = (Check("NOT exists(s_hops, h -> h.e_id = e_id)"),) if trail else ()
    collect = PruningAggregate((Slot("hops", kind, f"CAST(array() AS {kind})"),), {"hops": f"array_append(s_hops, {one})"}, checks, uses=full.aggregate.uses | {"label"} if "label" in full.edge_columns else full.aggregate.uses)
    walking = plan(query.vary(constraint=collect, semantics="walk", rewrites=frozenset(), dedupe=False))
    return replace(walking, nfa=full.nfa), full


def _finish(walking: PathPlan, full: PathPlan, level: DataFrame) -> DataFrame:
    q = walking.query
    out = level.where(F.col("len") >= q.min_len)
    if full.accepting is not None:
        out = out.where(F.col("q").isin(full.accepting))
    out = out.withColumn("hops", F.col("s_hops")).where(replay(full, F.col("hops")))
    if full.nfa is not None and full.needs_ids:
        out = out.dropDuplicates(["start", "len", "hops"])
    return out


_HOP_IDS = "transform(s_hops, h -> h.e_id)"


def _last_hop(walking: PathPlan, full: PathPlan, now: DataFrame, edges: DataFrame | native.HeldHalves) -> DataFrame:
    """The walks of the last hop, with how many each stands for."""
    if native.ends_alike(full):
        return native.step(walking, now, native.opened(edges), walking.query.max_len, more={"times": native.times_of([*walking.step_checks, *full.step_checks], _HOP_IDS)})
    return native.step(walking, now, edges, walking.query.max_len).withColumn("times", F.lit(1))


def _counted(found: DataFrame) -> int:
    return found.agg(F.sum("times")).first()[0] or 0


def _run(query: GuardedPathQuery, trail: bool, candidates: bool) -> DataFrame:
    spark = query.graph.edges.sparkSession
    walking, full = _collecting(query, trail)
    edges, now, rows, held = native.held_edges(walking), walking.anchors(), [], None
    for hop in range(1, query.max_len + 1):
        if hop == query.max_len:  # counted in one pass and not kept
            n = native.extensions(walking, now, edges) if candidates else None
            if n is None:
                n = native.step(walking, now, edges, hop).count() if candidates else _counted(_finish(walking, full, _last_hop(walking, full, now, edges)))
            if n:
                rows.append((hop, n))
            break
        now = native.step(walking, now, edges, hop).persist(StorageLevel.MEMORY_AND_DISK)
        total = now.count()
        if held is not None:
            held.unpersist()
        held = now
        n = total if candidates else _finish(walking, full, now).count()
        if n:
            rows.append((hop, n))
        if not total:
            break
    if held is not None:
        held.unpersist()
    edges.unpersist()
    return spark.createDataFrame(rows, "len long, n long")


def postfilter_walk(query: GuardedPathQuery, candidates: bool = False) -> DataFrame:
    """(len, n): all walks of the expression, everything tested at the end."""
    return _run(query, False, candidates)


#: Walks first, trail later: the same plan, kept under its own name for reports.
postfilter_walk_trail_late = postfilter_walk


def postfilter_trail(query: GuardedPathQuery, candidates: bool = False) -> DataFrame:
    """(len, n): no edge twice while matching, the other constraints at the end."""
    return _run(query, True, candidates)


def json_postfilter(query: GuardedPathQuery) -> DataFrame:
    """postfilter_walk for an engine without arrays: the list is JSON text, parsed and written at every hop."""
    spark = query.graph.edges.sparkSession
    walking, full = _collecting(query, False)
    kind = walking.aggregate.slots[0].dtype
    edges, now, rows, held = native.held_edges(walking), walking.anchors().withColumn("s_hops", F.lit("[]")), [], []
    for hop in range(1, query.max_len + 1):
        parsed = now.withColumn("s_hops", F.from_json("s_hops", kind))
        walked = _last_hop(walking, full, parsed, edges) if hop == query.max_len else native.step(walking, parsed, edges, hop).withColumn("times", F.lit(1))
        now = walked.withColumn("s_hops", F.to_json("s_hops", {"ignoreNullFields": "false"}))
        if hop < query.max_len:  # the last level is counted in one pass and not kept
            now = now.persist(StorageLevel.MEMORY_AND_DISK)
            held.append(now)
            if not now.count():
                break
            if len(held) > 1:
                held.pop(0).unpersist()
        n = _counted(_finish(walking, full, now.withColumn("s_hops", F.from_json("s_hops", kind))))
        if n:
            rows.append((hop, n))
    for level in [*held, edges]:
        level.unpersist()
    return spark.createDataFrame(rows, "len long, n long")


def list_reduction(query: GuardedPathQuery) -> DataFrame:
    """(len, n): the declarative form. One statement matches trails into a list of hops and tests that list in its WHERE clause, by a reduction over it."""
    walking, full = _collecting(query, True)
    distinct = ["start", "len", "s_hops"] if full.nfa is not None and full.needs_ids else []
    times = native.times_of([*walking.step_checks, *full.step_checks], _HOP_IDS) if native.ends_alike(full) else None
    return answer_counts(replace(walking, aggregate=replace(walking.aggregate, accept=(replay_text(full, "s_hops"),))), distinct=distinct, times=times)


def reattach_postfilter(query: GuardedPathQuery) -> DataFrame:
    """For an engine that sees no properties while it expands: ids only, then every path's edges are joined back and regrouped in order."""
    full = plan(query.vary(rewrites=frozenset()))
    bare = plan(query.vary(constraint=PruningAggregate(), semantics="walk", rewrites=frozenset(), dedupe=False), with_ids=True)
    if query.max_len > 1 and query.min_len and native.ends_alike(full):
        return _reattach_halves(bare, full)
    states = PruningAggregate((Slot("states", "ARRAY<STRUCT<q: INT, to_state: INT>>", "CAST(array() AS ARRAY<STRUCT<q: INT, to_state: INT>>)"),), {"states": "array_append(s_states, named_struct('q', q, 'to_state', to_state))"})
    bare = replace(bare, aggregate=bare.aggregate & states, nfa=full.nfa)
    out = None
    for level in list(native.frontiers(bare))[1:]:
        out = level if out is None else out.unionByName(level)
    out = out.where(F.col("len") >= query.min_len)
    if full.accepting is not None:
        out = out.where(F.col("q").isin(full.accepting))
    key = ["start", "len", "s_edge_ids", "s_states"]
    each = out.select(*key, F.posexplode("s_edge_ids").alias("k", "e_id")).join(full.edges(), "e_id")
    state = F.element_at("s_states", F.col("k") + 1)
    fields = [F.col(f"e_{c}") for c in full.edge_columns] + [F.col(f"w_{c}") for c in full.vertex_columns]
    hops = F.array_sort(F.collect_list(F.struct("k", *fields, state["q"].alias("q"), state["to_state"].alias("to_state"))))
    whole = each.groupBy(*key).agg(hops.alias("hops")).where(replay(full, F.col("hops")))
    return whole.select(F.col("len").cast("long").alias("len"), "start", "s_edge_ids").distinct().groupBy("len").agg(F.count(F.lit(1)).alias("n"))


def _reattach_halves(bare: PathPlan, full: PathPlan) -> DataFrame:
    """reattach_postfilter over halves. An edge's properties are those of its beginning. Paths of equal edges but the last one's end share the joins: their first edges are joined back and regrouped once, then the last one's."""
    q, begin = full.query, full.halves()[0]
    out = None
    for level in list(native.frontiers(replace(bare, query=bare.query.vary(max_len=q.max_len - 1))))[1:]:
        out = level if out is None else out.unionByName(level)
    known = begin.drop("e_n", "e_day", "e_part")
    names = ["e_id", *[f"e_{c}" for c in full.edge_columns if c not in ("id", "dst")]]
    hop = lambda *before: F.struct(*before, *names, F.lit(0).alias("q"), F.lit(0).alias("to_state"))
    key = ["start", "v", "len", "s_edge_ids"]
    each = out.select(*key, F.posexplode("s_edge_ids").alias("k", "e_id")).withColumn("e_key", F.expr(f"e_id div {SHIFT}")).join(known, "e_key")
    whole = each.groupBy(*key).agg(F.array_sort(F.collect_list(hop("k"))).alias("placed")).withColumn("hops", F.transform("placed", lambda h: h.dropFields("k"))).drop("placed")
    grown = whole.where(F.col("len") == q.max_len - 1).join(begin.select(F.col("e_src").alias("v"), "e_key", "e_n"), "v")
    grown = grown.join(known.withColumnsRenamed({"e_src": "v"}), ["v", "e_key"]).withColumnsRenamed({"v": "e_src"}).withColumns({"e_id": F.expr(native.OPEN_ID), "times": F.expr(native.times_of([*bare.step_checks, *full.step_checks], "s_edge_ids"))})
    last = grown.select((F.col("len") + 1).alias("len"), F.array_append("hops", hop()).alias("hops"), "times")
    shorter = whole.where(F.col("len") >= q.min_len).select("len", "hops", F.lit(1).alias("times"))
    found = shorter.unionByName(last).where(replay(full, F.col("hops")))
    return found.groupBy(F.col("len").cast("long").alias("len")).agg(F.sum("times").alias("n")).where("n > 0")


def split_regex_join(query: GuardedPathQuery, printed_bounds: bool = False) -> DataFrame:
    """(len, n): the parts of the expression are matched one by one, from every vertex but the first part, then joined where they meet; total length and constraint are tested after.

    printed_bounds: each part may have 0 to max_len edges, and the total up to max_len for each part.
    """
    tree = parse_regex(query.regex)
    parts = segments(tree)
    whole = plan(query.vary(rewrites=frozenset()))
    walking, _ = _collecting(query, False)
    least = 0 if printed_bounds else 1
    most = query.max_len if printed_bounds else query.max_len - (len(parts) - 1)
    found = None
    for k, part in enumerate(parts):
        sub = replace(walking, nfa=glushkov(part, query.graph.labels()), query=walking.query.vary(sources=query.sources if k == 0 else None, min_len=least, max_len=max(most, 1)))
        matched = None
        for level in native.frontiers(sub):
            some = level.where(F.col("len") >= least)
            some = some.where(F.col("q").isin(sorted(sub.nfa.accepting)) | (F.lit(printed_bounds) & (F.col("len") == 0)))
            matched = some if matched is None else matched.unionByName(some)
        matched = matched.select(F.col("start").alias(f"start{k}"), F.col("v").alias(f"v{k}"), F.col("len").alias(f"len{k}"), F.col("s_hops").alias(f"hops{k}"))
        found = matched if found is None else found.join(matched, F.col(f"v{k - 1}") == F.col(f"start{k}"))
    total = sum((F.col(f"len{k}") for k in range(1, len(parts))), F.col("len0"))
    joined = found.select(F.col("start0").alias("start"), total.alias("len"), F.concat(*[F.col(f"hops{k}") for k in range(len(parts))]).alias("hops"))
    if not printed_bounds:
        joined = joined.where(F.col("len").between(query.min_len, query.max_len))
    joined = joined.where("size(hops) > 0")
    # the parts numbered their states alone: run the whole automaton over the labels again
    rerun = _restate(whole, joined).where(replay(whole, F.col("hops")))
    ids = F.transform("hops", lambda h: h["e_id"])
    return rerun.select("start", "len", ids.alias("ids")).distinct().groupBy(F.col("len").cast("long").alias("len")).agg(F.count(F.lit(1)).alias("n"))


def _restate(p: PathPlan, rows: DataFrame) -> DataFrame:
    """Gives the hops the states of the whole automaton, a row for each of its runs; paths that it doesn't accept go. The moves are a literal of the expression's size."""
    moves = ", ".join(f"named_struct('f', {f}, 't', {t}, 'x', '{x}')" for f, t, x in p.nfa.rows())
    fields = [f"e_{c}" for c in p.edge_columns] + [f"w_{c}" for c in p.vertex_columns]
    one = ", ".join(f"'{f}', h.{f}" for f in fields)
    kind = "ARRAY<STRUCT<" + ", ".join(f"{f.name}: {f.dataType.simpleString()}" for f in rows.schema["hops"].dataType.elementType.fields) + ">>"
    run = f"STRUCT<q: INT, out: {kind}>"
    grown = f"transform(filter(array({moves}), m -> m.f = a.q AND m.x = h.e_label), m -> CAST(named_struct('q', m.t, 'out', array_append(a.out, named_struct({one}, 'q', a.q, 'to_state', m.t))) AS {run}))"
    text = f"aggregate(hops, CAST(array(named_struct('q', 0, 'out', array())) AS ARRAY<{run}>), (acc, h) -> flatten(transform(acc, a -> {grown})))"
    return rows.withColumn("r", F.explode(F.expr(text))).where(F.col("r.q").isin(p.accepting)).select("start", "len", F.col("r.out").alias("hops"))


def segment_candidates(query: GuardedPathQuery) -> DataFrame:
    """(segment, len, n): partial matches of each part of the expression, as split_regex_join makes them."""
    spark = query.graph.edges.sparkSession
    rows = []
    parts = segments(parse_regex(query.regex))
    for k, part in enumerate(parts):
        base = plan(query.vary(constraint=PruningAggregate(), semantics="walk", sources=query.sources if k == 0 else None, max_len=max(query.max_len - len(parts) + 1, 1), dedupe=False))
        sub = replace(base, nfa=glushkov(part, query.graph.labels()))
        rows += [(k, hop, n) for hop, level in enumerate(native.frontiers(sub)) if hop and (n := level.count())]
    return spark.createDataFrame(rows, "segment long, len long, n long")
