import random
from datetime import timedelta

import pytest
from pyspark.sql import functions as F

from pathsieve import metrics
from pathsieve.functions import constraints as C
from pathsieve.operators import baselines, layout, levels, recursive, results, udf_modes
from pathsieve.plans.aggregate import Check, PruningAggregate, compose
from pathsieve.plans.graph import PropertyGraph
from pathsieve.plans.regex import automaton
from pathsieve.plans.spec import GuardedPathQuery, plan

DAY = 86_400_000_000
TOY = [(1, 1, 3, "Domestic", 20 * DAY, 4000.0), (2, 3, 2, "Domestic", 3 * DAY, 7000.0), (3, 3, 4, "Domestic", 2 * DAY, 5000.0), (4, 4, 2, "Foreign", 4 * DAY, 6000.0), (5, 2, 4, "Foreign", 5 * DAY, 8000.0), (6, 4, 1, "Domestic", 9 * DAY, 3000.0)]
SCHEMA = "id long, src long, dst long, label string, t long, amount double"
QB = "dom:Domestic+ fgn:Foreign"
QB_RULE = C.StepWithin("t", by={("dom", "dom"): timedelta(days=2), ("dom", "fgn"): timedelta(days=3)})


def graph(spark, rows=TOY):
    return PropertyGraph(spark.createDataFrame(rows, SCHEMA), alphabet=tuple(sorted({r[3] for r in rows if r[3]})))


def counts(df):
    return {r["len"]: r["n"] for r in df.collect()}


def brute(rows, start, max_len, regex=None, test=None, trail=True):
    """All paths in Python, tested when finished."""
    nfa = automaton(regex, sorted({r[3] for r in rows if r[3]})) if regex else None
    out, paths = {}, [(start, [])]
    for n in range(1, max_len + 1):
        paths = [(e[2], [*p, e]) for v, p in paths for e in rows if e[1] == v]
        good = [p for _, p in paths if (not trail or len({e[0] for e in p}) == len(p)) and (nfa is None or nfa.accepts([e[3] for e in p])) and (test is None or test(p))]
        if good:
            out[n] = len(good)
    return out


def test_worked_example(spark):
    g = graph(spark)
    free = GuardedPathQuery(g, regex=QB, sources=(3,), max_len=5)
    assert sorted(r["edge_ids"] for r in levels.paths(free).collect()) == ["2-5", "3-4", "3-6-1-2-5"]
    ruled = free.vary(constraint=QB_RULE)
    assert sorted(r["edge_ids"] for r in levels.paths(ruled).collect()) == ["2-5", "3-4"]
    assert counts(levels.candidates(ruled)) == {1: 2, 2: 2}  # the prefix 3-6 goes at its second hop
    assert "CASE" in plan(ruled).step_checks[0] and not plan(ruled).aggregate.is_factorized
    for mode in udf_modes.MODES:
        assert counts(udf_modes.run_levels(ruled, mode)) == {2: 2}
    assert counts(recursive.levels(ruled)) == counts(baselines.postfilter_walk(ruled)) == counts(baselines.split_regex_join(ruled)) == {2: 2}
    assert "WITH RECURSIVE" in recursive.statement(ruled) and "factorized: False" in levels.explain(ruled)


def test_edge_cases(spark):
    empty = PropertyGraph(spark.createDataFrame([], SCHEMA))
    assert counts(levels.levels(GuardedPathQuery(empty, max_len=3))) == {}
    loop = graph(spark, [(1, 1, 1, "a", 1, 1.0)])
    assert counts(levels.levels(GuardedPathQuery(loop, sources=(1,), max_len=3))) == {1: 1}
    assert counts(levels.levels(GuardedPathQuery(loop, sources=(1,), max_len=3, semantics="walk"))) == {1: 1, 2: 1, 3: 1}
    assert counts(levels.levels(GuardedPathQuery(loop, sources=(1,), max_len=3, semantics="acyclic"))) == {}
    twins = graph(spark, [(1, 1, 2, "a", 1, 1.0), (2, 1, 2, "a", 1, 1.0), (3, 2, 1, "a", 1, 1.0)])
    assert counts(levels.levels(GuardedPathQuery(twins, C.Monotone("t"), sources=(1,), max_len=2))) == {1: 2}
    assert counts(levels.levels(GuardedPathQuery(twins, C.Monotone("t", strict=False), sources=(1,), max_len=3))) == {1: 2, 2: 2, 3: 2}
    assert counts(levels.levels(GuardedPathQuery(graph(spark), sources=(3,), min_len=0, max_len=1))) == {0: 1, 1: 2}
    assert counts(levels.levels(GuardedPathQuery(graph(spark), regex="nowhere", sources=(3,), max_len=2))) == {}
    assert levels.exists(GuardedPathQuery(graph(spark), regex=QB, sources=(3,))) and not levels.exists(GuardedPathQuery(graph(spark), regex="Foreign Foreign Foreign", sources=(3,)))
    with pytest.raises(ValueError):
        GuardedPathQuery(graph(spark), min_len=3, max_len=2)


def test_missing_properties(spark):
    rows = [(1, 1, 2, "a", None, 1.0), (2, 2, 3, "a", 5, None), (3, 1, 2, "a", 1, 2.0)]
    g = graph(spark, rows)
    assert counts(levels.levels(GuardedPathQuery(g, C.Monotone("t"), sources=(1,), max_len=2))) == {1: 2, 2: 1}
    assert counts(levels.levels(GuardedPathQuery(g, C.SpreadAtMost("amount", 5, "DOUBLE"), sources=(1,), max_len=2))) == {1: 2}
    for mode in udf_modes.MODES[:3]:
        assert counts(udf_modes.run_levels(GuardedPathQuery(g, C.Monotone("t"), sources=(1,), max_len=2), mode)) == {1: 2, 2: 1}


RULES = {
    "chronological": (C.Monotone("t"), lambda p: all(a[4] < b[4] for a, b in zip(p, p[1:], strict=False))),
    "spread": (C.SpreadAtMost("amount", 3, "DOUBLE"), lambda p: max(e[5] for e in p) - min(e[5] for e in p) <= 3),
    "wide": (C.SpreadAtLeast("amount", 3, "DOUBLE"), lambda p: max(e[5] for e in p) - min(e[5] for e in p) >= 3),
    "sum": (C.SumAtMost("amount", 9), lambda p: sum(e[5] for e in p) <= 9),
    "large sum": (C.SumAtLeast("amount", 9, edge_upper_bound=6), lambda p: sum(e[5] for e in p) >= 9),
    "neighbours": (C.AdjacentEqualExists("label"), lambda p: any(a[3] == b[3] for a, b in zip(p, p[1:], strict=False))),
    "same": (C.SameAsFirst("label"), lambda p: all(e[3] == p[0][3] for e in p)),
    "both": (C.Monotone("t", strict=False) & C.SpreadAtMost("t", 4) & C.StepWithin("t", 2), lambda p: all(0 <= b[4] - a[4] <= 2 for a, b in zip(p, p[1:], strict=False)) and p[-1][4] - p[0][4] <= 4),
}


@pytest.mark.parametrize("rule", RULES)
def test_random_graphs_against_brute_force(spark, rule):
    rng = random.Random(rule)
    rows = [(k, rng.randrange(5), rng.randrange(5), rng.choice("ab"), rng.randrange(8), float(rng.randrange(7))) for k in range(11)]
    constraint, test = RULES[rule]
    for regex in (None, "(a | b a)* b?"):
        q = GuardedPathQuery(graph(spark, rows), constraint, regex, (0,), max_len=3)
        expected = brute(rows, 0, 3, regex, test)
        runs = [levels.levels(q), recursive.levels(q), baselines.postfilter_walk(q), udf_modes.run_levels(q, "json_inline"), levels.levels(q.vary(rewrites=frozenset(["elide_trail", "hoist", "envelope", "remaining_hops"])))]
        assert [counts(r) for r in runs] == [expected] * len(runs), (rule, regex)


def test_soundness_tool_finds_an_unsound_check(spark):
    q = GuardedPathQuery(graph(spark), C.SpreadAtLeast("amount", 2000, "DOUBLE"), sources=(3,), max_len=3)
    metrics.assert_sound(q)
    hasty = PruningAggregate(q.constraint.slots, q.constraint.advance, (Check("greatest(s_max_amount, e_amount) - least(s_min_amount, e_amount) >= 2000"),), uses=q.constraint.uses)
    assert counts(levels.levels(q.vary(constraint=hasty))) != counts(levels.levels(q))


def test_composition(spark):
    a, b, c = C.Monotone("t"), C.StepWithin("t", DAY), C.SpreadAtMost("amount", 3000, "DOUBLE")
    assert [s.name for s in (C.Monotone("t") & C.Monotone("t")).slots] == ["last_t"]
    clash = C.AnyOf("e_amount > 5000", "true", ["amount"]) & C.AnyOf("e_amount < 5000", "true", ["amount"])
    assert [s.name for s in clash.slots] == ["any", "any_2"]
    q = GuardedPathQuery(graph(spark), clash, sources=(3,), max_len=3)
    assert counts(levels.levels(q)) == brute(TOY, 3, 3, None, lambda p: any(e[5] > 5000 for e in p) and any(e[5] < 5000 for e in p))
    orders = [compose(a, b, c), compose(c, b, a), a & (b & c)]
    found = [counts(levels.levels(GuardedPathQuery(graph(spark), x, sources=None, max_len=3))) for x in orders]
    assert found[0] == found[1] == found[2]


def test_plans(spark, tmp_path):
    g = graph(spark)
    q = GuardedPathQuery(g, QB_RULE, QB, (3,), max_len=2)
    text = levels.step(plan(q), plan(q).anchors(), plan(q).edges(), 1)._jdf.queryExecution().toString()
    assert "Python" not in text and "BroadcastHashJoin" in text
    assert not [s for s in plan(GuardedPathQuery(g, C.Monotone("t"))).aggregate.slots if s.name == "edge_ids"]  # a strictly growing time repeats no edge
    layout.write_bucketed(g, "toy_edges", 4)
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        left = spark.createDataFrame([(3,)], "v long").repartition(4, "v")
        text = left.join(spark.table("toy_edges"), F.col("v") == F.col("src"))._jdf.queryExecution().executedPlan().toString()
        assert text.count("Exchange") == 1
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
        spark.conf.unset("spark.sql.adaptive.enabled")
        spark.sql("DROP TABLE toy_edges")


def test_operators(spark):
    g = graph(spark)
    paths = levels.paths(GuardedPathQuery(g, sources=(3,), max_len=3))
    assert results.same_paths(paths, paths) and results.top_k(paths, 1, F.desc("len"), "edge_ids").count() == 1
    assert {(r["id"], r["next_id"]) for r in results.asof_next_edge(g).collect()} == {(2, 5), (3, 4), (5, 6), (4, 5), (6, 1)}
    assert layout.from_adjacency(layout.adjacency(g, "t", chunk=1)).count() == len(TOY)
    assert metrics.total_candidates(GuardedPathQuery(g, sources=(3,), max_len=2), "walk") >= metrics.total_candidates(GuardedPathQuery(g, sources=(3,), max_len=2))


def test_salted_heavy_sources(spark, monkeypatch):
    rng = random.Random(1)
    rows = [(k, rng.randrange(6), rng.randrange(6), "a", rng.randrange(50), 1.0) for k in range(60)]
    q = GuardedPathQuery(graph(spark, rows), C.Monotone("t"), sources=None, max_len=3)
    plain = counts(levels.levels(q))
    monkeypatch.setattr(levels, "HEAVY", 8)
    for rewrites in (["salt"], ["salt", "envelope", "elide_trail", "hoist"]):
        assert counts(levels.levels(q.vary(rewrites=frozenset(rewrites)))) == plain
