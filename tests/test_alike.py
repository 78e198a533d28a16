from dataclasses import replace
from datetime import datetime
from fractions import Fraction

import pytest

from pathsieve import catalog
from pathsieve.functions import constraints as C
from pathsieve.operators import alike, levels
from pathsieve.plans.spec import plan
from pathsieve.sources import encodings
from pathsieve.workloads import WORKLOADS
from tests.test_open_ends import dense  # noqa: F401

KNOWS = replace(WORKLOADS["q4_knows"], start="all")


def same(spark, dense, query, sql):  # noqa: F811
    rows = sorted((r["len"], r["n"]) for r in query(spark, dense[0]).collect())
    assert rows and rows == sorted(dense[1].execute(f"SELECT len, n FROM ({sql})").fetchall())
    return rows


def test_long_paths(spark, dense):  # noqa: F811
    workload = replace(WORKLOADS["q4_knows"], max_len=5)
    assert len(same(spark, dense, lambda s, d: levels.levels(workload.query(s, d)), workload.levels_sql(early=1))) == 5


@pytest.mark.parametrize("changes", [{}, {"semantics": "walk"}, {"constraint": C.SpreadAtMost("t", 0)}, {"constraint": C.Monotone("t", strict=False), "min_len": 2}, {"constraint": C.CollectThenTest(["t"], "size(s_all_t) < 2 OR s_all_t[0] <> s_all_t[1]", "len < 2 OR p_t[1] <> p_t[2]")}])
def test_classes_give_the_counts_of_sql(spark, dense, changes):  # noqa: F811
    workload = replace(KNOWS, max_len=4, **changes)
    p = plan(workload.query(spark, dense[0]))
    assert levels.ends_alike(p) and alike.applies(p, [c for c in p.step_checks if c not in levels._TRAIL])
    same(spark, dense, lambda s, d: levels.levels(workload.query(s, d)), workload.levels_sql())


def test_whole_prefixes_where_vertices_differ(spark, dense):  # noqa: F811
    p = plan(KNOWS.query(spark, dense[0], constraint=C.EdgePredicate("e_src > 2", "true", [])))
    assert not alike.applies(p, p.step_checks)


def test_without_rewrites_no_row_is_a_path(spark, dense, monkeypatch):  # noqa: F811
    def made(*_, **__):
        raise AssertionError("a prefix's edges are made")

    monkeypatch.setattr(levels, "expand", made)
    assert len(same(spark, dense, catalog.QUERIES["rewrites_none_q4"], catalog.ORACLES["rewrites_none_q4"])) == 3


def test_ends_of_repeated_keys(spark, tmp_path):
    """A beginning's ends are counted right where orders share a key or a customer has several of a day."""
    spark.createDataFrame([(c, "A" if c < 4 else "B") for c in range(6)], "c_custkey long, c_mktsegment string").write.parquet(f"{tmp_path}/customer.parquet")
    orders = [(k // 2 if k < 8 else k, k % 5, datetime(1995, 1, 1 + k % 2)) for k in range(20)] + [(3, 3, datetime(1995, 1, 1)), (3, 3, datetime(1995, 1, 1)), (None, 1, datetime(1995, 1, 1))]
    spark.createDataFrame(orders, "o_orderkey long, o_custkey long, o_orderdate timestamp_ntz").write.parquet(f"{tmp_path}/orders.parquet")
    graph = encodings.stored(spark, str(tmp_path), "knows")
    plain = encodings.ENCODINGS["knows"](spark, str(tmp_path)).edges
    count = lambda edges: sorted(map(tuple, edges.groupBy("src", "t").count().collect()))
    assert not graph.parts.exact and sorted(graph.edges.collect()) == sorted(plain.collect())
    assert sorted(map(tuple, graph.parts.begin.groupBy("src", "t").agg({"n": "sum"}).where("`sum(n)` > 0").collect())) == count(plain)


def trails(n: int, length: int, at: int = 0, done: frozenset = frozenset()) -> int:
    return 1 if not length else sum(trails(n, length - 1, to, done | {(at, to)}) for to in range(n) if to != at and (at, to) not in done)


def test_many_vertices_of_one_class(spark, tmp_path):
    """100 customers of one day: some 9e11 paths of length 6. Of n customers the number is a polynomial in n, known from few."""
    spark.createDataFrame([(c, "A") for c in range(100)], "c_custkey long, c_mktsegment string").write.parquet(f"{tmp_path}/customer.parquet")
    spark.createDataFrame([(c, c, datetime(1995, 1, 1)) for c in range(100)], "o_orderkey long, o_custkey long, o_orderdate timestamp_ntz").write.parquet(f"{tmp_path}/orders.parquet")
    expected = []
    for length in range(1, 7):
        points = [(n, trails(n, length)) for n in range(1, length + 2)]
        total = Fraction(0)
        for n, y in points:
            part = Fraction(y)
            for m, _ in points:
                part *= Fraction(100 - m, n - m) if m != n else 1
            total += part
        expected.append((length, int(total)))
    rows = catalog.QUERIES["q4_knows_long"](spark, str(tmp_path)).collect()
    assert sorted((r["len"], r["n"]) for r in rows) == expected


def test_counts_above_the_largest_bigint(spark, tmp_path):
    """3000 customers of one day: (n - 1) ** 6 walks of length 6, some 7e20. Trails are fewer by what comes back to an edge."""
    spark.createDataFrame([(c, "A") for c in range(3000)], "c_custkey long, c_mktsegment string").write.parquet(f"{tmp_path}/customer.parquet")
    spark.createDataFrame([(c, c, datetime(1995, 1, 1)) for c in range(3000)], "o_orderkey long, o_custkey long, o_orderdate timestamp_ntz").write.parquet(f"{tmp_path}/orders.parquet")
    workload = replace(WORKLOADS["q4_knows"], max_len=6)
    walks = {r["len"]: int(r["n"]) for r in levels.levels(workload.query(spark, str(tmp_path), semantics="walk")).collect()}
    assert walks == {n: 2999**n for n in range(1, 7)}
    found = {r["len"]: int(r["n"]) for r in levels.levels(workload.query(spark, str(tmp_path))).collect()}
    assert 0.999 * walks[6] < found[6] < walks[6] and found[2] == walks[2] and found[3] == walks[3] - 2999


def test_no_row_for_each_end_before_the_last_hop(spark, dense, monkeypatch):  # noqa: F811
    """Of two hops' paths, the first hop's ends are met by day and part, not by _hop()."""
    monkeypatch.setattr(alike, "_hop", None)
    workload = replace(KNOWS, max_len=2)
    same(spark, dense, lambda s, d: levels.levels(workload.query(s, d)), workload.levels_sql())
