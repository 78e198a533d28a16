from datetime import datetime, timedelta

import duckdb
import pytest

from pathsieve import catalog
from pathsieve.operators import baselines, levels, recursive, udf_modes
from pathsieve.plans.spec import plan
from pathsieve.workloads import WORKLOADS


@pytest.fixture(scope="module")
def dense(spark, tmp_path_factory):
    """(folder, DuckDB) of few customers who order often on few days, so that paths come back to their edges; one has two orders of a day, one is of another segment."""
    folder = str(tmp_path_factory.mktemp("dense"))
    customer = [(c, "A" if c < 5 else "B") for c in range(1, 7)]
    orders = [(k, 1 + k % 6, datetime(1995, 1, 1) + timedelta(days=(0, 0, 9, 20)[k // 6])) for k in range(24)] + [(24, 2, datetime(1995, 1, 1))]
    spark.createDataFrame(customer, "c_custkey long, c_mktsegment string").write.parquet(f"{folder}/customer.parquet")
    spark.createDataFrame(orders, "o_orderkey long, o_custkey long, o_orderdate timestamp_ntz").write.parquet(f"{folder}/orders.parquet")
    con = duckdb.connect()
    for t in ("customer", "orders"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{folder}/{t}.parquet/*.parquet'")
    return folder, con


def query(spark, dense, **changes):
    return WORKLOADS["q4_knows"].query(spark, dense[0], max_len=3, **changes)


def same(spark, dense, name):
    rows = sorted((r["len"], r["n"]) for r in catalog.QUERIES[name](spark, dense[0]).collect())
    assert rows == sorted(dense[1].execute(f"SELECT len, n FROM ({catalog.ORACLES[name]})").fetchall()) and len(rows) == 3


BASES = ["base_walk_q4", "base_trail_q4", "base_json_q4", "base_listreduce_q4", "base_reattach_q4"]


@pytest.mark.parametrize("name", BASES)
def test_baselines(spark, dense, name):
    same(spark, dense, name)


@pytest.mark.parametrize("trail", [False, True])
def test_last_hop_has_a_row_for_each_beginning(spark, dense, trail):
    walking, full = baselines._collecting(query(spark, dense), trail)
    edges = levels.held_edges(walking)
    now = levels.step(walking, levels.step(walking, walking.anchors(), edges, 1), edges, 2).persist()
    last = baselines._last_hop(walking, full, now, edges)
    walks = levels.step(walking, now, edges, 3)
    assert last.count() == now.join(edges.begin, now["v"] == edges.begin["e_src"]).count() < walks.count()
    assert baselines._counted(baselines._finish(walking, full, last)) == baselines._finish(walking, full, walks).count()


def test_whole_edges_where_an_end_matters(spark, dense):
    assert levels.ends_alike(plan(query(spark, dense)))
    for changes in ({"semantics": "acyclic"}, {"targets": (2,)}, {"via": (2,)}):
        assert not levels.ends_alike(plan(query(spark, dense, **changes)))


WAYS = ["q4_json_inline", "q4_rcte_sql_function", "rewrites_none_q4", "q4_arrow_udf", "q4_json_udf", "q4_pandas_udf", "q4_rcte_json_udf", "q4_flat_udf", "q4_rcte", "q4_rcte_pandas_udf"]


@pytest.mark.parametrize("name", WAYS)
def test_ways(spark, dense, name):
    same(spark, dense, name)


def test_functions_are_called_once_for_the_last_edges_of_a_beginning(spark, dense):
    q = query(spark, dense)
    clock = udf_modes.Clock(spark, (*udf_modes.FUNCTIONS, "json"))
    made = {r["len"]: r["n"] for r in udf_modes.run_levels(q, clock=clock).collect()}
    assert sum(made.values()) > 2 * clock.calls["accept"].value == 2 * clock.calls["emit"].value


def test_statement_leaves_last_edges_open(spark, dense):
    p = plan(query(spark, dense))
    text = recursive.to_sql(p, "a", "e", None, levels.times_of(p.step_checks, "s_edge_ids"))
    assert text.count("JOIN e_ends") == 1 and "AS times" in text.partition("UNION ALL SELECT")[2]
