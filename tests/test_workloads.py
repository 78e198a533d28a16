import glob
import os

import duckdb
import pytest

import __spark_entry__
from pathsieve import catalog
from tests.conftest import DATA

PICKED = ["q3_payments", "qb_paths", "q1_levels", "q1_json_udf", "q2_pandas_udf", "q4_rcte", "base_split_q1", "base_reattach_q1", "cand_q1_early", "tight_q1", "rx_ambiguous_paths", "rx_ambiguous_runs", "supply_same_nation", "op_asof_next", "op_interval_join", "layout_adjacency_q3", "stream_incremental_q3", "stream_stateful_window", "qa_pair", "collapse_count_q3", "op_udtf_transitions"]


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for f in glob.glob(f"{DATA}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    return con


@pytest.mark.parametrize("name", PICKED)
def test_query_equals_its_sql(spark, duck, name):
    df = catalog.QUERIES[name](spark, DATA)
    names = sorted(df.columns)
    found = sorted(repr(tuple(r[c] for c in names)) for r in df.collect())
    cursor = duck.execute(catalog.ORACLES[name])
    at = [[d[0] for d in cursor.description].index(c) for c in names]
    assert found == sorted(repr(tuple(r[k] for k in at)) for r in cursor.fetchall())


def test_every_query_has_sql():
    assert set(catalog.QUERIES) == set(catalog.ORACLES)


def test_entry(spark):
    assert __spark_entry__.entry(spark).count() > 0
    assert "q3_payments" in __spark_entry__.queries()
