import time
from types import SimpleNamespace

import duckdb
import numpy as np
import pandas as pd
import pytest

from pathsieve import catalog
from pathsieve.streaming import paths as streams


@pytest.fixture
def small_frames(spark):
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "3")
    yield
    spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")


def events(folder, copies=1, users=12):
    """A folder with an events table: many events of few users, out of order, some at the same time."""
    r = np.random.default_rng(3)
    ts = pd.Timestamp("2024-01-01") + pd.to_timedelta(r.integers(0, 3 * 86_400, 150) // 60 * 60, "s")
    one = pd.DataFrame({"event_id": np.arange(150), "ts": ts.astype("datetime64[us]"), "user_id": r.integers(0, users, 150), "event_type": r.choice(["click", "view"], 150), "value": 1.0, "props": "{}"})
    pd.concat([one.assign(event_id=one["event_id"] + k * 150) for k in range(copies)]).to_parquet(f"{folder}/events.parquet")
    return str(folder)


def same(spark, name, folder):
    df = catalog.QUERIES[name](spark, folder)
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{folder}/events.parquet'")
    found = con.execute(f"SELECT {', '.join(df.columns)} FROM ({catalog.ORACLES[name]})").fetchall()
    assert sorted(map(tuple, df.collect())) == sorted(found) and found


def test_a_window_whose_key_comes_in_several_frames(spark, small_frames, tmp_path):
    same(spark, "stream_stateful_window", events(tmp_path, 2))


def test_paths_of_a_key_in_parts(spark, small_frames, tmp_path, monkeypatch):
    monkeypatch.setattr(streams, "PART", 7)
    same(spark, "stream_stateful_paths", events(tmp_path))


def test_an_edge_costs_the_paths_that_it_extends(spark):
    """20,000 edges of one key within the window, which hardly meet: every edge against every prefix takes over 5 seconds."""
    rows = spark.range(20_000).selectExpr("id", "id AS src", "id + 1 AS dst", "'x' AS label", "timestamp_micros(1000000 * (20000 - id)) AS ts").withWatermark("ts", "1 day")
    step = {}
    began = time.perf_counter()
    frame = rows.toPandas()
    state = SimpleNamespace(hasTimedOut=False, exists=False, update=lambda x: step.update(state=x), setTimeoutTimestamp=lambda x: None, getCurrentWatermarkMs=lambda: 0)
    grouped = SimpleNamespace(applyInPandasWithState=lambda f, *_: list(f(("x",), iter([frame]), state)))
    edges = SimpleNamespace(schema=rows.schema, groupBy=lambda by: grouped)
    out = streams.stateful_paths(edges, "label", 12 * 3_600_000_000, 3)
    assert sum(map(len, out)) == 20_000 and len(step["state"][0]) == 20_000 and time.perf_counter() - began < 5
