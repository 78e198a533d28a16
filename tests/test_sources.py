from pyspark.sql import functions as F

from pathsieve.functions import constraints as C
from pathsieve.operators import levels
from pathsieve.plans.graph import PropertyGraph, degree_stats
from pathsieve.plans.spec import GuardedPathQuery
from pathsieve.sources.tables import micros, read_edges, stream_edges, write_paths
from pathsieve.streaming import paths as streams

ROWS = [(1, 1, 2, "a", 10), (2, 2, 3, "b", 20), (3, 3, 1, "a", 5), (4, 2, 3, "a", 30)]
SCHEMA = "id long, src long, dst long, label string, t long"


def test_edge_lists_in_several_formats(spark, tmp_path):
    df = spark.createDataFrame(ROWS, SCHEMA)
    for fmt in ("csv", "json", "orc", "parquet"):
        df.write.format(fmt).save(f"{tmp_path}/{fmt}")
        g = PropertyGraph.from_table(read_edges(spark, f"{tmp_path}/{fmt}", fmt, SCHEMA), "id", "src", "dst", "label", t="t")
        found = levels.paths(GuardedPathQuery(g, C.Monotone("t"), sources=(1,), max_len=2))
        write_paths(found, f"{tmp_path}/out-{fmt}")
        assert sorted(r["edge_ids"] for r in spark.read.parquet(f"{tmp_path}/out-{fmt}").collect()) == ["1", "1-2", "1-4"]
        assert g.labels() == ("a", "b") and degree_stats(g).first()["edges"] == 4


def test_streamed_chain_equals_the_batch_join(spark, tmp_path):
    df = spark.createDataFrame(ROWS, SCHEMA).withColumn("ts", F.timestamp_seconds("t"))
    df.write.parquet(f"{tmp_path}/edges")
    edges = lambda: stream_edges(spark, f"{tmp_path}/edges", df.schema, "ts", "1 hour")
    found = streams.run_to_end(streams.chain(edges(), edges(), "15 SECONDS").select("id1", "id2"), f"{tmp_path}/chained")
    assert {tuple(r) for r in found.collect()} == {(1, 2), (3, 1)}
    assert df.select(micros(F.col("ts").cast("timestamp_ntz")).alias("m")).first()["m"] == 10_000_000


def test_guard_and_batches(spark):
    g = PropertyGraph(spark.createDataFrame(ROWS, SCHEMA))
    q = GuardedPathQuery(g, max_len=3)
    assert sorted(map(tuple, levels.levels_in_batches(q, 2).collect())) == sorted(map(tuple, levels.levels(q).collect()))
    try:
        levels.levels(q.vary(max_frontier_rows=2))
    except RuntimeError as e:
        assert "max_frontier_rows" in str(e)
    else:
        raise AssertionError
