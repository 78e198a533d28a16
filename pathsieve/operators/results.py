"""Operators on answers: counts, summaries, rankings, set operations, exploding and replaying paths."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pathsieve.plans.graph import PropertyGraph


def count_paths(paths: DataFrame, *by: str) -> DataFrame:
    return paths.groupBy(*by).agg(F.count(F.lit(1)).alias("n"))


def distinct_ends(paths: DataFrame) -> DataFrame:
    """(len, n_ends): different last vertices of each length."""
    return paths.groupBy(F.col("len").cast("long").alias("len")).agg(F.countDistinct("v").alias("n_ends"))


def summarize(paths: DataFrame, how: str, *by: str) -> DataFrame:
    """Counts over rollup, cube or grouping sets (each column alone) of the given columns."""
    n = F.count(F.lit(1)).alias("n")
    if how == "rollup":
        return paths.rollup(*by).agg(n)
    if how == "cube":
        return paths.cube(*by).agg(n)
    return paths.groupingSets([[F.col(c)] for c in by], *[F.col(c) for c in by]).agg(n)


def top_k(paths: DataFrame, k: int, *order: str | Column) -> DataFrame:
    """The first k by the order: a bounded heap in each task."""
    return paths.orderBy(*order).limit(k)


def rank_paths(paths: DataFrame, per: str, k: int, *order: str | Column) -> DataFrame:
    """The first k of each value of `per`, with their rank."""
    return paths.withColumn("rank", F.row_number().over(Window.partitionBy(per).orderBy(*order)).cast("long")).where(F.col("rank") <= k)


def path_edges(paths: DataFrame, graph: PropertyGraph, *properties: str) -> DataFrame:
    """(start, edge_ids, k, id, properties): the edges of every path, k from 1."""
    each = paths.select("start", "edge_ids", F.posexplode(F.split("edge_ids", "-")).alias("k0", "text")).select("start", "edge_ids", (F.col("k0") + 1).cast("long").alias("k"), F.col("text").cast("long").alias("id"))
    return each.join(graph.edges.select("id", *properties), "id").select("start", "edge_ids", "k", "id", *properties)


def running_sum(edges: DataFrame, value: str) -> DataFrame:
    w = Window.partitionBy("start", "edge_ids").orderBy("k").rowsBetween(Window.unboundedPreceding, 0)
    return edges.withColumn("running", F.sum(value).over(w))


def asof_next_edge(graph: PropertyGraph, time: str = "t") -> DataFrame:
    """(id, next_id): the earliest edge out of an edge's end that is strictly later; ties by id.

    Arrivals and departures of a vertex go through one sort: no pair is made.
    """
    e = graph.edges
    arrivals = e.select(F.col("dst").alias("v"), F.col(time).alias("at"), F.lit(1).alias("kind"), F.col("id"))
    departures = e.select(F.col("src").alias("v"), F.col(time).alias("at"), F.lit(0).alias("kind"), F.col("id"))
    w = Window.partitionBy("v").orderBy(F.col("at").desc(), F.col("kind").desc(), F.col("id").desc())
    # from the last time to the first, so that the frame only grows; a departure at an arrival's time isn't later: it comes after the arrival here
    ahead = F.last(F.when(F.col("kind") == 0, F.col("id")), ignorenulls=True).over(w.rowsBetween(Window.unboundedPreceding, -1))
    return arrivals.unionByName(departures).withColumn("next_id", ahead).where("kind = 1 AND next_id IS NOT NULL").select("id", "next_id")


def binned_range_join(left: DataFrame, right: DataFrame, key: str, time: str, width: int) -> DataFrame:
    """Pairs of equal key whose times differ by at most `width`: an equi-join on time bins, so that it is never a nested loop. right's columns get the prefix r_."""
    bins = left.withColumn("bin", F.explode(F.array([F.floor(F.col(time) / width) + k for k in (-1, 0, 1)])))
    other = right.select(*[F.col(c).alias(f"r_{c}") for c in right.columns]).withColumn("r_bin", F.floor(F.col(f"r_{time}") / width))
    return bins.join(other, (F.col(key) == F.col(f"r_{key}")) & (F.col("bin") == F.col("r_bin"))).where(F.abs(F.col(time) - F.col(f"r_{time}")) <= width).drop("bin", "r_bin")


def two_hop(graph: PropertyGraph) -> DataFrame:
    """(src, mid, dst) of neighbouring edges."""
    a = graph.edges.select("src", F.col("dst").alias("mid"))
    return a.join(graph.edges.select(F.col("src").alias("mid"), "dst"), "mid").select("src", "mid", "dst")


def dead_ends(graph: PropertyGraph) -> DataFrame:
    """(v) of vertices that edges lead to and none leaves."""
    return graph.edges.select(F.col("dst").alias("v")).distinct().join(graph.edges.select(F.col("src").alias("v")).distinct(), "v", "left_anti")


def same_paths(a: DataFrame, b: DataFrame) -> bool:
    return a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()


@F.udtf(returnType="from_state: int, to_state: int, label: string")
class Transitions:
    """Table function: the automaton of a label expression."""

    def eval(self, regex: str) -> Iterator[tuple[int, int, str]]:
        from pathsieve.plans.regex import glushkov, parse_regex

        yield from glushkov(parse_regex(regex)).rows()


def register_sql(spark: SparkSession) -> None:
    """transitions('a+ b') in SQL."""
    spark.udtf.register("transitions", Transitions)
