"""Connected components of links between long ids, by star contraction in DataFrame joins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathsieve.llm.shared import cut


def _stars(edges: DataFrame, large: bool) -> DataFrame:
    """Every node tells its neighbours (large: those above it; else itself and those below it) the least id that it knows."""
    both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))) if large else edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
    told = both.join(least, "a")
    if large:
        return told.where("b > a AND b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
    return told.where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(least.where("a <> m").select("a", F.col("m").alias("b"))).distinct()


def components(links: DataFrame, a: str, b: str) -> DataFrame:
    """(id, component) of every id in a link; component is the least id that it reaches. Links to itself and repeated links don't matter; nulls are left out."""
    edges = cut(links.select(F.col(a).cast("long").alias("a"), F.col(b).cast("long").alias("b")).where("a <> b").distinct())
    seen = None
    while True:
        edges = cut(_stars(_stars(edges, True), False))
        now = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if now == seen:
            break
        seen = now
    return edges.select(F.col("a").alias("id"), F.col("b").alias("component")).unionByName(edges.select(F.col("b").alias("id"), F.col("b").alias("component")).distinct())
