"""Edge layouts that keep a level from scanning or shuffling all edges."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathsieve.plans.graph import PropertyGraph


def write_partitioned(graph: PropertyGraph, path: str, parts: int = 16) -> None:
    """Folders by hash of src, files sorted by (src, t): a frontier that touches few vertices reads few folders, and a time range skips row groups."""
    time = ["t"] if "t" in graph.edges.columns else []
    graph.edges.withColumn("sb", F.pmod(F.xxhash64("src"), F.lit(parts)).cast("int")).repartition(parts, "sb").sortWithinPartitions("sb", "src", *time).write.mode("overwrite").partitionBy("sb").parquet(path)


def read_partitioned(spark: SparkSession, path: str, sources: DataFrame | None = None, parts: int = 16) -> DataFrame:
    """Edges; with sources (v), a join that lets the engine prune folders at run time."""
    edges = spark.read.parquet(path)
    if sources is None:
        return edges.drop("sb")
    keys = sources.select(F.col("v").alias("src"), F.pmod(F.xxhash64("v"), F.lit(parts)).cast("int").alias("sb")).distinct()
    return edges.join(keys, ["sb", "src"], "left_semi").drop("sb")


def write_bucketed(graph: PropertyGraph, name: str, buckets: int = 16) -> None:
    """A table bucketed by src: joins on src need no shuffle of the edges."""
    spark = graph.edges.sparkSession
    spark.sql(f"DROP TABLE IF EXISTS {name}")
    graph.edges.write.bucketBy(buckets, "src").sortBy("src").mode("overwrite").saveAsTable(name)


def adjacency(graph: PropertyGraph, *properties: str, chunk: int = 10_000) -> DataFrame:
    """(src, chunk, out): out-edges as sorted arrays of at most `chunk` edges, so that no vertex makes an unbounded row."""
    columns = ["id", "dst", "label", *properties]
    dealt = graph.edges.withColumn("chunk", F.pmod(F.xxhash64("id"), F.lit(1 << 20)))
    sizes = graph.edges.groupBy("src").agg(F.ceil(F.count(F.lit(1)) / chunk).alias("chunks"))
    return dealt.join(sizes, "src").withColumn("chunk", F.pmod("chunk", F.col("chunks"))).groupBy("src", "chunk").agg(F.sort_array(F.collect_list(F.struct(*properties, *[c for c in columns if c not in properties]))).alias("out"))


def from_adjacency(adj: DataFrame, condition: str | None = None) -> DataFrame:
    """Edges again; condition over the array's fields (as x.<field>) runs before anything is exploded."""
    out = F.expr(f"filter(out, x -> {condition})") if condition else F.col("out")
    return adj.select("src", F.explode(out).alias("e")).select("src", "e.*")


def salted(graph: PropertyGraph, salts: int) -> DataFrame:
    """Edges with a salt by id, for frontiers that are replicated over the salts of heavy vertices."""
    return graph.edges.withColumn("salt", F.pmod(F.xxhash64("id"), F.lit(salts)).cast("int"))


def expand_salted(frontier: DataFrame, graph: PropertyGraph, heavy: DataFrame, salts: int) -> DataFrame:
    """frontier (v, ...) joined with its out-edges; those of heavy vertices (v) spread over `salts` keys, all others under one."""
    marks = heavy.select("v", F.lit(salts).alias("n_salts")).distinct()
    left = frontier.join(marks, "v", "left").withColumn("salt", F.explode(F.sequence(F.lit(0), F.coalesce("n_salts", F.lit(1)) - 1))).drop("n_salts")
    right = salted(graph, salts).join(marks.withColumnRenamed("v", "src"), "src", "left").withColumn("salt", F.when(F.col("n_salts").isNull(), 0).otherwise(F.col("salt"))).drop("n_salts")
    return left.join(right, (left["v"] == right["src"]) & (left["salt"] == right["salt"])).drop(left["salt"]).drop("salt")
