"""Property graphs as DataFrames."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


#: The id of an edge of two halves is its key times this, plus the other's.
SHIFT = 1_000_000_000


@dataclass(frozen=True)
class Halves:
    """Edges as a join that isn't carried out, where they are far more than the rows that make them.

    begin: (src, key, day, part, n, label, properties ...), a row for the edges that begin
    there, n of them; end: (dst, other, day, part). Two of equal day and part, of different
    keys and vertices, are an edge. exact: a key names one row and is below SHIFT. shared:
    properties that are the same for all edges of a day and part.
    """

    begin: DataFrame
    end: DataFrame
    exact: bool
    shared: tuple[str, ...] = ()
    edges: DataFrame = field(init=False)

    def __post_init__(self) -> None:
        met = self.begin.join(self.end, ["day", "part"]).where("key <> other AND src <> dst")
        more = [c for c in self.begin.columns if c not in ("src", "key", "day", "part", "n", "label")]
        object.__setattr__(self, "edges", met.select((F.col("key") * SHIFT + F.col("other")).alias("id"), "src", "dst", "label", *more))


@dataclass(frozen=True)
class PropertyGraph:
    """edges: (id, src, dst, label, properties ...); vertices: (v, properties ...), optional. alphabet: its labels, where known. halves: what makes the edges."""

    edges: DataFrame
    vertices: DataFrame | None = None
    alphabet: tuple[str, ...] = ()
    halves: Halves | None = None

    @classmethod
    def from_table(cls, df: DataFrame, id: str | Column, src: str | Column, dst: str | Column, label: str | Column | None = None, vertices: DataFrame | None = None, alphabet: tuple[str, ...] = (), **properties: str | Column) -> PropertyGraph:
        """Columns of any table in the roles of a graph."""
        as_column = lambda x: F.col(x) if isinstance(x, str) else x
        kept = [as_column(c).alias(n) for n, c in (("id", id), ("src", src), ("dst", dst), ("label", label if label is not None else F.lit("")), *properties.items())]
        return cls(df.select(*kept), vertices, alphabet)

    @property
    def parts(self) -> Halves | None:
        """The halves, unless the edges are others by now."""
        return self.halves if self.halves is not None and self.halves.edges is self.edges else None

    def labels(self) -> tuple[str, ...]:
        return self.alphabet or tuple(sorted(r[0] for r in self.edges.select("label").distinct().collect() if r[0] is not None))

    def where(self, condition: str | Column) -> PropertyGraph:
        return replace(self, edges=self.edges.where(condition))

    def reversed(self) -> PropertyGraph:
        return replace(self, edges=self.edges.withColumnsRenamed({"src": "dst", "dst": "src"}))


def out_degrees(graph: PropertyGraph) -> DataFrame:
    """(v, degree) of vertices with out-edges."""
    if graph.parts:
        return graph.parts.begin.groupBy(F.col("src").alias("v")).agg(F.sum("n").alias("degree")).where("degree > 0")
    return graph.edges.groupBy(F.col("src").alias("v")).agg(F.count(F.lit(1)).alias("degree"))


def degree_stats(graph: PropertyGraph) -> DataFrame:
    """One row: (vertices, edges, q1, q2, q3) over out-degrees."""
    return out_degrees(graph).agg(F.count(F.lit(1)).alias("vertices"), F.sum("degree").alias("edges"), *[F.percentile("degree", p).alias(n) for n, p in (("q1", 0.25), ("q2", 0.5), ("q3", 0.75))])


def starts(graph: PropertyGraph, kind: str = "iqr") -> DataFrame:
    """(v, degree) of vertices in the interquartile range of out-degrees, or (top) in the top quartile."""
    degrees = out_degrees(graph)
    bounds = degrees.agg(F.percentile("degree", 0.25).alias("low"), F.percentile("degree", 0.75).alias("high"))
    keep = F.col("degree").between(F.col("low"), F.col("high")) if kind == "iqr" else F.col("degree") >= F.col("high")
    return degrees.crossJoin(F.broadcast(bounds)).where(keep).select("v", "degree")  # bounds: one row


def first_start(graph: PropertyGraph, kind: str = "iqr") -> DataFrame:
    """(v) of the least vertex that qualifies."""
    return starts(graph, kind).agg(F.min("v").alias("v"))
