"""The query: a graph, a label expression, a pruning aggregate, endpoints, lengths; and its plan."""

from __future__ import annotations

import re
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathsieve.functions.constraints import Acyclic, Trail
from pathsieve.plans.aggregate import Check, PruningAggregate, compose
from pathsieve.plans.graph import PropertyGraph
from pathsieve.plans.regex import Nfa, automaton, is_ambiguous, min_hops_to_accept

REWRITES = frozenset(["elide_trail", "hoist", "envelope", "remaining_hops", "targets", "salt"])


@dataclass(frozen=True)
class GuardedPathQuery:
    """All paths of min_len to max_len edges from `sources` whose labels spell a word of `regex` and that satisfy `constraint`.

    sources: vertex ids, a DataFrame (v), or None for every vertex with out-edges.
    targets: where a path must end; via: vertices that it must pass between its ends.
    semantics: trail (no edge twice), acyclic (no vertex twice) or walk.
    dedupe: several automaton runs of one path count once; else each counts.
    max_frontier_rows: a level above it ends the run with an error that names all levels' sizes.
    """

    graph: PropertyGraph
    constraint: PruningAggregate = field(default_factory=PruningAggregate)
    regex: str | None = None
    sources: DataFrame | tuple[int, ...] | None = None
    targets: DataFrame | tuple[int, ...] | None = None
    via: tuple[int, ...] = ()
    min_len: int = 1
    max_len: int = 4
    semantics: str = "trail"
    dedupe: bool = True
    rewrites: frozenset[str] = frozenset(["elide_trail", "hoist"])
    max_frontier_rows: int | None = None

    def __post_init__(self) -> None:
        if not 0 <= self.min_len <= self.max_len:
            raise ValueError("0 <= min_len <= max_len")
        if self.semantics not in ("trail", "walk", "acyclic"):
            raise ValueError(f"semantics {self.semantics!r}")
        if unknown := self.rewrites - REWRITES:
            raise ValueError(f"rewrites {sorted(unknown)}")

    def vary(self, **changes: object) -> GuardedPathQuery:
        return replace(self, **changes)


@dataclass(frozen=True)
class PathPlan:
    """What executors run: everything resolved to SQL text and numbers."""

    query: GuardedPathQuery
    nfa: Nfa | None
    aggregate: PruningAggregate
    needs_ids: bool

    @property
    def accepting(self) -> list[int] | None:
        return None if self.nfa is None else sorted(self.nfa.accepting)

    def check_text(self, check: Check) -> str:
        """A test that depends on transitions becomes a CASE over states; one that doesn't is its plain text."""
        text = self._filled(check.text)
        if not check.cases:
            return text
        if self.nfa is None:
            raise ValueError("a constraint names tags, but the query has no label expression")
        by_text: dict[str, list[str]] = {}
        for (a, b), body in check.cases:  # transitions of equal bodies share a branch
            condition = " AND ".join(["true", *([] if a == "*" else [f"q IN ({self._states(a)})"]), *([] if b == "*" else [f"to_state IN ({self._states(b)})"])])
            by_text.setdefault(self._filled(body), []).append(f"({condition})")
        return f"CASE {' '.join(f'WHEN {" OR ".join(c)} THEN ({body})' for body, c in by_text.items())} ELSE ({text}) END"

    def _states(self, tag: str | None) -> str:
        states = [0] if tag is None else self.nfa.tagged(tag)
        if not states:
            raise ValueError(f"no label of the expression is tagged {tag!r}")
        return ", ".join(map(str, states))

    def _filled(self, text: str) -> str:
        return re.sub(r"\{(\w+)\}", lambda m: str(self.query.max_len) if m[1] == "max_len" else self._states(m[1]), text)

    @property
    def edge_checks(self) -> list[str]:
        return [self._filled(c.text) for c in self.aggregate.admit if c.edge_only]

    @property
    def step_checks(self) -> list[str]:
        hoisted = "hoist" in self.query.rewrites
        return [self.check_text(c) for c in self.aggregate.admit if not (hoisted and c.edge_only)]

    def advance(self) -> dict[str, str]:
        return {s.name: self._filled(self.aggregate.advance[s.name]) for s in self.aggregate.slots}

    @property
    def edge_columns(self) -> list[str]:
        return sorted({"id", "src", "dst"} | ({"label"} if self.nfa or "label" in self.aggregate.uses else set()) | {u for u in self.aggregate.uses if not u.startswith("vertex.")})

    @property
    def vertex_columns(self) -> list[str]:
        return sorted(u[7:] for u in self.aggregate.uses if u.startswith("vertex."))

    def edges(self) -> DataFrame:
        """The edge side: only used columns, renamed to e_<name>, labels and edge-only checks pushed to the scan."""
        edges = self.query.graph.edges
        if self.nfa is not None:
            edges = edges.where(F.col("label").isin(self.nfa.alphabet))
        edges = edges.select(*[F.col(c).alias(f"e_{c}") for c in self.edge_columns])
        if "hoist" in self.query.rewrites:
            for text in self.edge_checks:
                edges = edges.where(text)
        if self.vertex_columns:
            if self.query.graph.vertices is None:
                raise ValueError("the graph has no vertex table")
            vertices = self.query.graph.vertices.select(F.col("v").alias("e_dst"), *[F.col(c).alias(f"w_{c}") for c in self.vertex_columns])
            edges = edges.join(vertices, "e_dst", "left")
        return edges

    def halves(self) -> tuple[DataFrame, DataFrame] | None:
        """(beginnings e_*, ends i_*) of the edges, where the graph has such and the query's edges need no other side."""
        h = self.query.graph.parts
        if h is None or self.nfa is not None or self.vertex_columns or self.edge_checks:
            return None
        kept = [c for c in self.edge_columns if c not in ("id", "dst")] + ["key", "n", "day", "part"]
        return h.begin.select(*[F.col(c).alias(f"e_{c}") for c in kept]), h.end.select(F.col("dst").alias("e_dst"), F.col("other").alias("i_other"), F.col("day").alias("i_day"), F.col("part").alias("i_part"))

    def anchors(self) -> DataFrame:
        """(start, v, q, len, slots): one row for each start."""
        q, spark = self.query, self.query.graph.edges.sparkSession
        if q.sources is None and q.graph.parts:
            rows = q.graph.parts.begin.where("n > 0").select(F.col("src").alias("v")).distinct()
        elif q.sources is None:
            rows = q.graph.edges.select(F.col("src").alias("v")).distinct()
        elif isinstance(q.sources, DataFrame):
            rows = q.sources.select("v").distinct()
        else:
            rows = spark.createDataFrame([(int(v),) for v in sorted(set(q.sources))], "v long")
        seeds = [F.expr(f"CAST({s.seed} AS {s.dtype})").alias(f"s_{s.name}") for s in self.aggregate.slots]
        return rows.select(F.col("v").alias("start"), "v", F.lit(0).alias("q"), F.lit(0).alias("len"), *seeds)

    def transitions(self) -> DataFrame:
        return F.broadcast(self.nfa.to_df(self.query.graph.edges.sparkSession))  # rows of the expression, not of the data

    def hops_left(self) -> dict[int, int]:
        return min_hops_to_accept(self.nfa) if self.nfa else {}


def plan(query: GuardedPathQuery, early: bool = True, with_ids: bool = False) -> PathPlan:
    """Resolves a query. early=False leaves the trail test out as well (walks)."""
    nfa = None
    if query.regex is not None:
        needs = "[^" in query.regex or "." in query.regex
        nfa = automaton(query.regex, query.graph.labels() if needs else (), every_run=not query.dedupe)
    aggregate = query.constraint
    if query.semantics == "acyclic":
        aggregate = compose(aggregate, Acyclic())
    ambiguous = nfa is not None and query.dedupe and is_ambiguous(nfa)
    needs_ids = with_ids or ambiguous or bool(query.via)
    strict = any(t.startswith("strict:") and not t.startswith("strict:vertex") for t in aggregate.traits)
    if query.semantics == "trail" and early:
        # A strictly monotone edge property repeats no edge; where it may be missing, a repeated edge fails too, since NULL compares with nothing after the first hop.
        elide = "elide_trail" in query.rewrites and strict and not needs_ids and "trail" not in query.constraint.traits
        if not elide:
            aggregate = compose(aggregate, Trail())
    if needs_ids and "edge_ids" not in {s.name for s in aggregate.slots}:
        trail = Trail()
        aggregate = compose(aggregate, replace(trail, admit=(), oracle=(), traits=frozenset()))
    return PathPlan(query, nfa, aggregate, needs_ids)
