"""The experiment workloads on the given tables, and post-filter brute force in SQL for each."""

from __future__ import annotations

import re
from collections.abc import Callable
from dataclasses import dataclass, field
from datetime import timedelta

from pyspark.sql import DataFrame, SparkSession

from pathsieve.functions import constraints as C
from pathsieve.plans.aggregate import PruningAggregate, compose
from pathsieve.plans.graph import first_start
from pathsieve.plans.regex import Nfa, automaton
from pathsieve.plans.spec import GuardedPathQuery
from pathsieve.sources.encodings import EDGE_SQL, VERTEX_SQL, stored
from pathsieve.sources.tables import load

DAY = timedelta(days=1)


@dataclass(frozen=True)
class Workload:
    """start: iqr or top (one vertex by the degree rule), all, or SQL of (v)."""

    encoding: str
    constraint: PruningAggregate = field(default_factory=PruningAggregate)
    regex: str | None = None
    start: str = "iqr"
    max_len: int = 4
    min_len: int = 1
    semantics: str = "trail"
    targets: tuple[int, ...] | None = None
    via: tuple[int, ...] = ()
    every_run: bool = False

    def query(self, spark: SparkSession, sf_dir: str, **changes: object) -> GuardedPathQuery:
        graph = stored(spark, sf_dir, self.encoding)
        if self.start == "all":
            sources = None
        elif self.start in ("iqr", "top"):
            sources = first_start(graph, self.start)
        else:
            sources = SOURCES[self.start](spark, sf_dir)
        given = {"graph": graph, "constraint": self.constraint, "regex": self.regex, "sources": sources, "targets": self.targets, "via": self.via, "min_len": self.min_len, "max_len": self.max_len, "semantics": self.semantics}
        return GuardedPathQuery(**(given | changes))

    def nfa(self) -> Nfa | None:
        if self.regex is None:
            return None
        return automaton(self.regex, ALPHABETS[self.encoding] if "." in self.regex or "[^" in self.regex else (), self.every_run)

    # -- the same by brute force, for DuckDB -----------------------------------------

    def walks(self, tested: bool = True, trail: bool | None = None, semantics: str | None = None, early: int = 0) -> str:
        """CTEs ending in `answers` (start, v, len, ids): every walk with lists, then every constraint on the finished lists. tested=False: only the label expression's prefixes. early: the first so many constraints, and the trail, hold for every prefix of an answer, so that walks that break them are not carried on."""
        nfa, semantics = self.nfa(), semantics or self.semantics
        props = sorted({u for u in self.constraint.uses})
        names = [f"p_{u.replace('.', '_')}" for u in props]
        values = [f"w.{u[7:]}" if u.startswith("vertex.") else f"e.{u}" for u in props]
        vertex = f", vertices AS ({VERTEX_SQL[self.encoding]})" if self.encoding in VERTEX_SQL else ""
        degrees = ", degrees AS (SELECT src AS v, count(*) AS degree FROM edges GROUP BY src)"
        if self.start == "all":
            begin = "SELECT DISTINCT src AS v FROM edges"
        elif self.start in ("iqr", "top"):
            keep = "degree BETWEEN (SELECT quantile_cont(degree, 0.25) FROM degrees) AND (SELECT quantile_cont(degree, 0.75) FROM degrees)" if self.start == "iqr" else "degree >= (SELECT quantile_cont(degree, 0.75) FROM degrees)"
            begin = f"SELECT min(v) AS v FROM degrees WHERE {keep}"
        else:
            begin = SOURCE_SQL[self.start]
        rows = f", trans(f, t, l) AS (VALUES {', '.join(f"({f}, {t}, '{x}')" for f, t, x in nfa.rows())})" if nfa else ""
        seeds = "".join(f", CAST([] AS {PROPERTY_TYPES.get(u, 'BIGINT')}[])" for u in props)
        on_trail = " AND NOT list_contains(ids, e.id)" if trail else ""
        join = " JOIN trans ON trans.f = q AND trans.l = e.label" if nfa else ""
        vjoin = " LEFT JOIN vertices w ON w.v = e.dst" if any(u.startswith("vertex.") for u in props) else ""
        fill = lambda text: re.sub(r"\{(\w+)\}", lambda m: str(nfa.tagged(m[1])), text)
        kept = [f"({fill(x)})" for x in self.constraint.oracle[:early]] + ["len(ids) = len(list_distinct(ids))"] * (early > 0 and semantics == "trail")
        names_of = f"start, v, q, len, ids, vs, qs{''.join(', ' + n for n in names)}"
        grown = f"SELECT start, e.dst AS v, {'trans.t' if nfa else '0'} AS q, len + 1 AS len, list_append(ids, e.id) AS ids, list_append(vs, e.dst) AS vs, list_append(qs, {'trans.t' if nfa else '0'}) AS qs{''.join(f', list_append({n}, {v}) AS {n}' for n, v in zip(names, values, strict=True))} FROM walks JOIN edges e ON walks.v = e.src{vjoin}{join} WHERE len < {self.max_len}{on_trail}"
        if kept:
            grown = f"SELECT {names_of} FROM ({grown}) WHERE {' AND '.join(kept)}"
        body = (
            f"WITH RECURSIVE edges AS MATERIALIZED ({EDGE_SQL[self.encoding]}){vertex}{degrees}{rows}, begin AS ({begin}), "
            f"walks({names_of}) AS (SELECT v, v, 0, 0, CAST([] AS BIGINT[]), [v], CAST([] AS INTEGER[]){seeds} FROM begin UNION ALL {grown})"
        )
        if not tested:
            return f"{body}, answers AS (SELECT start, v, len, ids FROM walks WHERE len > 0)"
        tests = [f"len >= {self.min_len}"]
        if nfa:
            tests.append(f"q IN ({', '.join(map(str, sorted(nfa.accepting)))})")
        tests += ["len(ids) = len(list_distinct(ids))"] * (semantics == "trail") + ["len(vs) = len(list_distinct(vs))"] * (semantics == "acyclic")
        tests += [f"({fill(x)})" for x in self.constraint.oracle]
        if self.targets is not None:
            tests.append(f"v IN ({', '.join(map(str, self.targets))})")
        for x in self.via:
            tests.append(f"list_contains(vs[2:len], {x})")
        return f"{body}, answers AS (SELECT DISTINCT start, v, len, ids FROM walks WHERE {' AND '.join(tests)})"

    def levels_sql(self, **how: object) -> str:
        return f"{self.walks(**how)} SELECT CAST(len AS BIGINT) AS len, count(*) AS n FROM answers GROUP BY len"

    def paths_sql(self) -> str:
        return f"{self.walks()} SELECT start, v, CAST(len AS INTEGER) AS len, array_to_string(ids, '-') AS edge_ids FROM answers"

    def candidates_sql(self, trail: bool) -> str:
        """Prefixes of a check-at-the-end engine: all runs, so that nothing is made distinct."""
        return f"{self.walks(tested=False, trail=trail)} SELECT CAST(len AS BIGINT) AS len, count(*) AS n FROM answers GROUP BY len"


PROPERTY_TYPES = {"amount": "DOUBLE", "weight": "DOUBLE", "color": "VARCHAR", "label": "VARCHAR", "vertex.vlabel": "VARCHAR", "vertex.acctbal": "DOUBLE", "sim": "DOUBLE"}
ALPHABETS = {"payments": ("Domestic", "Foreign"), "handover": ("click", "error", "purchase", "signup", "view"), "dialog": ("assistant", "system", "user"), "basket": ("A", "N", "R")}


def _nation_customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "customer").where("c_nationkey = 3").selectExpr("2 * c_custkey AS v")


def _roots(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "conversations").selectExpr("conv_id * 1000000 AS v").distinct()


SOURCES: dict[str, Callable[[SparkSession, str], DataFrame]] = {"nation 3": _nation_customers, "roots": _roots}
SOURCE_SQL = {"nation 3": "SELECT 2 * c_custkey AS v FROM customer WHERE c_nationkey = 3", "roots": "SELECT DISTINCT conv_id * 1000000 AS v FROM conversations"}

Q1_REGEX = "normal:(click|view|purchase)+ fishy:(error|signup)+"
QB_REGEX = "dom:Domestic+ fgn:Foreign"


def _qb(near: int, far: int) -> PruningAggregate:
    return C.StepWithin("t", by={("dom", "dom"): near * DAY, ("dom", "fgn"): far * DAY})


Q1 = compose(C.Monotone("t"), C.SameAsFirst("region", "BIGINT"), C.SpreadAtMost("risk", 20, within="normal"), C.LastOfSegmentAtLeast("risk", "normal", "fishy", 40), C.SumAtLeast("amount", 200))
QA = lambda u: C.Monotone("t") & C.SpreadAtMost("amount", u, "DOUBLE")

WORKLOADS: dict[str, Workload] = {
    "qa": Workload("payments", QA(50_000)),
    "qa_wide": Workload("payments", QA(100_000)),
    "qa_all": Workload("payments", QA(50_000), start="all", max_len=3),
    "qa_zero": Workload("payments", QA(50_000), min_len=0, max_len=3),
    "qa_pair": Workload("payments", QA(100_000), min_len=2, max_len=3, targets=(13, 52, 779)),
    "qa_via": Workload("payments", QA(100_000), max_len=3, via=(449,)),
    "qb": Workload("payments", _qb(2, 3), QB_REGEX, "all"),
    "qb_wide": Workload("payments", _qb(30, 45), QB_REGEX, "all"),
    "q1": Workload("handover", Q1, Q1_REGEX, "top", 3),
    "q2": Workload("payments", C.AdjacentEqualExists("color")),
    "q2_handover": Workload("handover", C.AdjacentEqualExists("label"), max_len=3),
    "q3_payments": Workload("payments", C.Monotone("t")),
    "q3_handover": Workload("handover", C.Monotone("t"), max_len=3),
    "q3_basket_t": Workload("basket", C.Monotone("t"), max_len=4),
    "q3_basket_weight": Workload("basket", C.Monotone("weight", "DOUBLE"), max_len=4),
    "q4_knows": Workload("knows", C.SpreadAtMost("t", 14 * DAY)),
    "q4_handover": Workload("handover", C.SpreadAtMost("t", timedelta(hours=6)), max_len=3),
    "supply_same_nation": Workload("supply", compose(C.Monotone("t"), C.SameAsFirst("vertex.nation", "BIGINT"), C.VertexPredicate("w_nation = 3 AND w_acctbal > 0", "p_vertex_nation[i] = 3 AND p_vertex_acctbal[i] > 0", ["nation", "acctbal"])), start="nation 3", max_len=2),
    "supply_vertex_label": Workload("supply", compose(C.Monotone("t"), C.VertexPredicate("w_vlabel = 'supplier' OR w_nation = 3", "p_vertex_vlabel[i] = 'supplier' OR p_vertex_nation[i] = 3", ["vlabel", "nation"])), regex="buys ships", start="nation 3", max_len=2),
    "rx_domestic_foreign": Workload("payments", regex="Domestic+ Foreign", max_len=4, start="iqr"),
    "rx_dialog": Workload("dialog", regex="system? (user assistant)+", start="roots", max_len=8),
    "rx_ambiguous_paths": Workload("handover", regex="(click|click click)+ error", max_len=3, semantics="walk"),
    "rx_optional": Workload("payments", regex="Domestic? Foreign Domestic*", max_len=3),
    "rx_bounded": Workload("payments", regex="Domestic{1,2} Foreign{2}", max_len=4),
    "rx_negated": Workload("handover", regex="[^click view]{2}", max_len=2),
    "rx_wildcard": Workload("payments", regex=". Domestic .", max_len=3),
    "k_spread_at_least": Workload("payments", C.SpreadAtLeast("amount", 300_000, "DOUBLE"), max_len=3),
    "k_sum_at_least_bounded": Workload("payments", C.SumAtLeast("amount", 900_000, edge_upper_bound=600_000), max_len=3),
    "k_sum_at_most": Workload("payments", C.SumAtMost("amount", 200_000), max_len=3),
    "k_same_as_first": Workload("payments", C.SameAsFirst("color"), max_len=3),
    "k_step_within": Workload("payments", C.StepWithin("t", 30 * DAY), max_len=3),
    "k_decreasing": Workload("payments", C.Monotone("t", increasing=False, strict=False), max_len=3),
    "k_any_of": Workload("payments", C.AnyOf("e_amount > 400000", "p_amount[i] > 400000", ["amount"]), max_len=3),
    "k_all_of": Workload("payments", C.AllOf("e_amount > 150000", "p_amount[i] > 150000", ["amount"]), max_len=3),
    "k_edge_predicate": Workload("basket", C.EdgePredicate("e_weight < 20000", "p_weight[i] < 20000", ["weight"]) & C.Monotone("t"), max_len=3),
    "k_min_len": Workload("payments", C.Monotone("t"), min_len=3, max_len=3),
    "k_acyclic": Workload("payments", semantics="acyclic", max_len=3),
    "k_vertex": Workload("supply", C.VertexMonotone("acctbal", "DOUBLE"), start="nation 3", max_len=2),
    "k_collect_then_test": Workload("payments", C.CollectThenTest(["t"], "forall(sequence(2, greatest(size(s_all_t), 2)), i -> i > size(s_all_t) OR s_all_t[i - 1] > s_all_t[i - 2])", "len(list_filter(range(2, len + 1), lambda i: NOT (p_t[i] > p_t[i - 1]))) = 0"), max_len=3),
    "k_list_prop": Workload("knn", C.EdgePredicate("e_sim > 0.2", "p_sim[i] > 0.2", ["sim"]), start="all", max_len=2),
}
