"""The recursive-SQL executor: one WITH RECURSIVE statement per query."""

from __future__ import annotations

import re
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathsieve.operators.levels import EDGE_ID, ENDS, OPEN_ID, ends_alike, times_of
from pathsieve.plans.spec import GuardedPathQuery, PathPlan, plan
from pathsieve.sources.tables import shared_folder


def to_sql(p: PathPlan, anchors: str, edges: str, transitions: str | None, times: str | None = None) -> str:
    """The statement: a plain recursive select-project-join over the named views. The last hop stands behind the recursion, which would keep its rows. times: see recursion()."""
    slots = [f"s_{s.name}" for s in p.aggregate.slots]
    advance = [f"CAST({text} AS {s.dtype}) AS s_{s.name}" for s, text in zip(p.aggregate.slots, p.advance().values(), strict=True)]
    to_state = "to_state" if transitions else "0"
    checks = [f"({c.replace('to_state', to_state)})" for c in p.step_checks]
    join = f" JOIN {transitions} ON q = from_state AND e_label = t_label" if transitions else ""
    head = ", ".join(["start", "v", "q", "len", *slots])
    final = " AND ".join([f"len >= {p.query.min_len}", *([f"q IN ({', '.join(map(str, p.accepting))})"] if p.accepting else ["true"] if p.accepting is None else ["false"]), *p.aggregate.accept])
    grown = f"SELECT start, e_dst AS v, {to_state} AS q, len + 1 AS len{''.join(', ' + a for a in advance)}"
    return recursion(p, edges, f"SELECT {head} FROM {anchors}", grown, join, checks, f"SELECT {head}", final, times)


def recursion(p: PathPlan, edges: str, anchors: str, grown: str, join: str, checks: list[str], answers: str, final: str, times: str | None = None, last: str | None = None) -> str:
    """The statement's frame: `grown` extends the prefixes up to a hop before the last one; the answers are theirs and those of that hop, by `last` if it isn't `grown`.

    times: the last hop's edges are left open at their ends, and the answers have a column
    `times` of this text, how many each stands for (levels.ends_alike).
    """
    joined, last = f" JOIN {edges} ON v = e_src{join}", last or grown
    if p.halves() is not None:
        joined = f" JOIN {edges} ON v = e_src JOIN {edges}_ends ON {ENDS}{join}"
        put = lambda text, name, by: re.sub(rf"(?<![.\w'])e_{name}\b(?!:)", f"({by})", text)
        if times is not None:
            ended = lambda text: put(put(text, "id", OPEN_ID), "dst", "CAST(NULL AS BIGINT)")
            whole = f"{ended(last)}, {times} AS times FROM prefixes JOIN {edges} ON v = e_src{join} WHERE {' AND '.join([f'len = {p.query.max_len - 1}', *map(ended, checks)])}"
        grown, last, checks = put(grown, "id", EDGE_ID), put(last, "id", EDGE_ID), [put(c, "id", EDGE_ID) for c in checks]
    most = p.query.max_len - 1
    hop = lambda test, made=grown: f"{made} FROM prefixes{joined} WHERE {' AND '.join([test, *checks])}"
    if times is not None:
        return f"WITH RECURSIVE prefixes MAX RECURSION LEVEL {most + 1} AS ({anchors} UNION ALL {hop(f'len < {most}')}) {answers}, times FROM (SELECT *, 1 AS times FROM prefixes UNION ALL {whole}) WHERE {final}"
    if most < 1:
        return f"WITH RECURSIVE prefixes MAX RECURSION LEVEL {most + 2} AS ({anchors} UNION ALL {hop(f'len < {most + 1}')}) {answers} FROM prefixes WHERE {final}"
    return f"WITH RECURSIVE prefixes MAX RECURSION LEVEL {most + 1} AS ({anchors} UNION ALL {hop(f'len < {most}')}) {answers} FROM (SELECT * FROM prefixes UNION ALL {hop(f'len = {most}', last)}) WHERE {final}"


def _as_functions(p: PathPlan, name: str, made: list[str]) -> PathPlan:
    """The plan with each check and update behind a SQL-defined function, which the engine inlines again. made: gets their names."""
    spark = p.query.graph.edges.sparkSession
    types = {"len": "INT", "q": "INT", "to_state": "INT"} | {f"s_{s.name}": s.dtype for s in p.aggregate.slots} | {c: t for c, t in p.edges().dtypes}

    def behind(text: str, returns: str, k: str) -> str:
        used = [c for c in types if re.search(rf"\b{c}\b", text)]
        made.append(f"{name}_{k}")
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}_{k}({', '.join(f'{c} {types[c]}' for c in used)}) RETURNS {returns} RETURN {text}")
        return f"{name}_{k}({', '.join(used)})"

    agg = p.aggregate
    admit = tuple(replace(c, text=behind(p.check_text(c), "BOOLEAN", f"admit{k}"), cases=()) for k, c in enumerate(agg.admit))
    advance = {s.name: behind(text, s.dtype, f"advance_{s.name}") for s, text in zip(agg.slots, p.advance().values(), strict=True)}
    return replace(p, aggregate=replace(agg, admit=admit, advance=advance))


@contextmanager
def views(spark: SparkSession, p: PathPlan) -> Iterator[str]:
    """Views <name>_a, _e, _t of the plan's sides while a statement runs, with the row limit of recursion lifted; then all is as before."""
    name, limit = f"ps_{uuid.uuid4().hex[:12]}", spark.conf.get(_LIMIT, None)
    edges, ends = p.halves() or (p.edges(), None)
    if p.nfa is None:
        edges = edges.withColumn("to_state", F.lit(0))
    edges = edges.repartition("e_src").persist()  # every iteration reads them
    if ends is not None:
        ends = ends.repartition("i_day", "i_part").persist()
        ends.createOrReplaceTempView(f"{name}_e_ends")
    spark.conf.set(_LIMIT, "-1")
    p.anchors().createOrReplaceTempView(f"{name}_a")
    edges.createOrReplaceTempView(f"{name}_e")
    if p.nfa is not None:
        p.nfa.to_df(spark).select("from_state", "to_state", F.col("label").alias("t_label")).createOrReplaceTempView(f"{name}_t")
    try:
        yield name
    finally:
        for side in ("a", "e", "e_ends", "t"):
            spark.catalog.dropTempView(f"{name}_{side}")
        for side in (edges, ends):
            if side is not None:
                side.unpersist()
        if limit is None:
            spark.conf.unset(_LIMIT)
        else:
            spark.conf.set(_LIMIT, limit)


_LIMIT = "spark.sql.cteRecursionRowLimit"


def answers_of(p: PathPlan, sql_functions: bool = False, then: Callable[[DataFrame], DataFrame] = lambda out: out, times: str | None = None) -> DataFrame:
    """Rows (start, v, q, len, slots) of the statement (with times, for all but the last hop's, whose ends stay open), or what `then` makes of them, written to the shared folder."""
    spark = p.query.graph.edges.sparkSession
    with views(spark, p) as name:
        made: list[str] = []
        if sql_functions:
            p = _as_functions(p, name, made)
        out = then(spark.sql(to_sql(p, f"{name}_a", f"{name}_e", f"{name}_t" if p.nfa is not None else None, times)))
        path = shared_folder(spark, "recursion")
        out.write.parquet(path)
        for f in made:
            spark.sql(f"DROP TEMPORARY FUNCTION IF EXISTS {f}")
    return spark.read.schema(out.schema).parquet(path)


def answer_counts(p: PathPlan, sql_functions: bool = False, distinct: list[str] | None = None, times: str | None = None) -> DataFrame:
    """(len, n) of the statement's answers, counted as it runs. distinct: columns that tell answers apart. times: what a row of the last hop stands for, where its edges may stay open."""
    times = times if p.query.max_len > 1 else None
    n = F.count(F.lit(1)) if times is None else F.sum("times")
    return answers_of(p, sql_functions, lambda out: (out.dropDuplicates(distinct) if distinct else out).groupBy(F.col("len").cast("long").alias("len")).agg(n.alias("n")).where("n > 0"), times)


def run(query: GuardedPathQuery, sql_functions: bool = False) -> DataFrame:
    """Answers (start, v, q, len, slots). sql_functions: checks and updates as SQL-defined functions."""
    p, distinct = _planned(query)
    out = answers_of(p, sql_functions)
    return out.dropDuplicates(distinct) if distinct else out


def _planned(query: GuardedPathQuery) -> tuple[PathPlan, list[str]]:
    """(plan, columns that tell answers apart, where rows repeat them)."""
    if query.targets is not None or query.via:
        raise ValueError("endpoint sets are for the level executor")
    p = plan(query)
    return p, ["start", "len", "s_edge_ids"] if p.nfa is not None and query.dedupe and p.needs_ids else []


def levels(query: GuardedPathQuery, sql_functions: bool = False) -> DataFrame:
    p, distinct = _planned(query)
    return answer_counts(p, sql_functions, distinct, times_of(p.step_checks, "s_edge_ids") if ends_alike(p) else None)


def statement(query: GuardedPathQuery) -> str:
    p = plan(query)
    return to_sql(p, "anchors", "edges", "transitions" if p.nfa is not None else None)
