"""Slower variants: state as JSON text, functions as Python UDFs, and both.

mode        state            functions
json_udf    one JSON text    five Python functions
flat_udf    typed columns    the same five, over structs
json_inline one JSON text    native expressions
flat_inline typed columns    native expressions (the level executor itself)

kind: plain Python functions, the same with Arrow transfer, or pandas functions.
A clock counts the seconds and calls of each function, and those of the text between.
"""

from __future__ import annotations

import inspect
import json
import time
from collections.abc import Callable

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from pathsieve.operators import levels as native
from pathsieve.operators.recursive import recursion, views
from pathsieve.plans.aggregate import PruningAggregate
from pathsieve.plans.spec import GuardedPathQuery, PathPlan, plan

MODES, KINDS = ("json_udf", "flat_udf", "json_inline", "flat_inline"), ("python", "arrow", "pandas")


def _functions(aggregate: PruningAggregate, max_len: int) -> dict[str, Callable]:
    """The five functions over dictionaries."""
    steps, tests, finals = aggregate.step, [c.test for c in aggregate.admit], aggregate.accepts
    if None in tests:
        raise ValueError("a check has no Python function")
    seeds = {s.name: list(s.start) if isinstance(s.start, tuple) else s.start for s in aggregate.slots}

    def advance(state: dict, edge: dict) -> dict:
        out = {}
        for f in steps:
            out |= f(state, edge)
        return out

    return {
        "seed": lambda: dict(seeds),
        "advance": advance,
        "admit": lambda state, edge: all(bool(t(state, edge | {"max_len": max_len})) for t in tests),
        "emit": lambda state: state,
        "accept": lambda state: all(bool(f(state)) for f in finals),
    }


def _udf(f: Callable, kind: str, returns: str | T.DataType) -> Callable[..., Column]:
    if kind == "python":
        return F.udf(f, returns, useArrow=False)
    if kind == "arrow":
        return F.udf(f, returns, useArrow=True)
    if isinstance(returns, T.StructType):
        raise ValueError("pandas functions take the state as text")

    def batch(*columns: pd.Series) -> pd.Series:
        return pd.Series([f(*r) for r in zip(*columns, strict=True)])

    # fixed arities, as pandas functions need a plain signature
    two = lambda a, b: batch(a, b)
    one = lambda a: batch(a)
    return F.pandas_udf(one if len(inspect.signature(f).parameters) == 1 else two, returns, F.PandasUDFType.SCALAR)


class Clock:
    """Seconds and calls by name, added up over all workers; plain Python functions only."""

    def __init__(self, spark: SparkSession, names: tuple[str, ...]) -> None:
        self.seconds = {n: spark.sparkContext.accumulator(0.0) for n in names}
        self.calls = {n: spark.sparkContext.accumulator(0) for n in names}

    def over(self, name: str, f: Callable) -> Callable:
        seconds, calls = self.seconds[name], self.calls[name]

        def timed(*args: object) -> object:
            began = time.perf_counter()
            out = f(*args)
            seconds.add(time.perf_counter() - began)
            calls.add(1)
            return out

        return timed


#: The edges of a state that is JSON text.
_IDS = "from_json(d, 'edge_ids ARRAY<BIGINT>').edge_ids"
FUNCTIONS = ("seed", "advance", "admit", "emit", "accept")


def text_functions(parts: dict[str, Callable], kind: str, clock: Clock | None = None) -> dict[str, Callable]:
    """The five functions as they stand in a statement: state and edge are JSON texts. seed takes the start, which it doesn't use."""
    over = clock.over if clock else lambda _, f: f
    parts = {k: over(k, f) for k, f in parts.items()}
    parse, write = over("json", json.loads), over("json", json.dumps)
    texts = {
        "seed": (lambda start: write(parts["seed"]()), "string"),
        "advance": (lambda d, e: write(parts["advance"](parse(d), parse(e))), "string"),
        "admit": (lambda d, e: parts["admit"](parse(d), parse(e)), "boolean"),
        "emit": (lambda d: write(parts["emit"](parse(d))), "string"),
        "accept": (lambda d: parts["accept"](parse(d)), "boolean"),
    }
    return {k: _udf(f, kind, returns) for k, (f, returns) in texts.items()}


def struct_functions(parts: dict[str, Callable], kind: str, state: T.StructType) -> dict[str, Callable]:
    """The five functions over structs: no text between the hops."""
    names = state.fieldNames()
    cast = {f.name: float if isinstance(f.dataType, T.DoubleType) else lambda x: x for f in state.fields}  # a whole number isn't taken for a double
    whole = lambda row: row if isinstance(row, dict) else row.asDict(recursive=True)
    held = lambda values: tuple(None if values.get(n) is None else cast[n](values[n]) for n in names)
    typed = {
        "seed": (lambda start: held(parts["seed"]()), state),
        "advance": (lambda d, e: held(parts["advance"](whole(d), whole(e))), state),
        "admit": (lambda d, e: parts["admit"](whole(d), whole(e)), T.BooleanType()),
        "emit": (lambda d: held(parts["emit"](whole(d))), state),
        "accept": (lambda d: parts["accept"](whole(d)), T.BooleanType()),
    }
    return {k: _udf(f, kind, returns) for k, (f, returns) in typed.items()}


def _edge_struct(p: PathPlan) -> Column:
    """The hop: edge, vertex, tags."""
    parts = [F.col(f"e_{c}").alias(c) for c in p.edge_columns] + [F.col(f"w_{c}").alias(f"vertex_{c}") for c in p.vertex_columns]
    tags = p.nfa.tags if p.nfa else {}
    name = lambda state: F.element_at(F.create_map(*[F.lit(x) for k, v in tags.items() for x in (k, v or "")]), F.col(state)) if tags else F.lit(None).cast("string")
    return F.struct(*parts, name("q").alias("from_tag"), name("to_state").alias("to_tag"))


def _as_text(x: Column) -> Column:
    return F.to_json(x, {"ignoreNullFields": "false"})


def run_levels(query: GuardedPathQuery, mode: str = "json_udf", kind: str = "python", clock: Clock | None = None) -> DataFrame:
    """(len, n) by the chosen variant: seed at the start, admit and advance at every hop, accept and emit for the answers."""
    if mode == "flat_inline":
        return native.levels(query)
    spark = query.graph.edges.sparkSession
    p = plan(query)
    if p.nfa is not None and query.dedupe and p.needs_ids:
        raise ValueError("an ambiguous expression needs the level executor")
    names = [s.name for s in p.aggregate.slots]
    kinds = T._parse_datatype_string("struct<" + ", ".join([*(f"{s.name}: {s.dtype}" for s in p.aggregate.slots), "none: int"]) + ">")
    inline, text = mode == "json_inline", mode != "flat_udf"
    f = None if inline else text_functions(_functions(p.aggregate, query.max_len), kind, clock) if text else struct_functions(_functions(p.aggregate, query.max_len), kind, kinds)
    slots = lambda df: df.withColumn("x", F.from_json("d", kinds)).select("*", *[F.col(f"x.{n}").alias(f"s_{n}") for n in names])
    first = _as_text(F.struct(*[F.col(f"s_{n}").alias(n) for n in names], F.lit(None).cast("int").alias("none"))) if inline else f["seed"]("start")
    now, edges = p.anchors().select("start", "v", "q", "len", first.alias("d")), native.held_edges(p)
    rows, held = [], []
    for hop in range(1, query.max_len + 1):
        last = hop == query.max_len
        alone = last and native.ends_alike(p)  # the last edges' ends stay open
        wide = native.expand(slots(now) if inline else now, native.opened(edges) if alone else edges)
        if p.nfa is not None:
            t = p.transitions()
            wide = wide.join(t, (F.col("q") == F.col("from_state")) & (F.col("e_label") == t["label"])).drop("from_state", "label")
        else:
            wide = wide.withColumn("to_state", F.lit(0))
        if inline:
            for check in p.step_checks:
                wide = wide.where(check)
            new = [F.expr(f"CAST({x} AS {s.dtype})").alias(s.name) for s, x in zip(p.aggregate.slots, p.advance().values(), strict=True)]
            state = _as_text(F.struct(*new, F.lit(None).cast("int").alias("none")))
        else:
            now_state = F.concat(F.regexp_replace("d", r"\}$", ""), F.when(F.col("d") == "{}", "").otherwise(", "), F.lit('"len": '), F.col("len").cast("string"), F.lit("}")) if text else F.struct("d.*", F.col("len").alias("len"))
            wide = wide.withColumn("d_now", now_state).withColumn("e_now", _as_text(_edge_struct(p)) if text else _edge_struct(p)).where(f["admit"]("d_now", "e_now"))
            advance = f["advance"].asNondeterministic() if last else f["advance"]  # so that accept isn't merged into one pass with admit
            state = advance("d_now", "e_now")
        times = F.expr(native.times_of(p.step_checks, "s_edge_ids" if inline else _IDS if text else "d.edge_ids")) if alone else F.lit(1)
        now = wide.select("start", F.col("e_dst").alias("v"), F.col("to_state").alias("q"), (F.col("len") + 1).alias("len"), state.alias("d"), times.alias("times"))
        if not last:  # the last level is counted in one pass and not kept
            now = now.persist()
            held.append(now)
            if not now.count():
                break
            if len(held) > 1:
                held.pop(0).unpersist()
        found = now.where(F.col("len") >= query.min_len)
        if p.accepting is not None:
            found = found.where(F.col("q").isin(p.accepting))
        if inline:
            found = slots(found)
            for check in p.aggregate.accept:
                found = found.where(check)
            n = found.agg(F.sum("times")).first()[0]
        else:
            n = found.where(f["accept"]("d")).select(f["emit"]("d").alias("out"), "times").agg(F.sum(F.when(F.col("out").isNotNull(), F.col("times")))).first()[0]
        if n:
            rows.append((hop, n))
    for level in held:
        level.unpersist()
    edges.unpersist()
    return spark.createDataFrame(rows, "len long, n long")  # max_len rows at most


def run_recursive(query: GuardedPathQuery, kind: str = "python") -> DataFrame:
    """(len, n): the direct form, one recursive statement with the state as JSON text and all five functions in Python."""
    spark = query.graph.edges.sparkSession
    p = plan(query)
    if p.nfa is not None and query.dedupe and p.needs_ids:
        raise ValueError("an ambiguous expression needs the level executor")
    with views(spark, p) as name:
        for k, f in text_functions(_functions(p.aggregate, query.max_len), kind).items():
            spark.udf.register(f"{name}_{k}", f)
            if k == "advance":
                spark.udf.register(f"{name}_advance_last", f.asNondeterministic())  # so that accept isn't merged into one pass with admit
        join, to_state, tags = "", "0", "CAST(NULL AS STRING) AS from_tag, CAST(NULL AS STRING) AS to_tag"
        if p.nfa is not None:
            join, to_state = f" JOIN {name}_t ON q = from_state AND e_label = t_label", "to_state"
            case = lambda c: "CASE " + c + "".join(f" WHEN {k} THEN '{v}'" for k, v in sorted(p.nfa.tags.items()) if v) + " END" if any(p.nfa.tags.values()) else "CAST(NULL AS STRING)"
            tags = f"{case('q')} AS from_tag, {case('to_state')} AS to_tag"
        fields = ", ".join([*[f"e_{c} AS {c}" for c in p.edge_columns], *[f"w_{c} AS vertex_{c}" for c in p.vertex_columns], tags])
        edge = f"to_json(struct({fields}), map('ignoreNullFields', 'false'))"
        state = "concat(rtrim('}', d), CASE WHEN d = '{}' THEN '' ELSE ', ' END, '\"len\": ', CAST(len AS STRING), '}')"
        final = " AND ".join([f"len >= {query.min_len}", *([f"q IN ({', '.join(map(str, p.accepting))})"] if p.accepting else []), f"{name}_accept(d)"])
        anchors = f"SELECT start, v, q, len, {name}_seed(start) AS d FROM {name}_a"
        grown = f"SELECT start, e_dst AS v, {to_state} AS q, len + 1 AS len, {name}_advance({state}, {edge}) AS d"
        times = native.times_of(p.step_checks, _IDS) if query.max_len > 1 and native.ends_alike(p) else None
        out = spark.sql(recursion(p, f"{name}_e", anchors, grown, join, [f"{name}_admit({state}, {edge})"], f"SELECT len, {name}_emit(d) AS d", final, times, grown.replace("_advance(", "_advance_last(")))
        n = F.count("d") if times is None else F.coalesce(F.sum(F.when(F.col("d").isNotNull(), F.col("times"))), F.lit(0))
        rows = out.groupBy(F.col("len").cast("long").alias("len")).agg(n.alias("n")).where("n > 0").collect()  # max_len rows at most
        for k in (*FUNCTIONS, "advance_last"):
            spark.sql(f"DROP TEMPORARY FUNCTION IF EXISTS {name}_{k}")
    return spark.createDataFrame(rows, "len long, n long")
