"""The constraint library. Each function returns a pruning aggregate; combine them with `&`.

Properties are numbers or strings; times are microseconds (BIGINT), and time bounds may
be given as timedelta. A missing property (NULL) fails every check that needs it; only
the first edge has no predecessor to be compared with.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable
from datetime import timedelta

from pathsieve.plans.aggregate import Check, PruningAggregate, Slot

Bound = float | int | timedelta


def _number(bound: Bound) -> float | int:
    return round(bound.total_seconds() * 1_000_000) if isinstance(bound, timedelta) else bound


def _where(prop: str) -> str:
    """Column of a property: of the edge, or of the vertex it leads to (`vertex.x`)."""
    return f"w_{prop[7:]}" if prop.startswith("vertex.") else f"e_{prop}"


def _list(prop: str) -> str:
    return f"p_{prop.replace('.', '_')}"


def _none(text: str) -> str:
    """DuckDB: no place i of the path breaks the text."""
    return f"len(list_filter(range(1, len + 1), lambda i: NOT coalesce({text}, false))) = 0"


def Trail() -> PruningAggregate:
    """No edge twice."""
    return PruningAggregate(
        (Slot("edge_ids", "ARRAY<BIGINT>", "CAST(array() AS ARRAY<BIGINT>)", ()),),
        {"edge_ids": "array_append(s_edge_ids, e_id)"},
        (Check("NOT array_contains(s_edge_ids, e_id)", test=lambda s, e: e["id"] not in s["edge_ids"]),),
        oracle=("len(ids) = len(list_distinct(ids))",),
        step=(lambda s, e: {"edge_ids": [*s["edge_ids"], e["id"]]},),
        traits=frozenset(["trail"]),
    )


def Acyclic() -> PruningAggregate:
    """No vertex twice, the start included."""
    return PruningAggregate(
        (Slot("seen", "ARRAY<BIGINT>", "array(v)", ()),),
        {"seen": "array_append(s_seen, e_dst)"},
        (Check("NOT array_contains(s_seen, e_dst)", test=lambda s, e: e["dst"] not in (s["seen"] or [e["src"]])),),
        oracle=("len(vs) = len(list_distinct(vs))",),
        step=(lambda s, e: {"seen": [*(s["seen"] or [e["src"]]), e["dst"]]},),
    )


def Monotone(prop: str, dtype: str = "BIGINT", strict: bool = True, increasing: bool = True) -> PruningAggregate:
    """Each edge's property above (below) its predecessor's."""
    sign = (">" if increasing else "<") + ("" if strict else "=")
    e, s = _where(prop), f"last_{prop.replace('.', '_')}"
    name = prop.replace(".", "_")
    compare = {">": lambda a, b: a > b, ">=": lambda a, b: a >= b, "<": lambda a, b: a < b, "<=": lambda a, b: a <= b}[sign]
    return PruningAggregate(
        (Slot(s, dtype),),
        {s: e},
        (Check(f"len = 0 OR {e} {sign} s_{s}", test=lambda st, ed: st["len"] == 0 or (ed[name] is not None and st[s] is not None and compare(ed[name], st[s]))),),
        oracle=(_none(f"i = 1 OR {_list(prop)}[i] {sign} {_list(prop)}[i - 1]"),),
        step=(lambda st, ed: {s: ed[name]},),
        uses=frozenset([prop]),
        traits=frozenset([f"strict:{prop}"] if strict else []),
        envelope=(("min" if increasing else "max", s, sign, e, 0),),
    )


def _extremes(prop: str, dtype: str) -> tuple[tuple[Slot, ...], dict[str, str], Callable]:
    e, n = _where(prop), prop.replace(".", "_")
    low, high = f"min_{n}", f"max_{n}"

    def step(s: dict, ed: dict) -> dict:
        known = [x for x in (s[low], ed[n]) if x is not None], [x for x in (s[high], ed[n]) if x is not None]
        return {low: min(known[0], default=None), high: max(known[1], default=None)}

    return (Slot(low, dtype), Slot(high, dtype)), {low: f"least(s_{low}, {e})", high: f"greatest(s_{high}, {e})"}, step


def SpreadAtMost(prop: str, bound: Bound, dtype: str = "BIGINT", within: str | None = None) -> PruningAggregate:
    """Largest minus smallest value of the path at most `bound`; the gap only widens, so a prefix above it is hopeless. within: only over edges that lead to states of this tag."""
    slots, advance, step = _extremes(prop, dtype)
    e, n, u = _where(prop), prop.replace(".", "_"), _number(bound)
    low, high = f"min_{n}", f"max_{n}"
    text = f"{e} IS NOT NULL AND coalesce(greatest(s_{high}, {e}) - least(s_{low}, {e}) <= {u}, false)"

    def test(s: dict, ed: dict) -> bool:
        if within and ed["to_tag"] != within:
            return True
        if ed[n] is None:
            return False
        return max(x for x in (s[high], ed[n]) if x is not None) - min(x for x in (s[low], ed[n]) if x is not None) <= u

    check = Check("true", ((("*", within), text),), test=test) if within else Check(text, test=test)
    values = f"list_filter({_list(prop)}, lambda x, i: list_contains({{{within}}}, qs[i]))" if within else _list(prop)
    if within:
        advance = {k: f"CASE WHEN to_state IN ({{{within}}}) THEN {v} ELSE s_{k} END" for k, v in advance.items()}
        plain = step
        step = lambda s, ed: plain(s, ed) if ed["to_tag"] == within else {low: s[low], high: s[high]}
    return PruningAggregate(
        slots, advance, (check,), step=(step,), uses=frozenset([prop]),
        oracle=(f"len({values}) = 0 OR (len(list_filter({values}, lambda x: x IS NULL)) = 0 AND list_max({values}) - list_min({values}) <= {u})",),
        traits=frozenset() if within else frozenset([f"spread:{prop}:{u}"]),
        envelope=() if within else (("max", low, "<=", e, u), ("min", high, ">=", e, -u)),
    )


def SpreadAtLeast(prop: str, bound: Bound, dtype: str = "BIGINT") -> PruningAggregate:
    """Largest minus smallest value at least `bound`: a longer path may still reach it, so no prefix is dropped."""
    slots, advance, step = _extremes(prop, dtype)
    n, u = prop.replace(".", "_"), _number(bound)
    low, high = f"min_{n}", f"max_{n}"
    return PruningAggregate(slots, advance, (), (f"s_{high} - s_{low} >= {u}",), oracle=(f"coalesce(list_max({_list(prop)}) - list_min({_list(prop)}) >= {u}, false)",), step=(step,), accepts=(lambda s: s[low] is not None and s[high] - s[low] >= u,), uses=frozenset([prop]))


def StepWithin(prop: str, bound: Bound | None = None, by: dict[tuple[str | None, str | None], Bound] | None = None, dtype: str = "BIGINT") -> PruningAggregate:
    """Neighbouring edges differ by at most the bound; by: bounds for transitions between tags (others are free)."""
    e, n = _where(prop), prop.replace(".", "_")
    s = f"last_{n}"
    test_text = lambda u: f"len = 0 OR abs({e} - s_{s}) <= {u}"
    bounds = {k: _number(v) for k, v in (by or {}).items()}

    def test(st: dict, ed: dict) -> bool:
        u = bounds.get((ed["from_tag"], ed["to_tag"])) if by else _number(bound)
        return u is None or st["len"] == 0 or (ed[n] is not None and st[s] is not None and abs(ed[n] - st[s]) <= u)

    p = _list(prop)
    if by:
        check = Check("true", tuple((k, test_text(u)) for k, u in bounds.items()), test=test)
        cases = " ".join(f"WHEN list_contains({{{a}}}, qs[i - 1]) AND list_contains({{{b}}}, qs[i]) THEN abs({p}[i] - {p}[i - 1]) <= {u}" for (a, b), u in bounds.items())
        oracle = _none(f"i = 1 OR (CASE {cases} ELSE true END)")
    else:
        check, oracle = Check(test_text(_number(bound)), test=test), _none(f"i = 1 OR abs({p}[i] - {p}[i - 1]) <= {_number(bound)}")
    envelope = () if by else (("min", s, ">=", e, -_number(bound)), ("max", s, "<=", e, _number(bound)))
    return PruningAggregate((Slot(s, dtype),), {s: e}, (check,), oracle=(oracle,), step=(lambda st, ed: {s: ed[n]},), uses=frozenset([prop]), envelope=envelope)


def SameAsFirst(prop: str, dtype: str = "STRING") -> PruningAggregate:
    """The first edge's value on every edge."""
    e, n = _where(prop), prop.replace(".", "_")
    s = f"first_{n}"
    return PruningAggregate(
        (Slot(s, dtype),), {s: f"CASE WHEN len = 0 THEN {e} ELSE s_{s} END"}, (Check(f"len = 0 OR {e} = s_{s}", test=lambda st, ed: st["len"] == 0 or (ed[n] is not None and ed[n] == st[s])),),
        oracle=(_none(f"i = 1 OR {_list(prop)}[i] = {_list(prop)}[1]"),), step=(lambda st, ed: {s: ed[n] if st["len"] == 0 else st[s]},), uses=frozenset([prop]),
    )


def LastOfSegmentAtLeast(prop: str, leaving: str, entering: str, bound: Bound, dtype: str = "BIGINT") -> PruningAggregate:
    """The last edge of one tag before the first of the next has at least this value."""
    n, u = prop.replace(".", "_"), _number(bound)
    s, p = f"last_{n}", _list(prop)
    test = lambda st, ed: not (ed["from_tag"] == leaving and ed["to_tag"] == entering) or (st[s] is not None and st[s] >= u)
    return PruningAggregate(
        (Slot(s, dtype),), {s: _where(prop)}, (Check("true", (((leaving, entering), f"s_{s} >= {u}"),), test=test),),
        oracle=(_none(f"i = 1 OR NOT (list_contains({{{leaving}}}, qs[i - 1]) AND list_contains({{{entering}}}, qs[i])) OR {p}[i - 1] >= {u}"),), step=(lambda st, ed: {s: ed[n]},), uses=frozenset([prop]),
    )


def SumAtLeast(prop: str, bound: Bound, dtype: str = "DOUBLE", edge_upper_bound: float | None = None) -> PruningAggregate:
    """Total at least `bound`, tested at the end; with an upper bound of one edge also on the way, by what the hops left can add."""
    e, n, u = _where(prop), prop.replace(".", "_"), _number(bound)
    s = f"sum_{n}"
    checks = () if edge_upper_bound is None else (Check(f"s_{s} + {e} + ({{max_len}} - len - 1) * {edge_upper_bound} >= {u}", test=lambda st, ed: ed[n] is not None and st[s] + ed[n] + (ed["max_len"] - st["len"] - 1) * edge_upper_bound >= u),)
    return PruningAggregate((Slot(s, dtype, "0", 0),), {s: f"s_{s} + {e}"}, checks, (f"s_{s} >= {u}",), oracle=(f"len(list_filter({_list(prop)}, lambda x: x IS NULL)) = 0 AND list_reduce(list_concat([0], {_list(prop)}), lambda x, y: x + y) >= {u}",), step=(lambda st, ed: {s: None if st[s] is None or ed[n] is None else st[s] + ed[n]},), accepts=(lambda st: st[s] is not None and st[s] >= u,), uses=frozenset([prop]))


def SumAtMost(prop: str, bound: Bound, dtype: str = "DOUBLE") -> PruningAggregate:
    """Total at most `bound`, for a property that is never negative."""
    e, n, u = _where(prop), prop.replace(".", "_"), _number(bound)
    s = f"sum_{n}"
    return PruningAggregate((Slot(s, dtype, "0", 0),), {s: f"s_{s} + {e}"}, (Check(f"s_{s} + {e} <= {u}", test=lambda st, ed: ed[n] is not None and st[s] + ed[n] <= u),), oracle=(f"len(list_filter({_list(prop)}, lambda x: x IS NULL)) = 0 AND list_reduce(list_concat([0], {_list(prop)}), lambda x, y: x + y) <= {u}",), step=(lambda st, ed: {s: st[s] + ed[n]},), uses=frozenset([prop]))


def AdjacentEqualExists(prop: str, dtype: str = "STRING") -> PruningAggregate:
    """Two neighbouring edges of equal value somewhere: tracked on the way, tested at the end, nothing can be dropped early."""
    e, n = _where(prop), prop.replace(".", "_")
    s, p = f"last_{n}", _list(prop)
    return PruningAggregate(
        (Slot(s, dtype), Slot("completed", "BOOLEAN", "false", False)),
        {s: e, "completed": f"s_completed OR coalesce(len > 0 AND {e} = s_{s}, false)"},
        (), ("s_completed",), oracle=(f"len(list_filter(range(2, len + 1), lambda i: coalesce({p}[i] = {p}[i - 1], false))) > 0",),
        step=(lambda st, ed: {s: ed[n], "completed": bool(st["completed"] or (st["len"] > 0 and ed[n] is not None and ed[n] == st[s]))},),
        accepts=(lambda st: bool(st["completed"]),), uses=frozenset([prop]),
    )


def EdgePredicate(text: str, oracle: str, uses: Iterable[str], test: Callable[[dict], bool] | None = None) -> PruningAggregate:
    """A condition on each edge by itself, over e_<property>; oracle: the same over p_<property>[i]."""
    return PruningAggregate(admit=(Check(text, edge_only=True, test=test and (lambda s, e: test(e))),), oracle=(_none(oracle),), uses=frozenset(uses))


def AllOf(text: str, oracle: str, uses: Iterable[str]) -> PruningAggregate:
    return EdgePredicate(text, oracle, uses)


def AnyOf(text: str, oracle: str, uses: Iterable[str], name: str = "any") -> PruningAggregate:
    """At least one edge satisfies the text."""
    return PruningAggregate((Slot(name, "BOOLEAN", "false", False),), {name: f"s_{name} OR coalesce({text}, false)"}, (), (f"s_{name}",), oracle=(f"len(list_filter(range(1, len + 1), lambda i: coalesce({oracle}, false))) > 0",), uses=frozenset(uses))


def VertexPredicate(text: str, oracle: str, uses: Iterable[str]) -> PruningAggregate:
    """A condition on the vertex that each edge leads to, over w_<property>."""
    return PruningAggregate(admit=(Check(text),), oracle=(_none(oracle),), uses=frozenset(f"vertex.{u}" for u in uses))


def VertexMonotone(prop: str, dtype: str = "BIGINT", strict: bool = True) -> PruningAggregate:
    return Monotone(f"vertex.{prop}", dtype, strict)


def Collect(props: Iterable[str], dtypes: dict[str, str] | None = None) -> PruningAggregate:
    """Lists of the edges' values: what an engine keeps that tests only finished paths."""
    out = PruningAggregate()
    for p in props:
        kind = (dtypes or {}).get(p, "BIGINT")
        out = out & PruningAggregate((Slot(f"all_{p}", f"ARRAY<{kind}>", f"CAST(array() AS ARRAY<{kind}>)", ()),), {f"all_{p}": f"array_append(s_all_{p}, {_where(p)})"}, step=((lambda st, ed, p=p: {f"all_{p}": [*st[f"all_{p}"], ed[p]]}),), uses=frozenset([p]))
    return out


def CollectThenTest(props: Iterable[str], accept: str, oracle: str, dtypes: dict[str, str] | None = None) -> PruningAggregate:
    """The default construction: collect everything, test at the end."""
    return Collect(props, dtypes) & PruningAggregate(accept=(accept,), oracle=(oracle,))


def Custom(**parts: object) -> PruningAggregate:
    """Any constraint: the fields of PruningAggregate."""
    return PruningAggregate(**parts)
