"""Pruning aggregates: typed running state along a path, with a check at each hop.

Expressions are SQL text over these names: `s_<slot>` (state before the hop),
`e_<property>` (the new edge: e_id, e_src, e_dst, e_label and whatever the graph has),
`w_<property>` (the vertex it leads to, where a query attaches vertices), `len` (edges
so far), `q` and `to_state` (automaton). One text serves the level executor, the
recursive-SQL executor and the printed plan. Constraints also carry Python functions
over the same names, for the UDF variants.
"""

from __future__ import annotations

import re
from collections.abc import Callable
from dataclasses import dataclass, field, replace


@dataclass(frozen=True)
class Slot:
    """A key of the state. seed: SQL text of its value before the first edge; start: the same for Python."""

    name: str
    dtype: str
    seed: str = "NULL"
    start: object = None


@dataclass(frozen=True)
class Check:
    """A test of a hop. cases: (from tag, to tag) -> SQL text, where the test depends on the transition; tag None is the start, "*" any."""

    text: str
    cases: tuple[tuple[tuple[str | None, str | None], str], ...] = ()
    edge_only: bool = False
    test: Callable[[dict, dict], bool] | None = None


@dataclass(frozen=True)
class PruningAggregate:
    slots: tuple[Slot, ...] = ()
    advance: dict[str, str] = field(default_factory=dict)
    admit: tuple[Check, ...] = ()
    accept: tuple[str, ...] = ()
    emit: dict[str, str] = field(default_factory=dict)
    #: DuckDB predicates over whole paths: lists `p_<property>`, `ids`, `qs` (states after each edge), `len`.
    oracle: tuple[str, ...] = ()
    step: tuple[Callable[[dict, dict], dict], ...] = ()
    accepts: tuple[Callable[[dict], bool], ...] = ()
    uses: frozenset[str] = frozenset()
    #: What rewrites need to know: names such as "trail", "strict:t".
    traits: frozenset[str] = frozenset()
    #: SQL text of bounds that hold in every admitted hop, by (slot function, slot, comparison, edge property, offset).
    envelope: tuple[tuple[str, str, str, str, float], ...] = ()

    @property
    def is_factorized(self) -> bool:
        """No check depends on the automaton's states."""
        return not any(c.cases for c in self.admit) and not any(re.search(r"\b(q|to_state)\b", x) for x in [*self.advance.values(), *(c.text for c in self.admit)])

    def renamed(self, taken: set[str], nth: int) -> PruningAggregate:
        clash = {s.name: f"{s.name}_{nth}" for s in self.slots if s.name in taken}
        if not clash:
            return self
        swap = lambda text: re.sub(r"\bs_(\w+)\b", lambda m: f"s_{clash.get(m[1], m[1])}", text)

        def wrap(f: Callable) -> Callable:
            back = {v: k for k, v in clash.items()}

            def inner(state: dict, *rest: dict) -> object:
                out = f({back.get(k, k): v for k, v in state.items() if k not in clash}, *rest)
                return {clash.get(k, k): v for k, v in out.items()} if isinstance(out, dict) else out

            return inner

        return replace(
            self,
            slots=tuple(replace(s, name=clash.get(s.name, s.name)) for s in self.slots),
            advance={clash.get(k, k): swap(v) for k, v in self.advance.items()},
            admit=tuple(replace(c, text=swap(c.text), cases=tuple((k, swap(v)) for k, v in c.cases), test=c.test and wrap(c.test)) for c in self.admit),
            accept=tuple(map(swap, self.accept)),
            emit={k: swap(v) for k, v in self.emit.items()},
            step=tuple(map(wrap, self.step)),
            accepts=tuple(map(wrap, self.accepts)),
            envelope=tuple((f, clash.get(s, s), *rest) for f, s, *rest in self.envelope),
        )

    def __and__(self, other: PruningAggregate) -> PruningAggregate:
        """Both: states side by side, checks conjoined. Equal slots are kept once."""
        same = {s for s in other.slots if s in self.slots and self.advance.get(s.name) == other.advance.get(s.name)}
        taken = {s.name for s in self.slots} - {s.name for s in same}
        nth = 2
        while any(f"{n}_{nth}" in {s.name for s in self.slots} for n in taken):
            nth += 1
        other = other.renamed(taken, nth)
        return PruningAggregate(
            self.slots + tuple(s for s in other.slots if s not in same),
            self.advance | other.advance,
            self.admit + tuple(c for c in other.admit if c not in self.admit),
            self.accept + other.accept,
            self.emit | other.emit,
            self.oracle + other.oracle,
            self.step + other.step,
            self.accepts + other.accepts,
            self.uses | other.uses,
            self.traits | other.traits,
            self.envelope + other.envelope,
        )


def compose(*parts: PruningAggregate) -> PruningAggregate:
    out = PruningAggregate()
    for p in parts:
        out = out & p
    return out
