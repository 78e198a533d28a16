"""Regular expressions over edge labels, and their automata as small relations.

Syntax: labels (words, or quoted 'any text'), `.` for any label, `[^a b]` for any but
those, `|`, `*`, `+`, `?`, `{m}`, `{m,n}`, parentheses, and a tag before an item
(`dom:Domestic+`), by which constraints name the states that its labels lead to.
"""

from __future__ import annotations

import re
from collections import defaultdict, deque
from collections.abc import Iterable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

_LEX = re.compile(r"\s*(?:'([^']*)'|(\[\^[^\]]*\])|([A-Za-z_0-9\-]+):|([A-Za-z_0-9\-]+)|(\{\d+(?:,\d*)?\})|([().|*+?]))")


@dataclass(frozen=True)
class Ast:
    """kind: symbol (labels, negated), empty, cat, alt, star, plus."""

    kind: str
    parts: tuple[Ast, ...] = ()
    labels: frozenset[str] = frozenset()
    negated: bool = False
    tag: str | None = None


EMPTY = Ast("empty")


def cat(parts: Iterable[Ast]) -> Ast:
    parts = tuple(p for p in parts if p.kind != "empty")
    return parts[0] if len(parts) == 1 else Ast("cat", parts) if parts else EMPTY


def _tagged(node: Ast, tag: str) -> Ast:
    if node.kind == "symbol":
        return Ast("symbol", (), node.labels, node.negated, node.tag or tag)
    return Ast(node.kind, tuple(_tagged(p, tag) for p in node.parts))


def _repeated(node: Ast, low: int, high: int | None) -> Ast:
    if (low, high) == (1, None):
        return Ast("plus", (node,))
    tail = [Ast("star", (node,))] if high is None else []
    for _ in range((high or low) - low):
        tail = [Ast("alt", (EMPTY, cat([node, *tail])))]
    return cat([node] * low + tail)


def parse_regex(text: str) -> Ast:
    tokens, at = [], 0
    while text[at:].strip():
        m = _LEX.match(text, at)
        if not m:
            raise ValueError(f"label expression: can't read {text[at:]!r}")
        tokens.append(m.groups())
        at = m.end()
    at = 0

    def peek() -> str | None:
        return tokens[at][5] if at < len(tokens) else None

    def alternatives() -> Ast:
        nonlocal at
        parts = [sequence()]
        while peek() == "|":
            at += 1
            parts.append(sequence())
        return parts[0] if len(parts) == 1 else Ast("alt", tuple(parts))

    def sequence() -> Ast:
        parts = []
        while at < len(tokens) and peek() not in ("|", ")"):
            parts.append(item())
        return cat(parts)

    def item() -> Ast:
        nonlocal at
        quoted, negated, tag, word, count, sign = tokens[at]
        at += 1
        if tag is not None:
            return _tagged(item(), tag)
        if sign == "(":
            node = alternatives()
            if peek() != ")":
                raise ValueError("label expression: a parenthesis isn't closed")
            at += 1
        elif sign == ".":
            node = Ast("symbol", negated=True)
        elif negated is not None:
            node = Ast("symbol", labels=frozenset(negated[2:-1].replace(",", " ").split()), negated=True)
        elif quoted is not None or word is not None:
            node = Ast("symbol", labels=frozenset([quoted if quoted is not None else word]))
        else:
            raise ValueError(f"label expression: {sign or count!r} has nothing to repeat")
        while at < len(tokens) and (tokens[at][4] or tokens[at][5] in ("*", "+", "?")):
            count, sign = tokens[at][4:6]
            at += 1
            if count:
                low, _, high = count[1:-1].partition(",")
                if high and int(high) < int(low):
                    raise ValueError(f"label expression: {count}")
                node = _repeated(node, int(low), int(high) if high else None if "," in count else int(low))
            else:
                node = _repeated(node, *{"*": (0, None), "+": (1, None), "?": (0, 1)}[sign])
        return node

    node = alternatives()
    if at < len(tokens):
        raise ValueError("label expression: a parenthesis has no beginning")
    return node


@dataclass(frozen=True)
class Nfa:
    """Transitions (from, to, label) without empty moves; state 0 starts."""

    transitions: frozenset[tuple[int, int, str]]
    accepting: frozenset[int]
    tags: dict[int, str | None] = field(default_factory=dict)

    @property
    def states(self) -> set[int]:
        return {0, *self.accepting, *(s for f, t, _ in self.transitions for s in (f, t))}

    @property
    def alphabet(self) -> list[str]:
        return sorted({x for _, _, x in self.transitions})

    def tagged(self, tag: str | None) -> list[int]:
        return sorted(s for s in self.states if self.tags.get(s) == tag and (s or tag is None))

    def accepts(self, word: Iterable[str]) -> bool:
        now = {0}
        for x in word:
            now = {t for f, t, y in self.transitions if f in now and x == y}
        return bool(now & self.accepting)

    def rows(self) -> list[tuple[int, int, str]]:
        return sorted(self.transitions)

    def to_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows(), "from_state int, to_state int, label string")


def _labels(node: Ast, alphabet: Iterable[str]) -> frozenset[str]:
    return frozenset(alphabet) - node.labels if node.negated else node.labels


def thompson(node: Ast, alphabet: Iterable[str] = ()) -> tuple[list[tuple[int, int, str | None]], int, int]:
    """(moves, start, end); a move of label None is empty."""
    moves: list[tuple[int, int, str | None]] = []
    made = 0

    def state() -> int:
        nonlocal made
        made += 1
        return made - 1

    def build(n: Ast) -> tuple[int, int]:
        a, b = state(), state()
        if n.kind == "symbol":
            moves.extend((a, b, x) for x in _labels(n, alphabet))
        elif n.kind == "empty":
            moves.append((a, b, None))
        elif n.kind == "cat":
            last = a
            for p in n.parts:
                c, d = build(p)
                moves.append((last, c, None))
                last = d
            moves.append((last, b, None))
        else:
            for p in n.parts:
                c, d = build(p)
                moves.extend([(a, c, None), (d, b, None)])
                if n.kind in ("star", "plus"):
                    moves.append((d, c, None))
                if n.kind == "star":
                    moves.append((a, b, None))
        return a, b

    start, end = build(node)
    return moves, start, end


def drop_epsilon(moves: list[tuple[int, int, str | None]], start: int, end: int) -> Nfa:
    empty, real = defaultdict(set), defaultdict(set)
    for f, t, x in moves:
        (empty if x is None else real)[f].add(t if x is None else (t, x))

    def closure(s: int) -> set[int]:
        seen, todo = {s}, [s]
        while todo:
            for t in empty[todo.pop()] - seen:
                seen.add(t)
                todo.append(t)
        return seen

    names, queue, transitions, accepting = {start: 0}, deque([start]), set(), set()
    while queue:
        s = queue.popleft()
        reach = closure(s)
        if end in reach:
            accepting.add(names[s])
        for t, x in sorted({m for r in reach for m in real[r]}):
            if t not in names:
                names[t] = len(names)
                queue.append(t)
            transitions.add((names[s], names[t], x))
    return trim(Nfa(frozenset(transitions), frozenset(accepting)))


def glushkov(node: Ast, alphabet: Iterable[str] = ()) -> Nfa:
    """A state for each place of a label in the expression, so that tags survive; no empty moves arise."""
    places: list[Ast] = []
    follow: dict[int, set[int]] = defaultdict(set)

    def walk(n: Ast) -> tuple[bool, set[int], set[int]]:
        if n.kind == "empty":
            return True, set(), set()
        if n.kind == "symbol":
            places.append(n)
            return False, {len(places)}, {len(places)}
        found = [walk(p) for p in n.parts]
        if n.kind == "alt":
            return any(f[0] for f in found), set().union(*(f[1] for f in found)), set().union(*(f[2] for f in found))
        if n.kind in ("star", "plus"):
            some, first, last = found[0]
            for p in last:
                follow[p] |= first
            return some or n.kind == "star", first, last
        nullable, first, last = True, set(), set()
        for some, f, l in found:
            for p in last:
                follow[p] |= f
            first = first | f if nullable else first
            last = last | l if some else l
            nullable &= some
        return nullable, first, last

    nullable, first, last = walk(node)
    follow[0] = first
    transitions = {(f, t, x) for f, ts in follow.items() for t in ts for x in _labels(places[t - 1], alphabet)}
    nfa = Nfa(frozenset(transitions), frozenset(last | ({0} if nullable else set())), {k + 1: p.tag for k, p in enumerate(places)})
    return canonical(trim(nfa))


def trim(nfa: Nfa) -> Nfa:
    """Without states that can't be reached or can't accept."""
    ahead, back = defaultdict(set), defaultdict(set)
    for f, t, _ in nfa.transitions:
        ahead[f].add(t)
        back[t].add(f)

    def reach(some: Iterable[int], moves: dict[int, set[int]]) -> set[int]:
        seen = set(some)
        todo = list(seen)
        while todo:
            for t in moves[todo.pop()] - seen:
                seen.add(t)
                todo.append(t)
        return seen

    useful = reach([0], ahead) & reach(nfa.accepting, back)
    return Nfa(frozenset(m for m in nfa.transitions if m[0] in useful and m[1] in useful), nfa.accepting & useful, {s: t for s, t in nfa.tags.items() if s in useful})


def canonical(nfa: Nfa) -> Nfa:
    """States numbered breadth-first from 0, by label, then by former number."""
    ahead = defaultdict(list)
    for f, t, x in nfa.transitions:
        ahead[f].append((x, t))
    names, queue = {0: 0}, deque([0])
    while queue:
        for _, t in sorted(ahead[queue.popleft()]):
            if t not in names:
                names[t] = len(names)
                queue.append(t)
    return Nfa(frozenset((names[f], names[t], x) for f, t, x in nfa.transitions), frozenset(names[s] for s in nfa.accepting if s in names), {names[s]: t for s, t in nfa.tags.items() if s in names})


def determinize(nfa: Nfa, most_states: int = 4096) -> Nfa:
    """Subset construction; refused where a subset mixes tags, since checks could not tell them apart."""
    names: dict[frozenset[int], int] = {frozenset([0]): 0}
    queue, transitions, tags = deque([frozenset([0])]), set(), {}
    while queue:
        now = queue.popleft()
        steps = defaultdict(set)
        for f, t, x in nfa.transitions:
            if f in now:
                steps[x].add(t)
        for x in sorted(steps):
            to = frozenset(steps[x])
            if to not in names:
                kinds = {nfa.tags.get(s) for s in to}
                if len(kinds) > 1:
                    raise ValueError("a subset of states mixes tags")
                if len(names) >= most_states:
                    raise ValueError(f"more than {most_states} states")
                names[to] = len(names)
                tags[names[to]] = kinds.pop()
                queue.append(to)
            transitions.add((names[now], names[to], x))
    return Nfa(frozenset(transitions), frozenset(k for s, k in names.items() if s & nfa.accepting), tags)


def minimize(nfa: Nfa) -> Nfa:
    """Partition refinement of a deterministic automaton; states of different tags stay apart."""
    states = sorted(nfa.states)
    step = {(f, x): t for f, t, x in nfa.transitions}
    part = {s: (s in nfa.accepting, nfa.tags.get(s) or "") for s in states}
    while True:
        signature = {s: (part[s], tuple((x, part.get(step.get((s, x), -1))) for x in nfa.alphabet)) for s in states}
        order = {sig: k for k, sig in enumerate(sorted(set(signature.values()), key=repr))}
        refined = {s: order[signature[s]] for s in states}
        if len(set(refined.values())) == len(set(part.values())):
            break
        part = refined
    start = refined[0]
    name = {c: 0 if c == start else c + 1 for c in set(refined.values())}
    merged = Nfa(frozenset((name[refined[f]], name[refined[t]], x) for f, t, x in nfa.transitions), frozenset(name[refined[s]] for s in nfa.accepting), {name[refined[s]]: nfa.tags.get(s) for s in states if refined[s] != start})
    return canonical(trim(merged))


def automaton(text: str, alphabet: Iterable[str] = (), every_run: bool = False) -> Nfa:
    """The automaton of an expression: deterministic and least where its tags allow, so that a path has one run; every_run: with all runs of its places."""
    places = glushkov(parse_regex(text), alphabet)
    if every_run:
        return places
    try:
        return minimize(determinize(places))
    except ValueError:  # tags would be mixed, or there would be too many states
        return places


def is_ambiguous(nfa: Nfa) -> bool:
    """Whether some accepted word has two runs: two different states reached by one word both go on to accept by one word."""
    step = defaultdict(set)
    for f, t, x in nfa.transitions:
        step[f].add((x, t))
    seen, todo = {(0, 0)}, [(0, 0)]
    back = defaultdict(set)
    while todo:
        p, q = todo.pop()
        for x, a in step[p]:
            for y, b in step[q]:
                if x == y:
                    back[a, b].add((p, q))
                    if (a, b) not in seen:
                        seen.add((a, b))
                        todo.append((a, b))
    ends = [(p, q) for p, q in seen if p in nfa.accepting and q in nfa.accepting]
    useful, todo = set(ends), list(ends)
    while todo:
        for pair in back[todo.pop()] - useful:
            useful.add(pair)
            todo.append(pair)
    return any(p != q for p, q in useful)


def min_hops_to_accept(nfa: Nfa) -> dict[int, int]:
    """Least number of further edges after which each state accepts."""
    hops = dict.fromkeys(nfa.accepting, 0)
    queue = deque(nfa.accepting)
    while queue:
        s = queue.popleft()
        for f, t, _ in nfa.transitions:
            if t == s and f not in hops:
                hops[f] = hops[s] + 1
                queue.append(f)
    return hops


def segments(node: Ast) -> list[Ast]:
    """The parts of a concatenation, for engines that match them one by one."""
    return list(node.parts) if node.kind == "cat" else [node]
