"""Small graphs that show a violation: chase, closure and test of one witness, in plain Python.

A witness has a handful of triples, so one is cheap; there can be many, so they are rows of a DataFrame and each task
runs through its share.  Fresh IRIs start with ``w:`` and fresh literals with ``"w:``.  They count as nulls: one may turn
out to be a constant of its kind.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

from tripleschema.model import Atom, Existential, Pattern, Rule, is_literal, is_var

Graph = frozenset[Atom]
#: Graphs in the chases of one witness; beyond that it is left undecided.
BRANCHES = 4_000


class TooManyChases(RuntimeError):
    """A witness has more chases than are looked at."""


def is_null(t: str) -> bool:
    return t.startswith(("w:", '"w:'))


def match(atom: Atom, graph: Graph, binding: dict[str, str]) -> Iterator[dict[str, str]]:
    want = atom.replaced(binding)
    for triple in graph:
        found = dict(binding)
        for w, t in zip(want, triple, strict=True):
            if is_var(w):
                if found.setdefault(w, t) != t:
                    break
            elif w != t:
                break
        else:
            yield found


def match_all(atoms: Sequence[Atom], graph: Graph, binding: dict[str, str] | None = None) -> Iterator[dict[str, str]]:
    if not atoms:
        yield dict(binding or {})
        return
    for found in match(atoms[0], graph, binding or {}):
        yield from match_all(atoms[1:], graph, found)


def close(graph: Graph, rules: Sequence[Rule]) -> Graph:
    while True:
        new = set()
        for r in rules:
            for m in match_all(r.body, graph):
                heads = [h.replaced(m) for h in r.head]
                if not any(is_literal(h.s) or is_literal(h.p) for h in heads) and not any(is_literal(m[v]) for v in r.no_literal):
                    new |= {h for h in heads if h not in graph}
        if not new:
            return graph
        graph = graph | new


def broken(e: Existential, graph: Graph) -> list[dict[str, str]]:
    """Frontier bindings of antecedent matches without a consequent match."""
    out = []
    for m in match(e.a, graph, {}):
        front = {v: m[v] for v in e.frontier()}
        if front not in out and next(match(e.c, graph, front), None) is None:
            out.append(front)
    return out


def _fresh(graph: Graph) -> int:
    return 1 + max((int(t.rstrip('"').rsplit("#", 1)[1]) for triple in graph for t in triple if is_null(t) and "#" in t), default=-1)


def _merge(triple: Atom, p: Pattern) -> dict[str, str] | None:
    """How nulls of a triple must turn out for a pattern to admit it; None if they cannot."""
    out: dict[str, str] = {}
    for t, (kind, v) in zip(triple, p.places, strict=True):
        t = out.get(t, t)
        if kind in "CL":
            if is_null(t) and is_literal(t) == (kind == "L"):
                out[t] = v
            elif t != v:
                return None
        elif kind == "I" and is_literal(t):
            return None
    return out


def literal_matters(rules: Sequence[Rule]) -> set[str | None]:
    """Predicates whose objects some rule needs as IRIs (None for all): it fires for an IRI there and not for a literal."""
    return {None if is_var(a.p) else a.p for r in rules for a in r.body if a.o in r.firm()}


def _valid(graph: Graph, patterns: Sequence[Pattern]) -> bool:
    return all(not is_literal(t.s) and not is_literal(t.p) and any(p.admits(t) for p in patterns) for t in graph)


def chases(graph: Graph, rules: Sequence[Existential], patterns: Sequence[Pattern] | None, sensitive: set[str | None] = frozenset()) -> Iterator[Graph]:
    """Instances that the existential rules make of a graph.

    Without patterns there is one: each missing consequent is added with fresh IRIs.  With patterns an added triple must
    be admitted, and a null that has to be a constant becomes it everywhere.  Only the least ways of that are followed:
    what a more special one breaks, the more general one breaks too.  Where a predicate is ``sensitive``, an invented object
    is a fresh literal if that leads to an instance, as fewer facts follow from it, and else a fresh IRI."""
    seen = {graph}

    def ways_of(now: Graph, form: Atom) -> list[Graph]:
        if patterns is None:
            return [now | {form}]
        ways: list[tuple[set, Graph]] = []
        for p in patterns:
            m = _merge(form, p)
            if m is not None:
                merged = frozenset(t.replaced(m) for t in now | {form})
                if _valid(merged, patterns):
                    ways.append((set(m.items()), merged))
        return [g for m, g in ways if not any(other < m for other, _ in ways)]

    def run(now: Graph) -> Iterator[Graph]:
        gap = next(((e, b) for e in rules for b in broken(e, now)), None)
        if gap is None:
            yield now
            return
        e, front = gap
        n, fill = _fresh(now), dict(front)
        for v in e.c.variables():
            if v not in fill:
                fill[v] = f"w:#{n}"
                n += 1
        triple = e.c.replaced(fill)
        if is_literal(triple.s) or is_literal(triple.p):
            if patterns is None:
                yield now  # nothing can be added; the graph is no instance, which the caller sees
            return
        forms = [triple]
        if patterns is not None and is_var(e.c.o) and e.c.o not in front and e.c.o not in e.c[:2] and sensitive & {None, triple.p}:
            forms.insert(0, Atom(triple.s, triple.p, f'"{triple.o}"'))
        for form in forms:
            found = False
            for g in ways_of(now, form):
                if g in seen:
                    continue
                if len(seen) > BRANCHES:
                    raise TooManyChases(f"a witness has over {BRANCHES} chases")
                seen.add(g)
                for instance in run(g):
                    found = True
                    yield instance
            if found:
                return

    yield from run(graph)


def violates(graph: Graph, e: Existential, existentials: Sequence[Existential], rules: Sequence[Rule], patterns: Sequence[Pattern] | None) -> tuple[Graph, Graph] | None:
    """A chased instance and its closure that breaks ``e``; None if all of them keep it.  TooManyChases if that is open."""
    for instance in chases(graph, existentials, patterns, literal_matters(rules)):
        closed = close(instance, rules)
        if broken(e, closed):
            return instance, closed
    return None
