"""Terms, atoms, rules, existential rules and schemas.

A term is a string: ``?x`` a variable, ``"x"`` (with the quotes) a literal, anything else an IRI.  A schema pattern has a
kind and a value for each place: ``C`` a constant IRI, ``L`` a constant literal, ``I`` any IRI, ``A`` any term (objects
only).  A pattern's wildcards are independent of each other, so they need no names, and equal patterns are equal rows.
"""

from __future__ import annotations

import re
from collections.abc import Iterable, Iterator, Sequence
from dataclasses import dataclass, field
from typing import NamedTuple

#: The fresh IRI that stands for "any other IRI" in canonical graphs.
LAMBDA = "λ"


def is_var(t: str) -> bool:
    return t.startswith("?")


def is_literal(t: str) -> bool:
    return t.startswith('"')


def is_iri(t: str) -> bool:
    return not is_var(t) and not is_literal(t)


class Atom(NamedTuple):
    """A triple pattern of a rule, or a ground triple."""

    s: str
    p: str
    o: str

    def variables(self) -> list[str]:
        return list(dict.fromkeys(t for t in self if is_var(t)))

    def replaced(self, by: dict[str, str]) -> Atom:
        return Atom(*(by.get(t, t) for t in self))

    def __str__(self) -> str:
        return " ".join(self)


class Pattern(NamedTuple):
    s_k: str
    s_v: str | None
    p_k: str
    p_v: str | None
    o_k: str
    o_v: str | None

    @property
    def places(self) -> tuple[tuple[str, str | None], ...]:
        return ((self.s_k, self.s_v), (self.p_k, self.p_v), (self.o_k, self.o_v))

    def below(self, other: Pattern) -> bool:
        """Whether every triple of this pattern is one of the other."""
        return all(b == "A" or (b == "I" and a in "CI") or (a, x) == (b, y) for (a, x), (b, y) in zip(self.places, other.places, strict=True))

    def admits(self, triple: Sequence[str]) -> bool:
        return all(k == "A" or (k == "I" and not is_literal(t)) or v == t for (k, v), t in zip(self.places, triple, strict=True))

    def sandbox(self) -> Atom:
        return Atom(*(LAMBDA if k in "IA" else v for k, v in self.places))

    def __str__(self) -> str:
        return " ".join({"I": "*", "A": "**"}.get(k) or v for k, v in self.places)


PATTERN_SCHEMA = "s_k string, s_v string, p_k string, p_v string, o_k string, o_v string"
TRIPLE_SCHEMA = "s string, p string, o string, o_lit boolean"


def pattern(text: str) -> Pattern:
    """From text such as ``* :reads **``: ``*`` any IRI, ``**`` any term."""
    out = []
    for i, t in enumerate(tokens(text)):
        if t == "**" and i != 2:
            raise ValueError(f"only objects can be literals: {text}")
        out += [{"*": "I", "**": "A"}.get(t, "L" if is_literal(t) else "C"), None if t in ("*", "**") else t]
        if out[-2] == "L" and i != 2:
            raise ValueError(f"only objects can be literals: {text}")
    if len(out) != 6:
        raise ValueError(f"a pattern has three places: {text}")
    return Pattern(*out)


@dataclass(frozen=True)
class Rule:
    """If the body matches, the head holds; not for mappings with a literal at one of the variables ``no_literal``."""

    id: str
    body: tuple[Atom, ...]
    head: tuple[Atom, ...]
    no_literal: tuple[str, ...] = ()

    def variables(self) -> list[str]:
        return list(dict.fromkeys(v for a in self.body for v in a.variables()))

    def firm(self) -> set[str]:
        """Variables that stand in a subject or predicate place somewhere, which literals cannot."""
        return {t for a in (*self.body, *self.head) for t in a[:2] if is_var(t)} | set(self.no_literal)

    def __str__(self) -> str:
        return f"{' , '.join(map(str, self.body))} => {' , '.join(map(str, self.head))}"


@dataclass(frozen=True)
class Existential:
    """If a triple matches ``a``, some triple matches ``c``."""

    id: str
    a: Atom
    c: Atom

    def frontier(self) -> list[str]:
        return [v for v in self.a.variables() if v in self.c.variables()]

    def __str__(self) -> str:
        return f"{self.a} -> {self.c}"


@dataclass(frozen=True)
class Rules:
    """A rule set that is written with its schema."""

    rules: tuple[Rule, ...] = ()
    existentials: tuple[Existential, ...] = ()
    patterns: tuple[Pattern, ...] = field(default=())


# -- text


_TOKEN = re.compile(r'"(?:[^"\\]|\\.)*"|[^\s,]+')


def tokens(text: str) -> list[str]:
    return _TOKEN.findall(text)


def atoms(text: str) -> tuple[Atom, ...]:
    found = tokens(text)
    if len(found) % 3:
        raise ValueError(f"atoms have three places: {text}")
    return tuple(Atom(*found[i : i + 3]) for i in range(0, len(found), 3))


def rule(rule_id: str, text: str) -> Rule:
    """From ``?x :p ?y, ?y :q ?z => ?x :r ?z``."""
    body, arrow, head = text.partition("=>")
    if not arrow:
        raise ValueError(f"no => in {text}")
    return checked(Rule(rule_id, atoms(body), atoms(head)))


def existential(e_id: str, text: str) -> Existential:
    """From ``?x a :C -> ?x :p ?y``."""
    a, arrow, c = text.partition("->")
    a, c = atoms(a), atoms(c)
    if not arrow or len(a) != 1 or len(c) != 1:
        raise ValueError(f"an existential rule has one atom on either side: {text}")
    return Existential(e_id, a[0], c[0])


# -- well-formedness


def problems(r: Rule) -> list[str]:
    """What is wrong with a rule."""
    out = []
    body = set(r.variables())
    if not r.head:
        out.append("empty head")
    for h in r.head:
        if is_var(h.p):
            out.append(f"head predicate {h.p} is a variable")
        if is_var(h.s) and h.s == h.o:
            out.append(f"head repeats {h.s} as subject and object")
        if missing := [v for v in h.variables() if v not in body]:
            out.append(f"head variables {missing} are not in the body")
    for a in (*r.body, *r.head):
        if is_literal(a.s) or is_literal(a.p):
            out.append(f"literal outside the object place of {a}")
    return out


def checked(r: Rule) -> Rule:
    if found := problems(r):
        raise ValueError(f"rule {r.id}: {'; '.join(found)}")
    return r


def unify(a: Atom, b: Atom) -> dict[str, str] | None:
    """Most general unifier of two atoms with separate variables, as a substitution of both; None if they clash."""
    out: dict[str, str] = {}

    def walk(t: str) -> str:
        while t in out:
            t = out[t]
        return t

    for x, y in zip(a, b, strict=True):
        x, y = walk(x), walk(y)
        if x == y:
            continue
        if is_var(x):
            out[x] = y
        elif is_var(y):
            out[y] = x
        else:
            return None
    return {v: walk(v) for v in out}


def renamed(atoms_: Iterable[Atom], suffix: str) -> tuple[Atom, ...]:
    return tuple(Atom(*(f"{t}{suffix}" if is_var(t) else t for t in a)) for a in atoms_)


def weak_acyclicity(rules: Sequence[Existential]) -> tuple[bool, list[tuple]]:
    """Whether the chase must end, and a cycle through an invented value if not.

    Positions are (predicate, place); a frontier variable gives plain edges and edges to each place where the rule
    invents a value.  A cycle with an edge of the second kind may go on for ever."""
    plain: dict[tuple, set[tuple]] = {}
    invents: set[tuple[tuple, tuple]] = set()
    for e in rules:
        for i, v in enumerate(e.a):
            if not is_var(v):
                continue
            for j, w in enumerate(e.c):
                if not is_var(w):
                    continue
                if v == w:
                    plain.setdefault((e.a.p, i), set()).add((e.c.p, j))
                elif w not in e.a.variables() and v in e.c.variables():
                    plain.setdefault((e.a.p, i), set()).add((e.c.p, j))
                    invents.add(((e.a.p, i), (e.c.p, j)))
    for start, goal in invents:
        stack, seen = [goal], {goal}
        while stack:
            at = stack.pop()
            if at == start:
                return False, [start, goal]
            for nxt in plain.get(at, ()):
                if nxt not in seen:
                    seen.add(nxt)
                    stack.append(nxt)
    return True, []


def recursive_predicates(rules: Sequence[Rule]) -> set[str]:
    """Predicates that depend on themselves through the rules."""
    needs: dict[str, set[str]] = {}
    for r in rules:
        for h in r.head:
            needs.setdefault(h.p, set()).update(a.p for a in r.body)
    heads = set(needs)

    def reach(p: str) -> Iterator[str]:
        stack, seen = [p], set()
        while stack:
            for q in needs.get(stack.pop(), ()):
                for r in heads if is_var(q) else {q} & heads:
                    if r not in seen:
                        seen.add(r)
                        stack.append(r)
        yield from seen

    return {p for p in heads if p in set(reach(p))}
