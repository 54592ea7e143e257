"""Rule application and closure of graphs."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tripleschema.model import Rule, is_var
from tripleschema.operators import bgp
from tripleschema.plans.tables import written

TRIPLE = ["s", "p", "o", "o_lit"]


def apply(rule: Rule, triples: DataFrame) -> DataFrame:
    """The distinct head triples of one application of a rule (not the graph it was applied to)."""
    return bgp.heads(rule.head, bgp.evaluate(rule.body, triples), rule.no_literal).distinct()


@dataclass
class Closed:
    graph: DataFrame
    rounds: int
    added: int


def strata(rules: Sequence[Rule]) -> list[list[Rule]]:
    """Rules in groups that depend on each other, in an order in which no group feeds an earlier one."""
    n = len(rules)
    feeds = [{j for j in range(n) if any(is_var(b.p) or b.p in {h.p for h in rules[i].head} for b in rules[j].body)} for i in range(n)]
    reach = [set(f) for f in feeds]
    for k in range(n):
        for i in range(n):
            if k in reach[i]:
                reach[i] |= reach[k]
    groups, seen = [], set()
    for i in sorted(range(n), key=lambda i: (-len(reach[i]), i)):
        if i not in seen:
            group = [j for j in range(n) if j == i or (j in reach[i] and i in reach[j])]
            seen |= set(group)
            groups.append(group)
    out: list[list[int]] = []
    while groups:
        free = next(g for g in groups if not any(set(g) & reach[j] for h in groups if h is not g for j in h))
        groups.remove(free)
        out.append(free)
    return [[rules[i] for i in sorted(g)] for g in out]


def fed_by(rule: Rule, rules: Sequence[Rule]) -> set[str]:
    """The head predicates that a rule can lead to, its own included."""
    out, todo = set(), {h.p for h in rule.head}
    while todo:
        p = todo.pop()
        out.add(p)
        todo |= {h.p for r in rules if any(is_var(b.p) or b.p == p for b in r.body) for h in r.head} - out
    return out


def stored(triples: DataFrame, name: str) -> DataFrame:
    """Triples written once in a folder for each predicate, so that an atom reads its predicate only."""
    return written(triples.select(*TRIPLE), name, by="p").select(*TRIPLE)


def close(triples: DataFrame, rules: Sequence[Rule], mode: str = "seminaive", max_rounds: int | None = None) -> Closed:
    """The least graph that holds ``triples`` and all that the rules give.

    The graph is written once, by predicate.  Rules run in strata.  In a semi-naive round each body is evaluated once for
    each of its atoms, with only the last round's new triples at that atom; new triples are what an anti-join with the
    graph leaves, of which only the predicates of the heads are read.  Each round is written as a table of its own, so a
    lost executor repeats a task, not the rounds before."""
    if mode not in ("seminaive", "naive"):
        raise ValueError(mode)
    graph = stored(triples.distinct(), "graph")
    rounds = added = 0
    for group in strata(rules):
        heads = sorted({h.p for r in group for h in r.head})
        recursive = any(is_var(b.p) or b.p in heads for r in group for b in r.body)
        old, delta = None, graph
        while delta is not None and (max_rounds is None or rounds < max_rounds):
            found = None
            for r in group:
                slots = range(len(r.body)) if mode == "seminaive" and old is not None else [None]
                for i in slots:
                    if i is not None and not is_var(r.body[i].p) and r.body[i].p not in heads:
                        continue  # the last round gave nothing for this atom
                    sources = [graph] * len(r.body) if i is None else [graph if j < i else delta if j == i else old for j in range(len(r.body))]
                    more = bgp.heads(r.head, bgp.evaluate(r.body, sources, distinct=False), r.no_literal)
                    found = more if found is None else found.unionByName(more)
            if found is None:
                break
            new = stored(found.distinct().join(graph.where(F.col("p").isin(*heads)), TRIPLE, "left_anti"), "closure")
            n = new.count()
            rounds += 1
            added += n
            if not n:
                break
            old, delta, graph = graph, new, graph.unionByName(new)
            if not recursive:
                break
    return Closed(graph, rounds, added)
