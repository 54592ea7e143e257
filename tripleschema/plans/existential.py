"""Which existential rules the inference rules can break.

For every existential rule and every rule head that can feed it, the bodies that lead there are found by unfolding
rules backward (on the driver: it is about the few terms of the rule set).  All bodies of all rules are evaluated on the
sandbox in one plan; every mapping is grounded to a witness graph; all witnesses are rows, and each is chased to an
instance, closed and tested where it lies.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from dataclasses import dataclass
from itertools import chain, combinations

import pyarrow as pa
from pyspark.sql import DataFrame

from tripleschema.model import Atom, Existential, Pattern, Rule, is_var, recursive_predicates, renamed, unify, weak_acyclicity
from tripleschema.operators.schema import PLACES, Schema
from tripleschema.plans import batch, canon, witness
from tripleschema.plans.tables import local, prepare, written

#: Pattern tables up to this size travel with the witnesses.
MOST_PATTERNS = 100_000
#: Unfoldings of recursive rules in one body, where minimality alone does not end them, unless asked for otherwise.
RECURSIVE_DEPTH = 2
#: Bodies of recursive rules, unless asked for otherwise; without recursion there is no bound.
RECURSIVE_BODIES = 2_000
#: Predicates of the atoms that carry what a body must keep, and what cannot be a literal in it, because a rule that was
#: unfolded has it as a subject.
_KEPT, _FIRM = "\0kept", "\0firm"
#: Verdicts of a worker's table at most.
BATCH = 1_000


def triggers(e: Existential, r: Rule) -> list[int]:
    """The heads of a rule that can give a triple that matches the antecedent."""
    a = renamed([e.a], "'")[0]
    return [i for i, h in enumerate(r.head) if unify(h, a) is not None]


def specialise(r: Rule, head: int, antecedent: Atom) -> Rule:
    """The rule narrowed to the cases in which a head gives a match of the antecedent."""
    m = unify(r.head[head], renamed([antecedent], "'")[0])
    if m is None:
        raise ValueError(f"{antecedent} cannot come from {r}")
    return Rule(r.id, tuple(a.replaced(m) for a in r.body), tuple(a.replaced(m) for a in r.head), tuple(m.get(v, v) for v in r.no_literal if is_var(m.get(v, v))))


def _normal(body: Sequence[Atom]) -> tuple[Atom, ...]:
    """A body with its variables numbered by where they occur, the same for renamed copies but for rare symmetries."""
    body = sorted(set(body))
    mark: dict[str, object] = {v: () for a in body for v in a.variables()}
    for _ in range(4):
        seen = lambda t: (1, mark[t]) if is_var(t) else (0, t)  # noqa: B023, E731
        new: dict[str, list] = {v: [] for v in mark}
        for a in body:
            for i, t in enumerate(a):
                if is_var(t):
                    new[t].append((i, *(seen(x) if x != t else (2, "") for x in a)))
        ranks = {k: i for i, k in enumerate(sorted({repr(sorted(map(repr, v))) for v in new.values()}))}
        mark = {v: ranks[repr(sorted(map(repr, x)))] for v, x in new.items()}
    names: dict[str, str] = {}
    for v in sorted(mark, key=lambda v: (mark[v], v)):
        names[v] = f"?n{len(names)}"
    return tuple(sorted(a.replaced(names) for a in body))


def subsumes(general: Sequence[Atom], special: Sequence[Atom]) -> bool:
    """Whether the atoms of one body can be mapped into those of another: wherever the other matches, the first does."""
    by_predicate: dict[str, list[Atom]] = {}
    for a in special:
        by_predicate.setdefault(a.p, []).append(a)
    plain = [a for a in special if not a.p.startswith((_KEPT, _FIRM))]
    firm = {t for a in special for t in (a[:2] if not a.p.startswith(_KEPT) else ())}
    todo = sorted((a for a in general if a.p != _FIRM), key=lambda a: len(by_predicate.get(a.p, special)))
    asked = [a.s for a in general if a.p == _FIRM]

    def fit(i: int, m: dict[str, str]) -> bool:
        if i == len(todo):
            return all(y in firm if is_var(y) else not y.startswith('"') for y in (m.get(t, t) for t in asked))
        a = todo[i]
        for b in plain if is_var(a.p) else by_predicate.get(a.p, ()):
            more = dict(m)
            if all(more.setdefault(x, y) == y if is_var(x) else x == y for x, y in zip(a, b, strict=True)) and fit(i + 1, more):
                return True
        return False

    return fit(0, {})


def _marked(atoms_: Sequence[Atom]) -> tuple[Atom, ...] | None:
    """The body in normal form, with marks only where they say something; None if a literal stands where none can."""
    firm = {t for a in atoms_ if not a.p.startswith((_KEPT, _FIRM)) for t in a[:2]}
    if any(t.startswith('"') for t in firm) or any(a.p == _FIRM and a.s.startswith('"') for a in atoms_):
        return None
    return _normal([a for a in atoms_ if a.p != _FIRM or (is_var(a.s) and a.s not in firm)])


@dataclass
class Rewritings:
    bodies: list[tuple[Atom, ...]]
    complete: bool


def rewritings(body: Sequence[Atom], rules: Sequence[Rule], max_depth: int | None = None, limit: int | None = None, kept: Sequence[str] | None = None) -> Rewritings:
    """The minimal bodies from which the rules can derive ``body``, itself included.

    Each step unfolds one atom by a rule with a fitting head.  A body that another one subsumes is dropped with all that
    would come of it: whatever it derives for the terms ``kept`` (all variables, if not given), the other derives too.
    That ends by itself without recursion, and with recursion whenever finitely many bodies are minimal.  Where it does
    not, recursive rules are unfolded ``max_depth`` times in a body, to ``limit`` bodies (RECURSIVE_DEPTH and
    RECURSIVE_BODIES unless given), and the result says that it is not complete; other rules are never bounded."""
    kept = list(dict.fromkeys(v for a in body for v in a.variables())) if kept is None else list(kept)
    found, complete = _search(body, rules, max_depth, limit, kept)
    plain = {_normal([a for a in b if not a.p.startswith((_KEPT, _FIRM))]) for b in found}
    return Rewritings(sorted(plain), complete)


def unfolded_rules(r: Rule, rules: Sequence[Rule], max_depth: int | None = None, limit: int | None = None) -> tuple[list[Rule], bool]:
    """Rules from all minimal bodies of ``r`` to its head, and whether they are complete: what they give on a graph is what
    ``r`` gives on its closure."""
    kept = list(dict.fromkeys(v for h in r.head for v in h.variables()))
    found, complete = _search(r.body, rules, max_depth, limit, kept)
    out = []
    for n, b in enumerate(sorted(found)):
        now = {kept[int(a.p[len(_KEPT) :])]: a.s for a in b if a.p.startswith(_KEPT)}
        if not any(now[h.s].startswith('"') for h in r.head if is_var(h.s)):
            firm = tuple(a.s for a in b if a.p == _FIRM)
            out.append(Rule(f"{r.id}/{n}", tuple(a for a in b if not a.p.startswith((_KEPT, _FIRM))), tuple(h.replaced(now) for h in r.head), firm))
    return out, complete


def _search(body: Sequence[Atom], rules: Sequence[Rule], max_depth: int | None, limit: int | None, kept: Sequence[str]) -> tuple[list[tuple[Atom, ...]], bool]:
    """The minimal bodies, each with atoms that carry its terms for ``kept``."""
    inner = [recursive_rule(r, rules) for r in rules]
    depth = max_depth if max_depth is not None else RECURSIVE_DEPTH
    most = limit if limit is not None else (RECURSIVE_BODIES if any(inner) else 1 << 60)
    first = _normal([*body, *(Atom(t, f"{_KEPT}{i}", t) for i, t in enumerate(kept))])
    predicates = lambda b: frozenset(a.p for a in b if not is_var(a.p) and a.p != _FIRM)
    found: dict[tuple[Atom, ...], frozenset[str]] = {first: predicates(first)}
    met, frontier, complete, step = {first}, [(first, 0)], True, 0
    while frontier:
        following = []
        for b, used in frontier:
            if b not in found:  # a smaller body came after it
                continue
            for i, a in enumerate(b):
                for r, again in zip(rules, inner, strict=True):
                    body_r = renamed(r.body, f"_{step}")
                    heads = renamed(r.head, f"_{step}")
                    marks = [Atom(v, _FIRM, v) for v in dict.fromkeys([*(h.s for h in heads if is_var(h.s)), *(f"{v}_{step}" for v in r.no_literal)])]
                    for h in heads:
                        m = None if a.p.startswith((_KEPT, _FIRM)) else unify(h, a)
                        if m is None:
                            continue
                        new = _marked([x.replaced(m) for x in (*b[:i], *b[i + 1 :], *body_r, *marks)])
                        if new is None or new in met:
                            continue
                        have = predicates(new)
                        if any(p <= have and subsumes(old, new) for old, p in found.items()):
                            continue
                        if again and used >= depth or len(found) >= most:
                            complete = False
                            continue
                        met.add(new)
                        for old in [old for old, p in found.items() if have <= p and subsumes(new, old)]:
                            del found[old]
                        found[new] = have
                        following.append((new, used + again))
        frontier, step = following, step + 1
    return list(found), complete


def recursive_rule(r: Rule, rules: Sequence[Rule]) -> bool:
    """Whether a rule can feed its own body, through others or by itself."""
    around = recursive_predicates(rules)
    heads = {h.p for h in r.head} & around
    if not heads:
        return False
    fed, todo = set(heads), list(heads)
    while todo:
        p = todo.pop()
        for q in rules:
            if any(is_var(b.p) or b.p == p for b in q.body):
                new = {h.p for h in q.head} - fed
                fed |= new
                todo += new
    return any(is_var(b.p) or b.p in fed for b in r.body)


@dataclass
class Unfolded:
    case_id: str
    e: Existential
    rule: Rule
    body: tuple[Atom, ...]


def unfold(existentials: Sequence[Existential], rules: Sequence[Rule], do_specialise: bool = True, max_depth: int | None = None, limit: int | None = None) -> tuple[list[Unfolded], dict[str, bool]]:
    """All bodies to test, and for each existential rule whether they are all there are."""
    out, complete, known = [], {e.id: True for e in existentials}, {}
    for e in existentials:
        seen = set()
        for r in rules:
            for h in triggers(e, r):
                start = specialise(r, h, e.a) if do_specialise else r
                front = [start.head[h][i] for i, v in enumerate(e.a) if v in e.frontier()]
                front = tuple(dict.fromkeys(t for t in front if is_var(t)))
                key = (start.body, front)
                if key not in known:
                    known[key] = rewritings(start.body, rules, max_depth, limit, front)
                complete[e.id] &= known[key].complete
                for body in known[key].bodies:
                    if body not in seen:
                        seen.add(body)
                        out.append(Unfolded(f"{e.id}/{len(out)}", e, r, body))
    return out, complete


# -- witnesses


def ground(case_id: str, body: Sequence[Atom], binding: Sequence[str | None], firm: Sequence[int], literals: bool) -> Iterator[tuple[str, witness.Graph]]:
    """Witness graphs of one mapping: unbound variables become fresh IRIs, and in further witnesses, where literals may
    stand, fresh literals."""
    names = list(dict.fromkeys(v for a in body for v in a.variables()))
    free = [i for i, (v, b) in enumerate(zip(names, binding, strict=True)) if b is None and i not in firm]
    choices = chain.from_iterable(combinations(free, k) for k in range(len(free) + 1)) if literals else [()]
    for c in choices:
        fill = {v: b if b is not None else (f'"w:{i}"' if i in c else f"w:{i}") for i, (v, b) in enumerate(zip(names, binding, strict=True))}
        yield f"{case_id}:{''.join(map(str, c)) or '-'}", frozenset(a.replaced(fill) for a in body)


def _test_batches(cases: dict, existentials, rules, patterns, literals: bool, explain: bool):
    def table(out: list[tuple]) -> pa.RecordBatch:
        kinds = [pa.string(), pa.string(), pa.string(), pa.bool_(), *[pa.list_(pa.string())] * 3]
        return pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], t) for i, t in enumerate(kinds)], [c.split()[0] for c in _TESTED.split(", ")])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch_ in batches:
            out = []
            for case_id, b, firm in zip(*(batch_.column(i).to_pylist() for i in range(3)), strict=True):
                e, body = cases[case_id]
                bound = "|".join(x or "*" for x in b)
                for name, graph in ground(case_id, body, b, firm, literals):
                    try:
                        found, known = witness.violates(graph, e, existentials, rules, patterns), True
                    except witness.TooManyChases:
                        found, known = None, False
                    lines = lambda g: sorted(map(str, g)) if g is not None else []
                    out.append((e.id, case_id, f"{name}:{bound}", found is not None if known else None, lines(graph), lines(found and found[0]) if explain else [], lines(found and found[1]) if explain else []))
                    if len(out) == BATCH:
                        yield table(out)
                        out = []
            yield table(out)

    return run


_TESTED = "e_id string, case_id string, witness_id string, violates boolean, witness array<string>, instance array<string>, closed array<string>"


@dataclass
class Tested:
    rows: DataFrame
    complete: dict[str, bool]
    cases: list[Unfolded]


def tested(schema: Schema, rules: Sequence[Rule], faithful: bool = False, specialised: bool = True, witness_literals: bool = True, strict_witness: bool = True, max_depth: int | None = None, explain: bool = False, limit: int | None = None) -> Tested:
    """Every witness with its verdict.  ``faithful`` switches the three refinements off."""
    if faithful:
        specialised = witness_literals = strict_witness = False
    ok, cycle = weak_acyclicity(schema.existentials)
    if not ok:
        raise ValueError(f"the existential rules may invent values without end: {cycle}")
    spark = schema.patterns.sparkSession
    prepare(spark)
    unfolded, complete = unfold(schema.existentials, rules, specialised, max_depth, limit)
    if not unfolded:
        return Tested(local(spark, [], _TESTED), complete, [])
    c = batch.cases(spark, [batch.body_rule(u.case_id, u.body) for u in unfolded])
    kept = batch.filtered(c, batch.evaluate(c, canon.sandbox(schema.patterns, None)), schema.patterns)
    patterns = None
    if strict_witness:
        rows = schema.patterns.select(*PLACES).limit(MOST_PATTERNS + 1).collect()
        if len(rows) > MOST_PATTERNS:
            raise ValueError(f"strict witnesses take up to {MOST_PATTERNS} patterns")
        patterns = [Pattern(*r) for r in rows]
    kept = written(kept, "witness-mappings").repartition(spark.sparkContext.defaultParallelism)
    run = _test_batches({u.case_id: (u.e, u.body) for u in unfolded}, list(schema.existentials), list(rules), patterns, witness_literals, explain)
    return Tested(kept.mapInArrow(run, _TESTED), complete, unfolded)


@dataclass
class Retained:
    retained: tuple[Existential, ...]
    violated: tuple[str, ...]
    undecided: tuple[str, ...]
    witnesses: int
    bodies: int = 0

    @property
    def complete(self) -> bool:
        return not self.undecided


def retained(schema: Schema, rules: Sequence[Rule], mode: str = "safe", **options) -> Retained:
    """The existential rules that survive.  Where the search for recursive rules or the chases of a witness had to be
    bounded, what was not decided is reported and counts as lost, unless ``mode`` is "exact"."""
    from pyspark.sql import functions as F

    t = tested(schema, rules, **options)
    verdicts = {r.e_id: r for r in t.rows.groupBy("e_id").agg(F.bool_or(F.coalesce("violates", F.lit(False))).alias("bad"), F.bool_or(F.col("violates").isNull()).alias("open"), F.count("*").alias("n")).collect()}
    bad = {k for k, r in verdicts.items() if r.bad}
    open_ = {k for k, r in verdicts.items() if r.open}
    undecided = tuple(e.id for e in schema.existentials if e.id not in bad and (not t.complete[e.id] or e.id in open_))
    lost = bad | (set(undecided) if mode == "safe" else set())
    return Retained(tuple(e for e in schema.existentials if e.id not in lost), tuple(sorted(bad)), undecided, sum(r.n for r in verdicts.values()), len(t.cases))


def explained(schema: Schema, rules: Sequence[Rule], **options) -> DataFrame:
    """For the expert: each violation with its existential rule, the rule that feeds it, the body and the graphs."""
    t = tested(schema, rules, explain=True, **options)
    spark = schema.patterns.sparkSession
    cases = local(spark, [(u.case_id, u.rule.id, " , ".join(map(str, u.body))) for u in t.cases], "case_id string, rule_id string, body string")
    return t.rows.where("violates").join(cases, "case_id").select("e_id", "rule_id", "body", "witness", "instance", "closed")
