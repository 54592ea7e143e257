"""Body rewriting on the sandbox, as written: every atom becomes a union over which of its places are the fresh IRI."""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce
from itertools import product

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tripleschema.model import LAMBDA, Atom, is_var
from tripleschema.operators.bgp import column, ordered


def variants(atom: Atom, predicate_vars: bool = True) -> list[Atom]:
    """The atom with the fresh IRI at any of its places; without predicate variables the predicate stays."""
    return [Atom(*(LAMBDA if off else t for off, t in zip(mask, atom, strict=True))) for mask in product((False, True), (False, True) if predicate_vars else (False,), (False, True))]


def _branch(atom: Atom, names: Sequence[str], graph: DataFrame) -> DataFrame:
    rows = graph
    for place, t in zip("spo", atom, strict=True):
        if not is_var(t):
            rows = rows.where(F.col(place) == t)
    places: dict[str, str] = {}
    for place, t in zip("spo", atom, strict=True):
        if is_var(t):
            if t in places:
                rows = rows.where(F.col(places[t]) == F.col(place))
            places.setdefault(t, place)
    return rows.select(*((F.col(places[v]) if v in places else F.lit(None).cast("string")).alias(column(v)) for v in names))


def eightfold(atoms: Sequence[Atom], sandbox: DataFrame, predicate_vars: bool = True) -> DataFrame:
    """Mappings of the rewritten body: unions per atom, joined where bindings agree or one side has none.

    The fresh IRI is an ordinary constant here and null means unbound; mappings that bind every variable are kept."""
    names = list(dict.fromkeys(v for a in atoms for v in a.variables()))
    out: DataFrame | None = None
    for n, i in enumerate(ordered(atoms)):
        own = atoms[i].variables()
        union = reduce(DataFrame.unionByName, (_branch(v, own, sandbox) for v in variants(atoms[i], predicate_vars))).distinct()
        if out is None:
            out = union
            continue
        shared = [column(v) for v in own if column(v) in out.columns]
        right = union.select(*(F.col(c).alias(f"r_{c}") if c in shared else F.col(c) for c in union.columns))
        out = _tolerant(out, right, shared).distinct()
    return out.dropna(subset=[column(v) for v in names]) if names else out


def _tolerant(left: DataFrame, right: DataFrame, shared: list[str]) -> DataFrame:
    """Join on equal or either side null, split by the nulls of the first shared column."""
    if not shared:
        return left.crossJoin(right)
    first, rest = shared[0], shared[1:]
    agree = reduce(lambda a, b: a & b, ((F.col(c).isNull() | F.col(f"r_{c}").isNull() | (F.col(c) == F.col(f"r_{c}"))) for c in rest), F.lit(True))
    parts = [left.where(F.col(first).isNotNull()).join(right.where(F.col(f"r_{first}").isNotNull()), (F.col(first) == F.col(f"r_{first}")) & agree), left.where(F.col(first).isNull()).join(right, agree), left.where(F.col(first).isNotNull()).join(right.where(F.col(f"r_{first}").isNull()), agree)]
    both = reduce(DataFrame.unionByName, parts)
    return both.select(*(F.coalesce(c, f"r_{c}").alias(c) if c in shared else F.col(c) for c in [*left.columns, *(c for c in right.columns if not c.startswith("r_v_"))]))


def as_ucq(atoms: Sequence[Atom], predicate_vars: bool = True) -> list[tuple[Atom, ...]]:
    """The rewritten body as a union of conjunctive queries."""
    return [tuple(q) for q in product(*(variants(a, predicate_vars) for a in atoms))]


def evaluate_ucq(atoms: Sequence[Atom], sandbox: DataFrame, predicate_vars: bool = True) -> DataFrame:
    """The union of all conjunctive queries that bind every variable."""
    names = list(dict.fromkeys(v for a in atoms for v in a.variables()))
    out = None
    for q in as_ucq(atoms, predicate_vars):
        if {v for a in q for v in a.variables()} != set(names):
            continue
        found = None
        for a in q:
            rows = _branch(a, a.variables(), sandbox)
            if found is None:
                found = rows
            else:
                shared = [c for c in rows.columns if c in found.columns]
                found = found.join(rows, shared) if shared else found.crossJoin(rows)
        found = found.select(*(column(v) for v in names))
        out = found if out is None else out.unionByName(found)
    return out.distinct()
