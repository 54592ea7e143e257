"""Bodies of rules on graphs: one join plan per body, for graphs of any size."""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tripleschema.model import Atom, is_literal, is_var


def term(o: str = "o", lit: str = "o_lit") -> Column:
    """The object as a term string."""
    return F.when(F.col(lit), F.concat(F.lit('"'), F.col(o), F.lit('"'))).otherwise(F.col(o))


def column(v: str) -> str:
    """The column that holds a variable's binding."""
    return f"v_{v[1:]}"


def triple_of(t: str) -> tuple[str, bool]:
    return (t[1:-1], True) if is_literal(t) else (t, False)


def matches(atom: Atom, triples: DataFrame) -> DataFrame:
    """Bindings of one atom.  Constants become filters that reach the scan; a repeated variable compares its places."""
    rows = triples
    if not is_var(atom.p):
        rows = rows.where(F.col("p") == atom.p)
    if not is_var(atom.s):
        rows = rows.where(F.lit(False) if is_literal(atom.s) else F.col("s") == atom.s)
    if not is_var(atom.o):
        value, lit = triple_of(atom.o)
        rows = rows.where((F.col("o") == value) & (F.col("o_lit") == lit))
    places = {"s": F.col("s"), "p": F.col("p"), "o": term()}
    seen: dict[str, Column] = {}
    for place, t in zip("spo", atom, strict=True):
        if is_var(t):
            if t in seen:
                rows = rows.where(seen[t] == places[place])
            else:
                seen[t] = places[place]
    return rows.select(*(c.alias(column(v)) for v, c in seen.items())) if seen else rows.select(F.lit(True).alias("v_")).limit(1)


def ordered(atoms: Sequence[Atom]) -> list[int]:
    """Connected atoms next to each other, those with most constants first, so no product is planned by accident."""
    left, out, bound = list(range(len(atoms))), [], set()
    while left:
        linked = [i for i in left if bound & set(atoms[i].variables())] or left
        best = max(linked, key=lambda i: (sum(not is_var(t) for t in atoms[i]), -i))
        out.append(best)
        left.remove(best)
        bound |= set(atoms[best].variables())
    return out


def evaluate(atoms: Sequence[Atom], triples: DataFrame | Sequence[DataFrame], distinct: bool = True) -> DataFrame:
    """All mappings of a body, a column for each variable.  ``triples`` may give a graph for each atom."""
    graphs = list(triples) if isinstance(triples, Sequence) else [triples] * len(atoms)
    out: DataFrame | None = None
    for i in ordered(atoms):
        found = matches(atoms[i], graphs[i])
        if out is None:
            out = found
            continue
        shared = [c for c in found.columns if c in out.columns and c != "v_"]
        out = out.join(found.drop("v_") if shared else found.withColumnRenamed("v_", f"v_{i}"), shared) if shared else out.crossJoin(found.withColumnRenamed("v_", f"v_{i}"))
    out = out.select(*(column(v) for v in dict.fromkeys(v for a in atoms for v in a.variables())))
    return out.distinct() if distinct else out


def value(t: str) -> Column:
    return F.col(column(t)) if is_var(t) else F.lit(t)


def heads(head: Sequence[Atom], mappings: DataFrame, no_literal: Sequence[str] = ()) -> DataFrame:
    """Head triples of mappings.  A mapping that would put a literal in a subject place, or has one at a variable that may
    not be one, gives none of its triples."""
    firm = [value(a.s) for a in head] + [value(a.p) for a in head] + [value(v) for v in no_literal]
    valid = reduce(lambda a, b: a & b, (~c.startswith('"') for c in firm))
    triples = F.array(*(F.struct(value(a.s).alias("s"), value(a.p).alias("p"), value(a.o).alias("t")) for a in head))
    rows = mappings.where(valid).select(F.explode(triples).alias("t")).select("t.s", "t.p", "t.t")
    lit = F.col("t").startswith('"')
    return rows.select("s", "p", F.when(lit, F.expr("substring(t, 2, length(t) - 2)")).otherwise(F.col("t")).alias("o"), lit.alias("o_lit"))
