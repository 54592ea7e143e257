"""Conformance of graphs to schemas, and violations of existential rules."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tripleschema.model import Atom, Existential, is_var
from tripleschema.operators import bgp
from tripleschema.operators.schema import PLACES

#: Patterns with a wildcard predicate that are turned into one filter; more of them are joined.
COMPILED = 200
#: Patterns that are broadcast.
SMALL = 100_000


def admitted(s: Column, o: Column, o_lit: Column) -> Column:
    """Whether a triple fits a joined pattern row, predicates aside."""
    subject = (F.col("s_k") == "I") | (F.col("s_v") == s)
    obj = (F.col("o_k") == "A") | ((F.col("o_k") == "I") & ~o_lit) | ((F.col("o_k") == "C") & ~o_lit & (F.col("o_v") == o)) | ((F.col("o_k") == "L") & o_lit & (F.col("o_v") == F.concat(F.lit('"'), o, F.lit('"'))))
    return subject & obj


def conforming(triples: DataFrame, patterns: DataFrame, how: str = "left_semi") -> DataFrame:
    """The triples that some pattern admits (``left_anti``: those that none admits).

    Up to SMALL patterns are broadcast to where the triples are.  More of them are met by equal subjects or objects, so
    that no predicate, however frequent, is a join key by itself; what has neither constant is few, as the predicates
    are, and is broadcast in any case up to SMALL.  Rare patterns with a wildcard predicate become a filter up to COMPILED
    and are met like others beyond."""
    rows = patterns.select("s_k", "s_v", "p_k", F.col("p_v").alias("p_of"), "o_k", "o_v").distinct()
    free = patterns.where("p_k != 'C'").select(*PLACES).distinct().limit(COMPILED + 1).collect()
    few = rows.limit(SMALL + 1).count() <= SMALL
    t = triples.alias("t")
    if free and len(free) <= COMPILED:
        extra, rows = reduce(lambda a, b: a | b, map(compiled, free)), rows.where("p_k = 'C'")
        rest = t.where(~extra)
    else:
        extra, rest = None, t
    on = ((F.col("t.p") == F.col("p_of")) if extra is not None or not free else (F.col("p_of").isNull() | (F.col("t.p") == F.col("p_of")))) & admitted(F.col("t.s"), F.col("t.o"), F.col("t.o_lit"))
    if few:
        met = [rest.join(F.broadcast(rows), on, how)]
    else:
        object_is = F.col("o_v") == F.when(F.col("t.o_lit"), F.concat(F.lit('"'), F.col("t.o"), F.lit('"'))).otherwise(F.col("t.o"))
        parts = [(rows.where("s_k = 'C'"), F.col("s_v") == F.col("t.s")), (rows.where("s_k != 'C' and o_k in ('C', 'L')"), object_is), (F.broadcast(bounded(rows.where("s_k != 'C' and o_k not in ('C', 'L')"))), F.lit(True))]
        met, left = [], rest
        for part, key in parts:
            if how == "left_semi":
                met.append(left.join(part, key & on, "left_semi"))
            left = left.join(part, key & on, "left_anti").alias("t")
        met = met or [left]
    out = reduce(DataFrame.unionByName, met)
    return out if extra is None or how == "left_anti" else t.where(extra).unionByName(out)


def bounded(rows: DataFrame) -> DataFrame:
    """Patterns without constants but the predicate, checked to be few: there are two for each predicate at most."""
    if rows.limit(SMALL + 1).count() > SMALL:
        raise ValueError(f"more than {SMALL} predicates")
    return rows


def compiled(row) -> Column:
    """One pattern as a filter on triples."""
    parts = [F.lit(True)]
    if row.s_k == "C":
        parts.append(F.col("s") == row.s_v)
    if row.p_k == "C":
        parts.append(F.col("p") == row.p_v)
    if row.o_k == "I":
        parts.append(~F.col("o_lit"))
    elif row.o_k in "CL":
        value, lit = bgp.triple_of(row.o_v)
        parts.append((F.col("o") == value) & (F.col("o_lit") == lit))
    return reduce(lambda a, b: a & b, parts)


def violations(triples: DataFrame, rules: Sequence[Existential]) -> DataFrame:
    """``e_id`` and the triple that matches an antecedent without any match of the consequent: an anti-join per rule."""
    out = None
    for e in rules:
        rows = triples.select("s", "p", "o", "o_lit")
        found = _antecedent(e.a, rows)
        keys = [bgp.column(v) for v in e.frontier()]
        right = bgp.matches(e.c, rows)
        if keys:
            found = found.join(right.select(*keys).distinct(), keys, "left_anti")
        else:
            found = found.join(right.limit(1).select(F.lit(1).alias("k")), F.lit(1) == F.col("k"), "left_anti")
        found = found.select(F.lit(e.id).alias("e_id"), "s", "p", "o", "o_lit")
        out = found if out is None else out.unionByName(found)
    return out if out is not None else triples.limit(0).select(F.lit("").alias("e_id"), "s", "p", "o", "o_lit")


def _antecedent(atom: Atom, triples: DataFrame) -> DataFrame:
    """The matching triples with their bindings beside them."""
    rows = triples
    places = {"s": F.col("s"), "p": F.col("p"), "o": bgp.term()}
    for place, t in zip("spo", atom, strict=True):
        if not is_var(t):
            value, lit = bgp.triple_of(t)
            rows = rows.where((F.col(place) == value) & (F.col("o_lit") == lit) if place == "o" else F.col(place) == t)
    for v in atom.variables():
        own = [p for p, t in zip("spo", atom, strict=True) if t == v]
        for p in own[1:]:
            rows = rows.where(places[own[0]] == places[p])
        rows = rows.withColumn(bgp.column(v), places[own[0]])
    return rows


@dataclass
class Verdict:
    ok: bool
    offenders: DataFrame
    violations: DataFrame


def is_instance(triples: DataFrame, patterns: DataFrame, rules: Sequence[Existential]) -> Verdict:
    """Whether a graph is an instance of a schema: no triple outside its patterns, no violated existential rule."""
    offenders, broken = conforming(triples, patterns, "left_anti"), violations(triples, rules)
    return Verdict(offenders.isEmpty() and broken.isEmpty(), offenders, broken)
