"""Shape constraints to schemas and back.

A shape is a dictionary: a target (``target_class``, ``target_subjects_of`` or ``target_objects_of``) and components:
``in`` (the values that focus nodes may have), ``node_kind`` (``IRI`` or ``IRIOrLiteral``), ``min_count`` 1 with ``path``
(``inverse`` for incoming edges), ``has_value`` or ``class`` with ``path``.  Together the shapes are closed: only the
predicates they mention may occur.  What a schema cannot say is rejected.
"""

from __future__ import annotations

from collections.abc import Mapping, Sequence

from pyspark.sql import DataFrame, SparkSession

from tripleschema.model import Atom, Existential, Pattern, is_literal
from tripleschema.operators.schema import Schema, schema

TYPE = "a"
KNOWN = {"id", "target_class", "target_subjects_of", "target_objects_of", "in", "node_kind", "path", "min_count", "has_value", "class", "inverse"}


def _target(s: Mapping) -> tuple[str, str]:
    found = [(k, s[k]) for k in ("target_class", "target_subjects_of", "target_objects_of") if k in s]
    if len(found) != 1:
        raise ValueError(f"a shape has one target: {dict(s)}")
    return found[0]


def problems(s: Mapping) -> list[str]:
    out = [f"{k} is outside the fragment" for k in s if k not in KNOWN]
    if s.get("min_count", 1) != 1:
        out.append("only a minimum count of 1 can be said")
    if s.get("node_kind", "IRI") not in ("IRI", "IRIOrLiteral"):
        out.append("node_kind is IRI or IRIOrLiteral")
    if "min_count" in s and "path" not in s:
        out.append("a minimum count needs a path")
    return out


def to_schema(spark: SparkSession, shapes: Sequence[Mapping], predicates: Sequence[str] = ()) -> Schema:
    """The schema of closed shapes; ``predicates`` are allowed although no shape mentions them."""
    allowed: dict[str, dict] = {p: {} for p in predicates}
    rules: list[Existential] = []
    for s in shapes:
        if wrong := problems(s):
            raise ValueError("; ".join(wrong))
        kind, name = _target(s)
        at = allowed.setdefault(TYPE if kind == "target_class" else name, {})
        if kind == "target_objects_of":
            if "in" in s:
                at["in"] = [v for v in at["in"] if v in s["in"]] if "in" in at else list(s["in"])
            if s.get("node_kind") == "IRI":
                at["iri"] = True
        elif kind == "target_class":
            at.setdefault("classes", []).append(name)
        if "path" in s:
            allowed.setdefault(s["path"], {})
        focus = {"target_class": Atom("?x", TYPE, name), "target_subjects_of": Atom("?x", name, "?z"), "target_objects_of": Atom("?z", name, "?x")}[kind]
        label = s.get("id", f"shape{len(rules)}")
        if "min_count" in s or "has_value" in s:
            value = s.get("has_value", "?y")
            need = Atom(value, s["path"], "?x") if s.get("inverse") else Atom("?x", s["path"], value)
            rules.append(Existential(label, focus, need))
        elif "class" in s:
            if "path" in s:
                rules.append(Existential(label, Atom("?x", s["path"], "?y"), Atom("?y", TYPE, s["class"])))
            else:
                rules.append(Existential(label, focus, Atom("?x", TYPE, s["class"])))
            allowed.setdefault(TYPE, {}).setdefault("classes", []).append(s["class"])
    patterns: list[Pattern] = []
    for p, at in allowed.items():
        if "in" in at:
            patterns += [Pattern("I", None, "C", p, "L" if is_literal(v) else "C", v) for v in at["in"]]
        elif p == TYPE and at.get("classes"):
            patterns += [Pattern("I", None, "C", p, "C", c) for c in dict.fromkeys(at["classes"])]
        else:
            patterns.append(Pattern("I", None, "C", p, "I" if at.get("iri") or p == TYPE else "A", None))
    return schema(spark, patterns, rules)


def from_schema(patterns: DataFrame, existentials: Sequence[Existential] = ()) -> list[dict]:
    """Shapes for the expert: one for the objects of each predicate, one for each existential rule that has that form."""
    out: list[dict] = []
    by: dict[str, list] = {}
    for r in patterns.collect():  # one row for each pattern of a schema
        by.setdefault(r.p_v or "*", []).append(r)
    for p, rows in sorted(by.items()):
        if all(r.o_k in "CL" for r in rows):
            out.append({"target_objects_of": p, "in": sorted({r.o_v for r in rows})})
        else:
            out.append({"target_objects_of": p, "node_kind": "IRIOrLiteral" if any(r.o_k == "A" for r in rows) else "IRI"})
    for e in existentials:
        if e.a.p == TYPE and e.c.s == e.a.s:
            out.append({"id": e.id, "target_class": e.a.o, "path": e.c.p, "min_count": 1})
        elif e.c.s == e.a.s:
            out.append({"id": e.id, "target_subjects_of": e.a.p, "path": e.c.p, "min_count": 1})
        elif e.c.s == e.a.o:
            out.append({"id": e.id, "target_objects_of": e.a.p, "path": e.c.p, "min_count": 1})
    return out
