"""Existential rules whose bodies are many or long."""

from tripleschema.model import existential, rule
from tripleschema.operators import schema
from tripleschema.plans import existential as ex


def test_all_bodies_without_recursion():
    rules = [rule(f"r{i}{j}", f"?x :s{i}_{j} ?y => ?x :p{i} ?y") for i in range(4) for j in range(6)]
    body = rule("b", "?a :p0 ?b, ?b :p1 ?c, ?c :p2 ?d, ?d :p3 ?e => ?a :q ?e").body
    found = ex.rewritings(body, rules)
    assert found.complete and len(found.bodies) == 7**4
    assert not ex.rewritings(body, rules, limit=100).complete
    assert ex.unfold([existential("e", "?x :q ?y -> ?y :z ?w")], [*rules, rule("b", "?a :p0 ?b, ?b :p1 ?c => ?a :q ?c")], limit=10)[1] == {"e": False}


def test_literals_in_long_bodies(spark):
    more = [f":s{i}" for i in range(8)]
    s = schema.schema(spark, ["* :r **", *(f"* {p} **" for p in more)], [existential("e", "?x :p ?y -> ?y :q ?z")])
    body = "?x :r ?y, " + ", ".join(f"?x {p} ?z{i}" for i, p in enumerate(more))
    found = ex.retained(s, [rule("a", f"{body} => ?x :p ?y"), rule("b", "?x :r ?y => ?y :q ?x")])
    assert found.violated == ("e",) and found.witnesses == 2**9  # only a literal at ?y breaks it
