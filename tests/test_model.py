import pytest

from tripleschema import fixtures
from tripleschema.model import Atom, atoms, existential, pattern, problems, recursive_predicates, rule, unify, weak_acyclicity
from tripleschema.plans import existential as ex


def test_pattern_order():
    assert pattern('* :p "1"').below(pattern("* :p **"))
    assert not pattern('* :p "1"').below(pattern("* :p *"))
    assert pattern(":a :p :b").below(pattern("* * *")) and pattern("* :p *").below(pattern("* :p **"))
    assert not pattern("* :p **").below(pattern("* :p *"))
    with pytest.raises(ValueError):
        pattern("** :p *")


@pytest.mark.parametrize("text", ["?x :p ?y => ?x ?y :o", "?x :p ?y => ?x :q ?x", "?x :p ?y => ?x :q ?z", '?x :p ?y => "l" :q ?x'])
def test_malformed_rules(text):
    with pytest.raises(ValueError):
        rule("r", text)


def test_rule_text_round_trip():
    r = fixtures.LOAN_RULES[2]
    assert rule("debt", str(r)) == r and not problems(r)
    assert r.firm() == {"?m", "?i"}


def test_unify():
    assert unify(Atom("?x", "a", "?y"), Atom("?z", "a", ":C"))["?y"] == ":C"
    assert unify(Atom("?x", ":p", "?x"), Atom(":a", ":p", ":b")) is None


def test_weak_acyclicity():
    assert weak_acyclicity(fixtures.STAR_EXISTENTIALS)[0]
    ok, cycle = weak_acyclicity([existential("e", "?x :p ?y -> ?y :p ?z")])
    assert not ok and cycle


def test_recursion():
    assert recursive_predicates(fixtures.STAR_RULES) == {":within", ":soldIn"}
    assert not recursive_predicates(fixtures.LOAN_RULES)


def test_rewritings_unfold_heads():
    found = ex.rewritings(fixtures.LOAN_RULES[3].body, fixtures.LOAN_RULES)
    assert found.complete and len(found.bodies) == 6  # one atom as it is or unfolded, the other as it is or unfolded once or twice
    deep = ex.rewritings(atoms("?x :after ?y"), fixtures.AFTER_RULES, max_depth=3)
    assert not deep.complete and len(deep.bodies) > 3


def test_triggers_and_specialise():
    e = existential("e", "?x a :Off -> ?x :owner ?y")
    r = rule("r", "?x :kind ?y => ?x a ?y")
    assert ex.triggers(e, r) == [0]
    assert ex.specialise(r, 0, e.a).body == (Atom("?x", ":kind", ":Off"),) or ex.specialise(r, 0, e.a).body[0].o == ":Off"
    assert ex.triggers(e, rule("s", "?x :kind ?y => ?x a :On")) == []
