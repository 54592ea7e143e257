"""A worked example, the two approaches against each other, and closed random graphs against predicted schemas."""

import random

import pytest

from tripleschema import fixtures
from tripleschema.model import TRIPLE_SCHEMA, Atom, existential, is_literal, pattern, rule
from tripleschema.operators import bgp, check, closure, schema
from tripleschema.plans import analysis, batch, canon, consequence, existential as ex, gen, rewrite, witness
from tripleschema.plans.tables import local

def shown(df):
    return {r.pattern for r in schema.rendered(df).collect()}


def graph(spark, triples):
    return local(spark, [(t.s, t.p, *bgp.triple_of(t.o)) for t in triples], TRIPLE_SCHEMA)


def test_canonical_sizes(spark):
    p = schema.frame(spark, fixtures.LOAN_PATTERNS)
    assert canon.sandbox(p).count() == 7
    # nine IRIs and ten terms with the fresh one: two patterns of 81, one of 90, four of 9; a body may add an IRI of its own
    assert [canon.critical_instance(p, r.body).count() for r in fixtures.LOAN_RULES] == [288, 350, 288, 350]
    with pytest.raises(canon.CriticalInstanceTooLarge):
        canon.critical_instance(p, fixtures.LOAN_RULES[0].body, limit=100)


@pytest.mark.parametrize("approach", ["sandbox", "critical"])
def test_worked_example(spark, approach):
    found = consequence.simple(schema.frame(spark, fixtures.LOAN_PATTERNS), fixtures.LOAN_RULES, approach)
    assert found.rounds == 3
    assert shown(found.patterns) == set(fixtures.LOAN_PATTERNS) | {"* :visits *", "* :owesFor *", "* :blockedAt :desk"}


def test_worked_example_existential(spark):
    s = schema.schema(spark, fixtures.LOAN_PATTERNS, fixtures.LOAN_EXISTENTIALS)
    visit, kinds, debt, block = fixtures.LOAN_RULES
    assert ex.retained(s, fixtures.LOAN_RULES).violated == ("staff",)
    assert ex.retained(s, (kinds, debt, block)).retained == fixtures.LOAN_EXISTENTIALS  # nobody visits
    assert ex.retained(s, (visit, debt, block)).retained == fixtures.LOAN_EXISTENTIALS  # no branch is inferred
    assert not ex.retained(s, (visit, kinds)).retained
    rejected = analysis.with_policy(s, fixtures.LOAN_RULES, "reject_rules")
    assert rejected.kept == () and rejected.rejected["kinds"] == "breaks staff"


def test_worked_example_data(spark):
    g = graph(spark, fixtures.LOAN_GRAPH)
    p = schema.frame(spark, fixtures.LOAN_PATTERNS)
    assert check.is_instance(g, p, fixtures.LOAN_EXISTENTIALS).ok
    for mode in ("naive", "seminaive"):
        closed = closure.close(g, fixtures.LOAN_RULES, mode)
        assert (closed.graph.count(), closed.added) == (14, 6)
    assert [r.s for r in check.violations(closed.graph, fixtures.LOAN_EXISTENTIALS).collect()] == [":b2"]


def test_rewriting_forms_agree(spark):
    box = canon.sandbox(schema.frame(spark, ["* :a *", "* :b :c", ":k :a **", "* :b *"]))
    body = (Atom("?v3", ":a", "?v4"), Atom("?v3", ":b", ":c"))
    assert len(rewrite.as_ucq(body)) == 64 and len(rewrite.as_ucq(body, False)) == 16
    a, b = rewrite.eightfold(body, box), rewrite.evaluate_ucq(body, box)
    assert {tuple(r) for r in a.collect()} == {tuple(r) for r in b.collect()}
    c = batch.cases(spark, [batch.body_rule("q", body)])
    fused = batch.evaluate(c, canon.sandbox(schema.frame(spark, ["* :a *", "* :b :c", ":k :a **", "* :b *"]), None))
    assert {tuple(x or "λ" for x in r.b) for r in fused.collect()} == {tuple(r) for r in a.collect()}


LITERALS = [  # schema, rule, what it adds
    (['* :p "1"', "* :q *"], "?x :p ?y, ?z :q ?y => ?x :r ?y", set()),  # a literal cannot be where only IRIs are
    (['* :p "1"', "* :q **"], "?x :p ?y, ?z :q ?y => ?x :r ?y", {'* :r "1"'}),
    (["* :p **"], "?x :p ?y => ?y :r ?x", {"* :r *"}),  # the literal cases drop out
    (["* :p **"], "?x :p ?y => ?x :r ?y", {"* :r **"}),
    (["* :p **", "* :q *"], "?x :p ?y, ?z :q ?y => ?x :r ?y", {"* :r *"}),
    (['* :p "1"'], "?x :p ?y => ?y :r ?x", set()),
    (["* :p **"], '?x :p "1" => ?x :r ?x2 , ?x :s "1"'.replace("?x :r ?x2 , ", ""), {'* :s "1"'}),
    (["* :p *"], '?x :p "1" => ?x :s :t', set()),
    (["* :p *", ":a :p :b"], "?x :p ?x => ?x :self :yes", {"* :self :yes"}),
]


@pytest.mark.parametrize(("patterns", "text", "added"), LITERALS)
def test_literal_traps(spark, patterns, text, added):
    p = schema.frame(spark, patterns)
    r = rule("r", text)
    want = schema.minimised(schema.frame(spark, [*patterns, *added]))
    for approach in ("sandbox", "critical"):
        assert shown(consequence.simple(p, [r], approach).patterns) == shown(want)


def test_approaches_agree_on_generated(spark):
    for seed in range(4):
        g = gen.generate(gen.Config(pi_c=0.3, n_preds=4, n_iris=2, n_lits=2, n_patterns=6, n_rules=3), seed)
        p = schema.frame(spark, g.patterns)
        a, b = consequence.simple(p, g.rules), consequence.simple(p, g.rules, "critical")
        assert shown(a.patterns) == shown(b.patterns)


def random_instance(rng, patterns, n):
    iris, literals = [":i1", ":i2", "cust:0", "cust:1"], ['"x0"', '"x1"', '"z"']
    out = set()
    for _ in range(n):
        p = rng.choice(patterns)
        out.add(Atom(*(v if k in "CL" else rng.choice(iris if k == "I" else iris + literals) for k, v in p.places)))
    return frozenset(out)


def test_closures_stay_inside(spark):
    rng = random.Random(7)
    for seed in range(3):
        g = gen.generate(gen.Config(pi_c=0.2, n_preds=4, n_iris=2, n_lits=2, n_patterns=6, n_rules=3), seed)
        predicted = [pattern_of(r) for r in consequence.simple(schema.frame(spark, g.patterns), g.rules).patterns.collect()]
        for _ in range(40):
            closed = witness.close(random_instance(rng, g.patterns, 8), g.rules)
            assert all(any(p.admits(t) for p in predicted) for t in closed)


def pattern_of(row):
    from tripleschema.model import Pattern

    return Pattern(*row)


VERDICTS = [  # patterns, existential rules, rules, survivors
    (["* :p *", "* a :C"], ["?x a :C -> ?x :q ?y"], ["?x :p ?y => ?x a :C", "?x :p ?y => ?x :q ?y"], {"e0"}),  # the consequent comes too
    (["* :p *"], ["?x a :C -> ?x :q ?y"], ["?x :z ?y => ?x a :C"], {"e0"}),  # cannot be reached
    (["* :p *"], ["?x a :C -> ?x :q ?y"], ["?x :p ?y => ?x :m ?y", "?x :m ?y => ?x :n ?y", "?x :n ?y => ?x a :C"], set()),  # three steps deep
    (["* :p *", "* :q *"], ["?x a :C -> ?x :q ?y", "?x :p ?y -> ?x :q ?z"], ["?x :p ?y => ?x a :C"], {"e0", "e1"}),  # the chase supplies it
    (["* :kind *"], ["?x a :Off -> ?x :owner ?y"], ["?x :kind ?y => ?x a ?y"], set()),  # a head wider than the antecedent
    (["* :r **"], ["?x :p ?y -> ?y :q ?z"], ["?x :r ?y => ?x :p ?y", "?x :r ?y => ?y :q ?x"], set()),  # only a literal breaks it
    (["* :p *", ":a :q **", ":a :r :a"], ["?x :t :a -> ?x :q :a", "?x :p ?y -> ?x :r ?k"], ["?x :p ?y => ?x :t :a"], set()),  # a null becomes a constant
]


@pytest.mark.parametrize(("patterns", "existentials", "rules", "kept"), VERDICTS)
def test_verdicts(spark, patterns, existentials, rules, kept):
    s = schema.schema(spark, patterns, [existential(f"e{i}", t) for i, t in enumerate(existentials)])
    found = ex.retained(s, [rule(f"r{i}", t) for i, t in enumerate(rules)])
    assert {e.id for e in found.retained} & {"e0"} == kept & {"e0"} and found.complete


def test_recursion_ends_by_minimality(spark):
    s = schema.schema(spark, ["* :next *"], [existential("e", "?x :after ?y -> ?y :next ?z")])
    found = ex.retained(s, fixtures.AFTER_RULES)
    assert found.violated == ("e",)
    s = schema.schema(spark, ["* :next *"], [existential("e", "?x :after ?y -> ?x :next ?z")])
    found = ex.retained(s, fixtures.AFTER_RULES)  # every path begins with a step, so one body is minimal
    assert found.complete and found.retained == s.existentials


def test_schema_order(spark):
    a, b = schema.frame(spark, ["* :p **", "* :p *", '* :p "1"']), schema.frame(spark, ["* :p **"])
    assert schema.equivalent(a, b) and shown(schema.minimised(a)) == {"* :p **"}
    assert not schema.covers(schema.frame(spark, ["* :p *"]), b)
    assert {(r.pattern) for r in schema.rendered(schema.difference(a, b).where("change = 'removed'")).collect()} == {"* :p *", '* :p "1"'}


def test_questions(spark):
    p = schema.frame(spark, fixtures.LOAN_PATTERNS)
    assert {r.rule_id for r in analysis.applicable(p, fixtures.LOAN_RULES).collect()} == {"visit", "kinds", "debt", "block"}
    assert {r.rule_id for r in analysis.can_derive(p, fixtures.LOAN_RULES, pattern("* :blockedAt :desk")).collect()} == {"block"}
    less = p.where("o_k != 'L'")
    assert {(r.rule_id, r.change) for r in analysis.applicability_diff(p, less, fixtures.LOAN_RULES).collect()} == {("debt", "lost"), ("block", "lost")}


def test_cycles_end(spark):
    ring = graph(spark, [Atom(f":{i}", ":next", f":{(i + 1) % 4}") for i in range(4)])
    assert closure.close(ring, fixtures.AFTER_RULES).graph.where("p = ':after'").count() == 16


def test_invalid_heads_are_dropped_whole(spark):
    g = graph(spark, [Atom(":a", ":p", '"1"'), Atom(":b", ":p", ":c")])
    found = closure.apply(rule("r", "?x :p ?y => ?y :q ?x , ?x :r :ok"), g)
    assert {(r.s, r.p) for r in found.collect()} == {(":c", ":q"), (":b", ":r")}


def test_empty_rule_sets(spark):
    p = schema.frame(spark, ["* :p *"])
    assert shown(consequence.simple(p, []).patterns) == {"* :p *"}
    assert consequence.simple(local(spark, [], "s_k string, s_v string, p_k string, p_v string, o_k string, o_v string"), fixtures.LOAN_RULES).patterns.isEmpty()
    assert not is_literal(":x")
