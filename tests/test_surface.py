import json
import uuid

import pytest

from tripleschema import fixtures
from tripleschema.functions import shapes
from tripleschema.model import TRIPLE_SCHEMA
from tripleschema.operators import schema
from tripleschema.plans.tables import local, shared_dir
from tripleschema.sources import store, tables
from tripleschema.streaming import observations

SHAPES = fixtures.LOAN_SHAPES


def test_shapes(spark):
    s = shapes.to_schema(spark, SHAPES)
    assert {r.pattern for r in schema.rendered(s.patterns).collect()} == set(fixtures.LOAN_PATTERNS)
    assert [(e.a, e.c) for e in s.existentials] == [(fixtures.LOAN_EXISTENTIALS[0].a, fixtures.LOAN_EXISTENTIALS[0].c)]
    again = shapes.to_schema(spark, shapes.from_schema(s.patterns, s.existentials))
    assert schema.equivalent(s.patterns, again.patterns) and len(again.existentials) == 1
    for bad in ({"target_class": ":C", "path": ":p", "min_count": 2}, {"target_class": ":C", "not": {}}, {"in": [":a"]}, {"target_objects_of": ":p", "node_kind": "Literal"}):
        with pytest.raises(ValueError):
            shapes.to_schema(spark, [bad])


def test_text_and_store(spark):
    rows = [("a:1", "p", 'x "y" \\ z', True), ("a:1", "p", "b:2", False), ("_:n", "q", "_:m", False), ("a:2", "p", "", True)]
    g = local(spark, rows, TRIPLE_SCHEMA)
    path = f"{shared_dir(spark)}/nt-{uuid.uuid4().hex}"
    store.write_ntriples(g, path)
    back, bad = store.read_ntriples(spark, path)
    assert sorted(map(tuple, back.collect())) == sorted(rows) and bad.isEmpty()
    ids, terms = store.encode(g)
    assert sorted(map(tuple, store.decode(ids, terms).collect())) == sorted(rows)
    store.write_store(g, path + "-store")
    assert "PartitionFilters: [isnotnull(p" in store.read_store(spark, path + "-store").where("p = 'q'")._jdf.queryExecution().toString()


def test_data_source_and_json(spark):
    spark.dataSource.register(store.TripleSource)
    df = spark.read.format("triples").option("text", ':a :p "x y"\n# no\n:a :q :b').option("partitions", 2).load()
    assert sorted(map(tuple, df.collect())) == [(":a", ":p", "x y", True), (":a", ":q", ":b", False)]
    s = store.load_schema(spark, json.dumps({"patterns": ["* :p **"], "existentials": {"e": "?x :p ?y -> ?x :q ?z"}}))
    assert s.patterns.count() == 1 and len(s.existentials) == 1


def test_plans_have_no_products(spark):
    from tripleschema.operators import bgp, check

    g = tables.events(spark, "/root/testdata/sf0.001")
    for r in fixtures.EVENT_RULES:
        assert "CartesianProduct" not in bgp.evaluate(r.body, g)._jdf.queryExecution().toString()
    text = check.violations(g, fixtures.EVENT_EXISTENTIALS)._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoop" not in text and "CartesianProduct" not in text


def test_stream_equals_batch(spark):
    d = "/root/testdata/sf0.001"
    stream = observations.drained(observations.readings(observations.event_stream(spark, d))).select("s", "p", "o", "o_lit").distinct()
    batch = tables.events(spark, d).where("p in (':senses', ':at', ':reads')")
    assert stream.exceptAll(batch).isEmpty() and batch.exceptAll(stream).isEmpty()
    alarms = observations.new_patterns(observations.readings(observations.event_stream(spark, d)), schema.frame(spark, ["* :at *"]), fixtures.EVENT_RULES, ("a", ":senses"))
    assert alarms and "* :closed" not in {r.pattern for r in schema.rendered(alarms[-1][1]).collect()}


def test_entry(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() == 12
    assert set(entry.oracle_sql()) <= set(entry.queries())
