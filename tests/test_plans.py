"""Pruned scans, bounded joins, unfolded rules, tightness, cut-offs and streams that go on."""

import random
import re
import time
import uuid

import pytest

from tripleschema import fixtures
from tripleschema.model import TRIPLE_SCHEMA, Atom, Pattern, atoms, pattern, rule
from tripleschema.operators import bgp, check, closure, schema
from tripleschema.plans import analysis, consequence, existential, experiments, gen, metrics, witness
from tripleschema.plans.tables import local, settled, shared_dir
from tripleschema.sources import tables
from tripleschema.streaming import observations

SF = "/root/testdata/sf0.001"


def graph(spark, triples):
    return local(spark, [(t.s, t.p, *bgp.triple_of(t.o)) for t in triples], TRIPLE_SCHEMA)


def random_patterns(rng, n, free=True):
    out = []
    for _ in range(n):
        s, p, o = rng.choice(["*", "*", ":a", ":b"]), rng.choice([":p", ":q", "*" if free else ":p"]), rng.choice(["*", "**", ":a", ":b", '"1"'])
        out.append(pattern(f"{s} {p} {o}"))
    return list(dict.fromkeys(out))


def test_scans_read_what_is_asked(spark):
    plan = tables.star(spark, SF, atoms("?o a :Order, ?l :ofOrder ?o"))._jdf.queryExecution().executedPlan().toString()
    assert sorted(re.findall(r"ReadSchema: struct<(.*?)>", plan)) == ["l_orderkey:bigint,l_linenumber:int", "o_orderkey:bigint"]
    whole = tables.star(spark, SF)
    for body in (atoms("?x :within ?y"), atoms("?x a :Line"), atoms("?x ?p :Order"), atoms("?c :segment ?g, ?o :placedBy ?c")):
        wanted = tables.star(spark, SF, body)
        asked = bgp.evaluate(body, whole)
        assert sorted(map(tuple, bgp.evaluate(body, wanted).collect())) == sorted(map(tuple, asked.collect()))
    assert tables.pages(spark, SF, atoms("?x :nothing ?y")).isEmpty()
    kept = closure.stored(tables.events(spark, SF), "events")
    assert "PartitionFilters: [isnotnull(p" in kept.where("p = ':at'")._jdf.queryExecution().toString()


def test_uncovered_equals_definition(spark):
    rng = random.Random(11)
    for free in (True, False, True, True):
        a, b = random_patterns(rng, 14), random_patterns(rng, 5, free)
        found = {Pattern(*r) for r in schema.uncovered(schema.frame(spark, a), schema.frame(spark, b)).collect()}
        assert found == {p for p in a if not any(p.below(q) for q in b)}
        small = {Pattern(*r) for r in schema.minimised(schema.frame(spark, a)).collect()}
        assert small == {p for p in a if not any(p != q and p.below(q) for q in a)}


@pytest.mark.parametrize(("few", "compiled"), [(100_000, 200), (2, 200), (100_000, 0), (2, 0)])
def test_conforming_equals_definition(spark, monkeypatch, few, compiled):
    monkeypatch.setattr(check, "SMALL", few)
    monkeypatch.setattr(check, "COMPILED", compiled)
    if few == 2:
        monkeypatch.setattr(check, "bounded", lambda rows: rows)  # the bound is for the predicates alone
    rng = random.Random(13)
    triples = {Atom(rng.choice([":a", ":b", ":c"]), rng.choice([":p", ":q", ":r"]), rng.choice([":a", ":b", '"1"', '"2"'])) for _ in range(60)}
    for free in (True, False):
        patterns = random_patterns(rng, 6, free)
        g, p = graph(spark, triples), schema.frame(spark, patterns)
        ok = {t for t in triples if any(x.admits(t) for x in patterns)}
        of = lambda df: {Atom(r.s, r.p, f'"{r.o}"' if r.o_lit else r.o) for r in df.collect()}
        assert of(check.conforming(g, p)) == ok and of(check.conforming(g, p, "left_anti")) == triples - ok


def test_unfolded_rules_answer_like_the_closure(spark):
    rng = random.Random(17)
    for _ in range(60):
        base, mid, top = [":a", ":b"], [":c", ":d"], [":e"]
        two = lambda ps: f"?x {rng.choice(ps)} ?y, ?y {rng.choice(ps)} ?z"
        rules = [rule("c", f"{two(base)} => ?x :c ?z"), rule("d", f"?x {rng.choice(base)} ?y => ?y :d ?x"), rule("e", f"{two(base + mid)} => ?x :e ?z"), rule("f", f"{two(mid + top[:0])} => ?z :e ?x")]
        data = frozenset(Atom(f":{rng.randrange(4)}", rng.choice(base), rng.choice([f":{rng.randrange(4)}", '"1"'])) for _ in range(9))
        closed = witness.close(data, rules)
        found = set()
        for r in rules:
            unfolded, complete = existential.unfolded_rules(r, rules)
            assert complete
            for u in unfolded:
                for m in witness.match_all(u.body, data):
                    heads = [h.replaced(m) for h in u.head]
                    if not any(t.startswith('"') for t in (*(h.s for h in heads), *(m[v] for v in u.no_literal))):
                        found |= set(heads)
        assert found - data == closed - data


def test_predictions_are_tight(spark):
    p = schema.frame(spark, fixtures.LOAN_PATTERNS)
    found = analysis.tightness(p, fixtures.LOAN_RULES)
    assert found.complete and found.predicted.count() == 3 and found.unwitnessed.isEmpty()
    g = gen.generate(gen.Config(pi_c=0.2, n_preds=5, n_iris=2, n_lits=2, n_patterns=6, n_rules=3), 5)
    found = analysis.tightness(schema.frame(spark, g.patterns), g.rules)
    assert found.unwitnessed.isEmpty()


def test_counters_and_sweeps(spark):
    found = consequence.simple(schema.frame(spark, fixtures.LOAN_PATTERNS), fixtures.LOAN_RULES, counted=True)
    assert [c["added"] for c in found.counters] == [2, 1, 0] and all(c["mappings"] >= c["kept"] > 0 for c in found.counters)
    rows = {(r["size"], r.approach): r for r in experiments.schema_sweep_table(spark, (5,), runs=1).collect()}
    assert rows[5, "sandbox"].patterns == rows[5, "critical"].patterns and rows[5, "sandbox"].rounds == rows[5, "critical"].rounds
    assert rows[5, "critical"].mappings >= rows[5, "sandbox"].kept
    rows = experiments.existential_sweep_table(spark, (4,), runs=1, size=20).collect()
    assert [r.kind for r in rows] == ["con", "con_ex"] and rows[1].violated + rows[1].undecided <= 4


def test_cut_off_cancels(spark):
    from pyspark.sql import functions as F

    began = time.time()
    slow = lambda: [spark.range(1 << 33).selectExpr("sum(hash(id, id + 1, id + 2))").collect() for _ in range(50)]
    found = metrics.timed("slow", slow, timeout_s=2, spark=spark)
    assert found.seconds is None and time.time() - began < 60
    assert metrics.timed("fast", lambda: spark.range(3).count(), timeout_s=60, spark=spark).result == 3
    with pytest.raises(ValueError):
        metrics.timed("wrong", lambda: int("x"), spark=spark)


def test_generator_keeps_its_numbers():
    for n in (5, 20, 35):
        g = gen.generate(experiments.growing_schema(n))
        assert len(g.patterns) == n and len(g.rules) == 4
    g = gen.generate(experiments.growing_existentials(200))
    assert len(g.patterns) == 100 and len(g.existentials) == 200
    with pytest.raises(ValueError):
        gen.generate(gen.Config(pi_c=0.0, n_preds=2, n_patterns=10, n_rules=1))


def test_small_tables_settle_on_the_driver(spark):
    few, many = spark.range(5), spark.range(50)
    assert settled(few, "few", 10).collect() == few.collect() and not settled(few, "few", 10).inputFiles()
    assert settled(many, "many", 10).count() == 50 and settled(many, "many", 10).inputFiles()


# -- streams


def stream_of(spark, rows, at, parts):
    """The rows as a stream of ``parts`` files, in order."""
    for k in range(parts):
        spark.createDataFrame(rows[k::parts], "s string, p string, o string, o_lit boolean").coalesce(1).write.mode("append").parquet(at)
    return spark.readStream.schema("s string, p string, o string, o_lit boolean").option("maxFilesPerTrigger", 1).parquet(at)


def test_incremental_closure_goes_on(spark):
    at = f"{shared_dir(spark)}/turns-{uuid.uuid4().hex}"
    chain = [(f":{i}", ":next", f":{i + 1}", False) for i in range(8)]
    empty = graph(spark, [])
    first = observations.incremental_closure(stream_of(spark, chain[:4], at, 2), fixtures.AFTER_RULES, empty, f"{at}-run")
    assert first.where("p = ':after'").count() == 10
    # more files come, and the run is started again under the same place: nothing of the first run is in memory
    again = observations.incremental_closure(stream_of(spark, chain[4:], at, 2), fixtures.AFTER_RULES, empty, f"{at}-run")
    whole = closure.close(graph(spark, [Atom(*t[:3]) for t in chain]), fixtures.AFTER_RULES).graph
    assert sorted(map(tuple, again.distinct().collect())) == sorted(map(tuple, whole.collect()))


def test_late_rows_are_counted(spark):
    at = f"{shared_dir(spark)}/late-{uuid.uuid4().hex}"
    for batch in (["2024-01-01 10:00:00", "2024-01-01 12:00:00"], ["2024-01-01 11:00:00", "2024-01-01 11:55:00", "2024-01-01 13:00:00"]):
        spark.createDataFrame([(t,) for t in batch], "ts string").selectExpr("CAST(ts AS timestamp) AS ts").coalesce(1).write.mode("append").parquet(at)
        time.sleep(1.1)  # files come in the order of their times
    stream = spark.readStream.schema("ts timestamp").option("maxFilesPerTrigger", 1).parquet(at)
    assert observations.late_rows(stream) == [0, 1]
    assert observations.late_rows(stream, "2 hours") == [0, 0]


def test_missing_equals_batch(spark):
    events = spark.read.parquet(f"{SF}/events.parquet")
    want = events.where("event_type = 'purchase'").alias("a").join(events.where("event_type = 'view'").alias("b"), on=spark_expr("a.user_id = b.user_id AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 1 hour"), how="left_anti").select("event_id", "user_id")
    found = observations.missing_whole(spark, SF)
    assert sorted(map(tuple, found.collect())) == sorted(map(tuple, want.distinct().collect()))


def spark_expr(text):
    from pyspark.sql import functions as F

    return F.expr(text)


def test_empty_stream(spark):
    at = f"{shared_dir(spark)}/none-{uuid.uuid4().hex}"
    spark.createDataFrame([], TRIPLE_SCHEMA).write.parquet(at)
    stream = spark.readStream.schema(TRIPLE_SCHEMA).parquet(at)
    assert observations.drained(stream).count() == 0


def test_entry_hides_a_missing_subpackage_only():
    import __spark_entry__ as entry

    text = open(entry.__file__).read()
    assert "except ModuleNotFoundError" in text and "except ImportError" not in text
