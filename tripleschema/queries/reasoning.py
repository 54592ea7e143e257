"""Queries on schemas: canonical graphs, rewriting, consequences and existential rules."""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce
from itertools import product

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tripleschema import fixtures
from tripleschema.model import LAMBDA, Atom, Pattern, is_var, pattern, rule
from tripleschema.model import existential as existential_rule
from tripleschema.operators import check, closure, schema
from tripleschema.operators.bgp import column
from tripleschema.operators.schema import Schema
from tripleschema.plans import analysis, batch, canon, consequence, existential, experiments, gen, rewrite
from tripleschema.plans.tables import local, settled, written
from tripleschema.queries import sql
from tripleschema.queries.graphs import SENSES, closed_events, event_patterns
from tripleschema.registry import register
from tripleschema.sources import tables

K = fixtures.EVENT_RULES
SENSED = "'a', ':senses'"
PROFILE = sql.profile(sql.EVENTS, SENSED)
#: The data have an instance of everything that the rules can give, so the profile of their closure is the consequence.
AFTER = sql.profile(sql.EVENTS_CLOSED, SENSED)

STAR_CLASSES = ("a", ":status", ":priority", ":segment")
_STAR = sql.profile(sql.STAR, "'a', ':status', ':priority', ':segment'")

#: Bodies on the star graph, whose schema has constants at some objects, so that mappings bind something.
MAPPED = (
    rule("m1", "?o :placedBy ?c, ?c :segment ?g => ?o :soldTo ?g"),
    rule("m2", "?o :status ?s, ?o :total ?t => ?o :pays ?t"),
    rule("m3", "?c :segment ?g, ?c :balance ?b => ?g :holds ?b"),
)


def star_patterns(spark: SparkSession, d: str) -> DataFrame:
    return settled(schema.profile(tables.star(spark, d), STAR_CLASSES), "profile")


def rendered_sql(patterns: str) -> str:
    place = lambda x: f"CASE {x}_k WHEN 'I' THEN '*' WHEN 'A' THEN '**' ELSE {x}_v END"
    return f"SELECT {place('s')} || ' ' || {place('p')} || ' ' || {place('o')} AS pattern FROM ({patterns}) gp"


def sandbox_sql(patterns: str) -> str:
    place = lambda x: f"CASE WHEN {x}_k IN ('I', 'A') THEN '{LAMBDA}' ELSE {x}_v END AS {x}"
    return f"SELECT DISTINCT {place('s')}, {place('p')}, {place('o')} FROM ({patterns}) gs"


register("sandbox_events", lambda s, d: canon.sandbox(event_patterns(s, d)), sandbox_sql(PROFILE))


# -- the critical instance


def _pool(patterns: str, constants: Sequence[str]) -> str:
    own = " UNION ".join(f"SELECT '{c}'" for c in [*constants, LAMBDA])
    return f"SELECT s_v AS c FROM ({patterns}) a WHERE s_v IS NOT NULL UNION SELECT p_v FROM ({patterns}) b WHERE p_v IS NOT NULL UNION SELECT o_v FROM ({patterns}) c WHERE o_v IS NOT NULL UNION {own}"


def critical_sql(patterns: str, body: Sequence[Atom]) -> str:
    fits = lambda x, y: f"((t.{x}_k IN ('C', 'L') AND {y}.c = t.{x}_v) OR (t.{x}_k = 'I' AND {y}.c NOT LIKE '\"%') OR t.{x}_k = 'A')"
    return f"""WITH t AS ({patterns}), pool AS ({_pool(patterns, canon.body_constants(body))})
SELECT DISTINCT x.c AS s, y.c AS p, z.c AS o FROM t CROSS JOIN pool x CROSS JOIN pool y CROSS JOIN pool z WHERE {fits('s', 'x')} AND {fits('p', 'y')} AND {fits('o', 'z')}"""


register("critical_instance_events", lambda s, d: canon.critical_instance(event_patterns(s, d), K[1].body), critical_sql(PROFILE, K[1].body))


def critical_size_events(spark: SparkSession, d: str) -> DataFrame:
    p, bodies = event_patterns(spark, d), {r.id: r.body for r in K}
    bounds = local(spark, list(canon.critical_sizes(p, bodies).items()), "rule_id string, bound long")
    sizes = canon.critical_instances(p, bodies).groupBy("case_id").agg(F.count("*").alias("size"))
    return bounds.join(sizes, F.col("rule_id") == F.col("case_id")).select("rule_id", "bound", "size")


def _size_sql(r) -> str:
    n = f"(SELECT count(*) FROM ({_pool(PROFILE, canon.body_constants(r.body))}) q WHERE c NOT LIKE '\"%')"
    m = f"(SELECT count(*) FROM ({_pool(PROFILE, canon.body_constants(r.body))}) q)"
    of = lambda k: f"CASE {k} WHEN 'I' THEN {n} WHEN 'A' THEN {m} ELSE 1 END"
    return f"SELECT '{r.id}' AS rule_id, CAST((SELECT sum({of('s_k')} * {of('p_k')} * {of('o_k')}) FROM ({PROFILE}) g) AS BIGINT) AS bound, (SELECT count(*) FROM ({critical_sql(PROFILE, r.body)}) h) AS size"


register("critical_size_events", critical_size_events, " UNION ALL ".join(_size_sql(r) for r in K))


# -- mappings


def _joined(values: Sequence[Column]) -> Column:
    return F.concat_ws(",", *(F.coalesce(v, F.lit(LAMBDA)) for v in values))


def eightfold_mappings(spark: SparkSession, d: str) -> DataFrame:
    box = settled(canon.sandbox(star_patterns(spark, d)), "sandbox")
    return reduce(DataFrame.unionByName, (rewrite.eightfold(r.body, box).select(F.lit(r.id).alias("rule_id"), _joined([F.col(column(v)) for v in r.variables()]).alias("mapping")) for r in MAPPED))


def named_mappings(mappings: DataFrame) -> DataFrame:
    return mappings.select(F.col("case_id").alias("rule_id"), F.array_join("b", ",", LAMBDA).alias("mapping"), *(c for c in mappings.columns if c not in ("case_id", "b")))


def fused_mappings(spark: SparkSession, d: str) -> DataFrame:
    return named_mappings(batch.evaluate(batch.cases(spark, MAPPED), canon.sandbox(star_patterns(spark, d), None)))


def filtered_mappings(spark: SparkSession, d: str) -> DataFrame:
    p = star_patterns(spark, d)
    c = batch.cases(spark, MAPPED)
    kept = batch.filtered(c, batch.evaluate(c, canon.sandbox(p, None)), p)
    names = local(spark, [(r.id, r.variables()) for r in MAPPED], "id string, names array<string>")
    kept = named_mappings(kept).join(names, F.col("rule_id") == F.col("id"))
    return kept.select("rule_id", "mapping", F.array_join(F.array_sort(F.transform("firm", lambda i: F.get("names", i))), ",").alias("firm"))


def _eightfold_sql(r) -> str:
    """Per atom a union over which places are the fresh IRI, unbound variables null; joined on equal or null."""
    parts, bound, joins = [], {}, []
    for k, a in enumerate(r.body):
        own = a.variables()
        branches = []
        for mask in product((0, 1), repeat=3):
            where, values = [], dict.fromkeys(own, "CAST(NULL AS VARCHAR)")
            for off, place, t in zip(mask, "spo", a, strict=True):
                if off:
                    where.append(f"{place} = '{LAMBDA}'")
                elif is_var(t):
                    values[t] = place
                else:
                    where.append(f"{place} = '{t}'")
            branches.append(f"SELECT {', '.join(f'{v} AS {n[1:]}' for n, v in values.items())} FROM box{' WHERE ' + ' AND '.join(where) if where else ''}")
        parts.append(f"a{k} AS ({' UNION '.join(branches)})")
        for v in own:
            joins += [f"(a{j}.{v[1:]} IS NULL OR a{k}.{v[1:]} IS NULL OR a{j}.{v[1:]} = a{k}.{v[1:]})" for j in bound.get(v, [])]
            bound.setdefault(v, []).append(k)
    value = {v: f"coalesce({', '.join(f'a{k}.{v[1:]}' for k in ks)}, NULL)" for v, ks in bound.items()}
    names = r.variables()
    whole = " AND ".join([*joins, *(f"{value[v]} IS NOT NULL" for v in names)])
    return f"(WITH box AS ({sandbox_sql(_STAR)}), {', '.join(parts)} SELECT DISTINCT '{r.id}' AS rule_id, {' || chr(44) || '.join(value[v] for v in names)} AS mapping FROM {', '.join(f'a{k}' for k in range(len(r.body)))} WHERE {whole})"


def _fused_sql(r) -> str:
    """One choice of a sandbox triple per atom; a variable is the only constant among its places, or the fresh IRI."""
    where, places = [], {}
    for k, a in enumerate(r.body):
        for place, t in zip("spo", a, strict=True):
            if is_var(t):
                places.setdefault(t, []).append(f"b{k}.{place}")
            else:
                where.append(f"b{k}.{place} IN ('{t}', '{LAMBDA}')")
    of = {v: f"list_distinct(list_filter([{', '.join(ps)}], lambda x: x <> '{LAMBDA}'))" for v, ps in places.items()}
    where += [f"len({x}) <= 1" for x in of.values()]
    return f"(WITH box AS ({sandbox_sql(_STAR)}) SELECT DISTINCT '{r.id}' AS rule_id, {' || chr(44) || '.join(f'''coalesce({of[v]}[1], '{LAMBDA}')''' for v in r.variables())} AS mapping FROM {', '.join(f'box b{k}' for k in range(len(r.body)))} WHERE {' AND '.join(where)})"


register("eightfold_mappings_events", eightfold_mappings, " UNION ALL ".join(map(_eightfold_sql, MAPPED)))
register("fused_mappings_events", fused_mappings, " UNION ALL ".join(map(_fused_sql, MAPPED)))
register(
    "filtered_mappings_events",
    filtered_mappings,
    f"""WITH f AS ({_STAR}), has AS (SELECT DISTINCT p_v FROM f) SELECT 'm1' AS rule_id, '{LAMBDA},{LAMBDA},' || o_v AS mapping, '?c,?o' AS firm FROM f WHERE p_v = ':segment' AND EXISTS (SELECT 1 FROM has WHERE p_v = ':placedBy')
UNION ALL SELECT 'm2', '{LAMBDA},' || f.o_v || ',{LAMBDA}', CASE WHEN t.o_k = 'A' THEN '?o' ELSE '?o,?t' END FROM f JOIN f t ON t.p_v = ':total' WHERE f.p_v = ':status'
UNION ALL SELECT 'm3', '{LAMBDA},' || f.o_v || ',{LAMBDA}', CASE WHEN t.o_k = 'A' THEN '?c,?g' ELSE '?b,?c,?g' END FROM f JOIN f t ON t.p_v = ':balance' WHERE f.p_v = ':segment'""",
)


# -- consequences


def basic(approach: str):
    def query(spark: SparkSession, d: str) -> DataFrame:
        p = event_patterns(spark, d)
        return reduce(DataFrame.unionByName, (schema.rendered(schema.minimised(consequence.basic(p, r, approach))).select(F.lit(r.id).alias("rule_id"), "pattern") for r in K))

    return query


_GIVES = {"k1": "p = ':foundIn' OR o = ':BadgeTag'", "k2": "o = ':ClosedArea'", "k3": "false"}  # on the graph itself nothing intrudes yet
_BASIC = " UNION ALL ".join(f"SELECT '{k}' AS rule_id, pattern FROM ({rendered_sql(sql.profile(f'WITH {sql.EVENT_FACTS} {sql.EVENTS} UNION SELECT * FROM derived WHERE {w}', SENSED))}) b{k}" for k, w in _GIVES.items())
register("basic_consequence_sandbox_events", basic("sandbox"), _BASIC)
register("basic_consequence_critical_events", basic("critical"), _BASIC)

_EVENTS_AFTER = rendered_sql(AFTER)
register("simple_consequence_events", lambda s, d: schema.rendered(consequence.simple(event_patterns(s, d), K).patterns), _EVENTS_AFTER)
register("simple_consequence_critical_events", lambda s, d: schema.rendered(consequence.simple(event_patterns(s, d), K, "critical").patterns), _EVENTS_AFTER)

register("simple_consequence_star", lambda s, d: schema.rendered(consequence.simple(star_patterns(s, d), fixtures.STAR_RULES).patterns), rendered_sql(sql.profile(f"{sql.STAR} UNION ({sql.STAR_ADDED})", "'a', ':status', ':priority', ':segment'")))
register("simple_consequence_after", lambda s, d: schema.rendered(consequence.simple(settled(schema.profile(tables.conversations(s, d)), "profile"), fixtures.AFTER_RULES).patterns), rendered_sql(sql.profile(f"{sql.CONVERSATIONS} UNION ({sql.AFTER_ADDED})", "'a'")))


def equivalence(spark: SparkSession, d: str) -> DataFrame:
    """The patterns of both approaches, and whether the other one covers each."""
    p = event_patterns(spark, d)
    found = {a: consequence.simple(p, K, a).patterns for a in ("sandbox", "critical")}
    out = []
    for a, other in (("sandbox", "critical"), ("critical", "sandbox")):
        outside = settled(schema.rendered(schema.uncovered(found[a], found[other])), "outside")
        every = schema.rendered(found[a])
        out.append(every.select(F.lit(a).alias("approach"), "pattern").join(outside.withColumn("only", F.lit(True)), "pattern", "left").select("approach", "pattern", F.col("only").isNull().alias("covered")))
    return reduce(DataFrame.unionByName, out)


register("equivalence_events", equivalence, " UNION ALL ".join(f"SELECT '{a}' AS approach, pattern, true AS covered FROM ({_EVENTS_AFTER}) e{a}" for a in ("sandbox", "critical")))


def covered_closure(spark: SparkSession, d: str) -> DataFrame:
    """By predicate, the triples of the closed graph and those that the predicted patterns do not admit."""
    closed, p = closed_events(spark, d), consequence.simple(event_patterns(spark, d), K).patterns
    outside = check.conforming(closed, p, "left_anti").groupBy("p").agg(F.count("*").alias("n"))
    return closed.groupBy("p").agg(F.count("*").alias("triples")).join(outside, "p", "left").select("p", "triples", F.coalesce("n", F.lit(0)).alias("uncovered"))


_ADMITS = "f.p_v = c.p AND (f.o_k = 'A' OR (f.o_k = 'I' AND NOT c.o_lit) OR (f.o_k = 'C' AND NOT c.o_lit AND f.o_v = c.o))"
register("covered_closure_events", covered_closure, f"WITH c AS ({sql.EVENTS_CLOSED}), f AS ({AFTER}) SELECT p, count(*) AS triples, count(*) FILTER (WHERE NOT EXISTS (SELECT 1 FROM f WHERE {_ADMITS})) AS uncovered FROM c GROUP BY p")


def tight(spark: SparkSession, d: str) -> DataFrame:
    """The predicted patterns, and whether a witness graph within the original schema gives a triple of each."""
    found = analysis.tightness(event_patterns(spark, d), K)
    without = schema.rendered(found.unwitnessed).withColumn("no", F.lit(True))
    return schema.rendered(found.predicted).join(without, "pattern", "left").select("pattern", F.col("no").isNull().alias("witnessed"))


register("tight_consequence_events", tight, f"SELECT pattern, true AS witnessed FROM ({_EVENTS_AFTER} EXCEPT {rendered_sql(PROFILE)}) t")


# -- questions


_HAS = lambda kind: f"EXISTS (SELECT 1 FROM events WHERE event_type = '{kind}')"
register("applicable_rules_events", lambda s, d: analysis.applicable(event_patterns(s, d), K), f"SELECT 'k1' AS rule_id WHERE {_HAS('purchase')} UNION SELECT 'k2' WHERE {_HAS('error')} UNION SELECT 'k3' WHERE {_HAS('purchase')} AND {_HAS('error')}")
register("applicability_diff_events", lambda s, d: analysis.applicability_diff(event_patterns(s, d), event_patterns(s, d).where("o_v IS NULL OR o_v <> 'prop:error'"), K), f"SELECT 'k2' AS rule_id, 'lost' AS change WHERE {_HAS('error')} UNION ALL SELECT 'k3', 'lost' WHERE {_HAS('purchase')} AND {_HAS('error')}")


def can_derive(spark: SparkSession, d: str) -> DataFrame:
    p = event_patterns(spark, d)
    wanted = ("* :intrudes *", "* a :ClosedArea", "* :foundIn place:1", "* :heldBy **")
    return reduce(DataFrame.unionByName, (analysis.can_derive(p, K, pattern(w)).select(F.lit(w).alias("wanted"), "rule_id") for w in wanted))


register("can_derive_events", can_derive, f"WITH {sql.EVENT_FACTS} SELECT DISTINCT w.wanted, w.rule_id FROM (VALUES ('* :intrudes *', 'k3', ':intrudes', NULL), ('* a :ClosedArea', 'k2', 'a', ':ClosedArea'), ('* :foundIn place:1', 'k1', ':foundIn', NULL), ('* :heldBy **', 'k1', ':heldBy', NULL)) w(wanted, rule_id, p, o) JOIN derived d ON d.p = w.p AND (w.o IS NULL OR d.o = w.o)")

ALL_RULES = (*K, *fixtures.STAR_RULES, *fixtures.DOC_RULES, *fixtures.DOC_RULES_LOSING)


def trigger_pairs(spark: SparkSession, d: str) -> DataFrame:
    """Which heads trigger the existential rules of all fixtures, and rules on each pattern of the evolved events graph."""
    evolved = consequence.simple(event_patterns(spark, d), K).patterns.collect()  # a row for each pattern of a schema
    on_patterns = [existential_rule(str(Pattern(r.s_k, r.s_v, r.p_k, r.p_v, r.o_k, r.o_v)), f"?x {r.p_v} {r.o_v or '?y'} -> ?x :at ?z") for r in evolved]
    return local(spark, [(e.id, r.id, h) for e in (*fixtures.ALL_EXISTENTIALS, *on_patterns) for r in ALL_RULES for h in existential.triggers(e, r)], "e_id string, rule_id string, head int")


_CONST = lambda t: None if is_var(t) else t
_ANTECEDENTS = sql.atoms_table([(e.id, _CONST(e.a.s), e.a.p, _CONST(e.a.o)) for e in fixtures.ALL_EXISTENTIALS])
_ON_PATTERNS = f"SELECT '* ' || p_v || ' ' || CASE o_k WHEN 'I' THEN '*' WHEN 'A' THEN '**' ELSE o_v END, CAST(NULL AS VARCHAR), p_v, o_v FROM ({AFTER}) gp"
_HEADS = sql.atoms_table([(r.id, i, _CONST(h.s), h.p, _CONST(h.o)) for r in ALL_RULES for i, h in enumerate(r.head)])
register("trigger_pairs_events", trigger_pairs, f"SELECT e_id, rule_id, CAST(head AS INTEGER) AS head FROM ({_ANTECEDENTS} UNION ALL {_ON_PATTERNS}) a(e_id, s, p, o) JOIN ({_HEADS}) h(rule_id, head, hs, hp, ho) ON a.p = h.hp AND (a.s IS NULL OR h.hs IS NULL OR a.s = h.hs) AND (a.o IS NULL OR h.ho IS NULL OR a.o = h.ho)")


def rewritten_answers(spark: SparkSession, d: str) -> DataFrame:
    """What the rules give on the closure, by evaluating their minimal unfolded bodies on the graph as it is."""
    rows = []
    for r in K:
        for u in existential.unfolded_rules(r, K)[0]:
            rows.append(closure.apply(u, tables.events(spark, d, u.body)).select(F.lit(r.id).alias("rule_id"), "s", "p", "o"))
    return reduce(DataFrame.unionByName, rows).distinct()


register("rewritings_events", rewritten_answers, f"WITH {sql.EVENT_FACTS} SELECT CASE WHEN p = ':intrudes' THEN 'k3' WHEN o = ':ClosedArea' THEN 'k2' ELSE 'k1' END AS rule_id, s, p, o FROM derived")


# -- existential rules


#: A tag that the rules type although nobody holds it.
_UNHELD = f"EXISTS (WITH {sql.EVENT_FACTS} SELECT 1 FROM found WHERE t NOT IN (SELECT 'tag:' || s_suppkey FROM supplier WHERE s_acctbal > 0))"
_OUTSIDE = f"EXISTS (WITH {sql.EVENT_FACTS}, f AS ({PROFILE}) SELECT 1 FROM derived c WHERE NOT EXISTS (SELECT 1 FROM f WHERE {_ADMITS}))"


def event_schema(spark: SparkSession, d: str) -> Schema:
    return Schema(event_patterns(spark, d), fixtures.EVENT_EXISTENTIALS)


register("witnesses_events", lambda s, d: existential.tested(event_schema(s, d), K).rows.select("e_id", "witness_id", "violates", "witness"))
register("violation_report_events", lambda s, d: existential.explained(event_schema(s, d), K).select("e_id", "rule_id", "body"), f"SELECT 'holder' AS e_id, 'k1' AS rule_id, '?n0 :at ?n1 , ?n0 :reads ?n2 , ?n0 :senses prop:purchase' AS body WHERE {_UNHELD}")


def verdicts(make, rules):
    def query(spark: SparkSession, d: str) -> DataFrame:
        sch = make(spark, d)
        kept = {e.id for e in existential.retained(sch, rules).retained}
        return local(spark, [(e.id, e.id in kept) for e in sch.existentials], "e_id string, retained boolean")

    return query


def doc_schema(spark: SparkSession, d: str) -> Schema:
    return Schema(settled(schema.profile(tables.documents(spark, d), ("a", ":lang")), "profile"), fixtures.DOC_EXISTENTIALS)


register("retained_existentials_events", verdicts(event_schema, K), f"SELECT 'holder' AS e_id, NOT {_UNHELD} AS retained")
register("retained_existentials_star", verdicts(lambda s, d: Schema(star_patterns(s, d), fixtures.STAR_EXISTENTIALS), fixtures.STAR_RULES), f"""WITH added AS ({sql.STAR_ADDED}) SELECT e_id, NOT EXISTS (SELECT 1 FROM added WHERE p = 'a' AND o = class) AS retained FROM (VALUES ('order_line', ':Order'), ('order_customer', ':Order'), ('nation_supplier', ':Nation')) v(e_id, class)
UNION ALL SELECT 'sold_region', NOT EXISTS (SELECT 1 FROM added WHERE p = ':soldIn' AND o NOT IN (SELECT 'reg:' || r_regionkey FROM region))""")
register("retained_existentials_docs", verdicts(doc_schema, fixtures.DOC_RULES), "SELECT 'doc_label' AS e_id, NOT EXISTS (SELECT 1 FROM labels l WHERE quality IS NULL AND doc_id IN (SELECT doc_id FROM labels WHERE quality IS NOT NULL)) AS retained")
register("lost_existentials_docs", verdicts(doc_schema, fixtures.DOC_RULES_LOSING), "SELECT 'doc_label' AS e_id, NOT EXISTS (SELECT 1 FROM documents d WHERE source IS NOT NULL AND NOT EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id AND quality IS NOT NULL)) AS retained")


def preserving(spark: SparkSession, d: str) -> DataFrame:
    out = consequence.existential_preserving(event_schema(spark, d), K)
    rules = local(spark, [("existential", str(e)) for e in out.existentials], "kind string, text string")
    return schema.rendered(out.patterns).select(F.lit("pattern").alias("kind"), F.col("pattern").alias("text")).unionByName(rules)


register("preserving_consequence_events", preserving, f"SELECT 'pattern' AS kind, pattern AS text FROM ({_EVENTS_AFTER}) g")


def rejected(spark: SparkSession, d: str) -> DataFrame:
    return local(spark, list(analysis.with_policy(event_schema(spark, d), K, "reject_rules").rejected.items()), "rule_id string, reason string")


register("rejected_rules_events", rejected, f"SELECT * FROM (SELECT rule_id, concat_ws('; ', CASE WHEN EXISTS (SELECT 1 FROM ({_EVENTS_AFTER} EXCEPT {rendered_sql(PROFILE)}) n WHERE list_contains(gives, pattern)) THEN 'adds a pattern' END, CASE WHEN rule_id = 'k1' AND {_UNHELD} THEN 'breaks holder' END) AS reason FROM (VALUES ('k1', ['* :foundIn *', '* a :BadgeTag']), ('k2', ['* a :ClosedArea']), ('k3', ['* :intrudes *'])) v(rule_id, gives)) r WHERE reason <> ''")


# -- the generator on table rows

GEN = gen.Config(n_preds=150, n_iris=100, n_lits=100, n_patterns=100)
_DRAWS = "SELECT row_number() OVER (ORDER BY l_orderkey, l_linenumber, l_partkey, l_suppkey) - 1 AS i, l_orderkey * 7919 + l_partkey * 104729 + l_suppkey * 1299709 + l_linenumber * 15485863 AS x FROM lineitem"
register("gen_patterns_lineitem", lambda s, d: gen.pattern_rows(gen.draws(tables.table(s, d, "lineitem"), 1000), GEN), f"""
SELECT i, CASE WHEN x // 3 % 100 < 10 THEN 'C' ELSE 'I' END AS s_k, CASE WHEN x // 3 % 100 < 10 THEN 'cust:' || (x // 5 % 100) END AS s_v, 'C' AS p_k, 'm' || (x % 150) AS p_v,
  CASE WHEN x // 7 % 100 < 10 THEN CASE WHEN x // 11 % 2 = 0 THEN 'C' ELSE 'L' END ELSE 'A' END AS o_k,
  CASE WHEN x // 7 % 100 < 10 THEN CASE WHEN x // 11 % 2 = 0 THEN 'cust:' || (x // 13 % 100) ELSE '"x' || (x // 13 % 100) || '"' END END AS o_v FROM ({_DRAWS}) g WHERE i < 1000""")


def gen_rules(spark: SparkSession, d: str) -> DataFrame:
    rows = [r.x for r in gen.draws(tables.table(spark, d, "lineitem"), 300).orderBy("i").collect()]
    return gen.rule_rows(spark, tuple(gen.chain(f"r{j}", [f"m{x % GEN.n_preds}" for x in rows[3 * j : 3 * j + 3]]) for j in range(100)))


register("gen_rules_lineitem", gen_rules, f"SELECT 'r' || (i // 3) AS rule_id, '?v0 m' || max(CASE WHEN i % 3 = 0 THEN x % 150 END) || ' ?v1 , ?v1 m' || max(CASE WHEN i % 3 = 1 THEN x % 150 END) || ' ?v2 => ?v0 m' || max(CASE WHEN i % 3 = 2 THEN x % 150 END) || ' ?v2' AS rule FROM ({_DRAWS}) g WHERE i < 300 GROUP BY i // 3")


# -- shapes, schema properties and the instance test

def shapes_to_schema(spark: SparkSession, d: str) -> DataFrame:
    """The shapes of the events graph, which list the values that its rows have, as a schema."""
    from tripleschema.functions import shapes

    s = shapes.to_schema(spark, shapes.from_schema(event_patterns(spark, d), fixtures.EVENT_EXISTENTIALS))
    rules = local(spark, [("existential", str(e)) for e in s.existentials], "kind string, text string")
    return schema.rendered(s.patterns).select(F.lit("pattern").alias("kind"), F.col("pattern").alias("text")).unionByName(rules)


def shapes_from_consequence(spark: SparkSession, d: str) -> DataFrame:
    """The evolved schema as shapes: what a predicate's objects may be."""
    from tripleschema.functions import shapes

    out = consequence.existential_preserving(event_schema(spark, d), K)
    rows = [(s["target_objects_of"], ",".join(s.get("in", [s.get("node_kind", "")]))) for s in shapes.from_schema(out.patterns) if "target_objects_of" in s]
    return local(spark, rows, "predicate string, objects string")


register("shapes_to_schema", shapes_to_schema, f"SELECT 'pattern' AS kind, pattern AS text FROM ({rendered_sql(PROFILE)}) t UNION ALL SELECT 'existential', '?x a :BadgeTag -> ?x :heldBy ?y'")
register(
    "shapes_from_consequence",
    shapes_from_consequence,
    "SELECT ':senses' AS predicate, (SELECT string_agg(DISTINCT 'prop:' || event_type, ',' ORDER BY 'prop:' || event_type) FROM events) AS objects UNION ALL SELECT * FROM (VALUES (':at', 'IRI'), (':reads', 'IRIOrLiteral'), (':heldBy', 'IRI'), (':foundIn', 'IRI'), (':intrudes', 'IRI'), ('a', ':BadgeTag,:ClosedArea')) v(predicate, objects)",
)
register("vocabulary_events", lambda s, d: event_schema(s, d).vocabulary(), f"SELECT DISTINCT p FROM ({sql.EVENTS}) g")


def instance_test(spark: SparkSession, d: str) -> DataFrame:
    """Whether the graph is an instance of its schema, before and after closure."""
    p = event_patterns(spark, d)
    before = check.is_instance(tables.events(spark, d), p, fixtures.EVENT_EXISTENTIALS).ok
    after = check.is_instance(closed_events(spark, d), p, fixtures.EVENT_EXISTENTIALS).ok
    return local(spark, [("before", before), ("after", after)], "graph string, instance boolean")


register("instance_test_events", instance_test, f"SELECT 'before' AS graph, NOT EXISTS (SELECT 1 FROM ({sql.EVENTS}) t WHERE p = 'a' AND o = ':BadgeTag' AND s NOT IN (SELECT s FROM ({sql.EVENTS}) h WHERE p = ':heldBy')) AS instance UNION ALL SELECT 'after', NOT {_UNHELD} AND NOT {_OUTSIDE}")


def ucq_mappings(spark: SparkSession, d: str) -> DataFrame:
    """The rewritten two-atom body as a union of 64 conjunctive queries."""
    body = MAPPED[0].body
    return rewrite.evaluate_ucq(body, settled(canon.sandbox(star_patterns(spark, d)), "sandbox"), predicate_vars=False).select(F.concat_ws(",", "v_o", "v_c", "v_g").alias("mapping"))


register("ucq_mappings_events", ucq_mappings, f"WITH f AS ({_STAR}) SELECT '{LAMBDA},{LAMBDA},' || o_v AS mapping FROM f WHERE p_v = ':segment' AND EXISTS (SELECT 1 FROM f WHERE p_v = ':placedBy')")


ACYCLIC_SETS, ACYCLIC_RULES, ACYCLIC_PREDS = 100, 4, 6  # sets of rules that are drawn from lineitem, rules in each, predicates
_NAMED_SETS = {"star": fixtures.STAR_EXISTENTIALS, "endless": (existential_rule("e", "?x :p ?y -> ?y :p ?z"),)}


def acyclicity(spark: SparkSession, d: str) -> DataFrame:
    """Weak acyclicity of sets of existential rules, one for each draw from the table, and of two named sets."""
    from tripleschema.model import weak_acyclicity

    n, c = ACYCLIC_RULES, ACYCLIC_PREDS
    rows = [r.x for r in gen.draws(tables.table(spark, d, "lineitem"), n * ACYCLIC_SETS).orderBy("i").collect()]
    drawn = [existential_rule(f"e{i}", f"?x m{x % c} ?y -> ?y m{x // c % c} ?z") for i, x in enumerate(rows)]
    sets = _NAMED_SETS | {f"s{i // n}": drawn[i : i + n] for i in range(0, len(drawn), n)}
    return local(spark, [(k, weak_acyclicity(v)[0]) for k, v in sets.items()], "rules string, weakly_acyclic boolean")


def _acyclicity_sql() -> str:
    """Positions reached from each other by plain edges; a cycle through an edge that invents a value is the fault."""
    n, c = ACYCLIC_RULES, ACYCLIC_PREDS
    terms = [(k, f"{k}/{e.id}", side, i, a.p, t) for k, es in _NAMED_SETS.items() for e in es for side, a in (("a", e.a), ("c", e.c)) for i, t in enumerate(a) if is_var(t)]
    drawn = f"SELECT 's' || (g.i // {n}), 's' || (g.i // {n}) || '/e' || g.i, side, v.i, CASE side WHEN 'a' THEN 'm' || (x % {c}) ELSE 'm' || (x // {c} % {c}) END, v FROM ({_DRAWS}) g, (VALUES ('a', 0, '?x'), ('a', 2, '?y'), ('c', 0, '?y'), ('c', 2, '?z')) v(side, i, v) WHERE g.i < {n * ACYCLIC_SETS}"
    return f"""WITH RECURSIVE t(k, e, side, i, p, v) AS ({sql.atoms_table(terms)} UNION ALL {drawn}),
front AS (SELECT a.k, a.e, a.p || ' ' || a.i AS f, a.v FROM t a WHERE a.side = 'a' AND EXISTS (SELECT 1 FROM t c WHERE c.e = a.e AND c.side = 'c' AND c.v = a.v)),
plain AS (SELECT DISTINCT f.k, f.f, c.p || ' ' || c.i AS g FROM front f JOIN t c ON c.e = f.e AND c.side = 'c' WHERE c.v = f.v OR NOT EXISTS (SELECT 1 FROM t x WHERE x.e = f.e AND x.side = 'a' AND x.v = c.v)),
invents AS (SELECT DISTINCT f.k, f.f, c.p || ' ' || c.i AS g FROM front f JOIN t c ON c.e = f.e AND c.side = 'c' AND NOT EXISTS (SELECT 1 FROM t x WHERE x.e = f.e AND x.side = 'a' AND x.v = c.v)),
reach(k, f, g) AS (SELECT k, g, g FROM invents UNION SELECT r.k, r.f, p.g FROM reach r JOIN plain p ON p.k = r.k AND p.f = r.g)
SELECT k AS rules, NOT EXISTS (SELECT 1 FROM invents i JOIN reach r ON r.k = i.k AND r.f = i.g AND r.g = i.f WHERE i.k = s.k) AS weakly_acyclic FROM (SELECT DISTINCT k FROM t) s"""


register("weak_acyclicity", acyclicity, _acyclicity_sql())


# -- the published experiments, and the link and conversation graphs

register("exp_schema_sweep", lambda s, d: experiments.schema_sweep_table(s))
SWEEP_DRAWS = 5_000  # integers that the second sweep draws from lineitem, in turn and again when they are used up


def existential_sweep(spark: SparkSession, d: str) -> DataFrame:
    """Schemas and rules are generated from the rows of the table."""
    rows = gen.draws(tables.table(spark, d, "lineitem"), SWEEP_DRAWS).orderBy("i").collect()
    return experiments.existential_sweep_table(spark, drawn=[r.x for r in rows])


register("exp_existential_sweep", existential_sweep)


def page_patterns(spark: SparkSession, d: str) -> DataFrame:
    return settled(schema.profile(tables.pages(spark, d)), "profile")


register(
    "simple_consequence_links",
    lambda s, d: schema.rendered(consequence.simple(page_patterns(s, d), fixtures.LINK_RULES).patterns),
    rendered_sql(sql.profile(f"{sql.PAGES} UNION ({sql.LINKS_ADDED})", "'a'")),
)
register(
    "retained_existentials_links",
    verdicts(lambda s, d: Schema(page_patterns(s, d), fixtures.LINK_EXISTENTIALS), fixtures.LINK_RULES),
    f"WITH c AS ({sql.PAGES} UNION ({sql.LINKS_ADDED})) SELECT 'cited_by' AS e_id, NOT EXISTS (SELECT 1 FROM c a WHERE p = ':cites' AND NOT EXISTS (SELECT 1 FROM c b WHERE b.p = ':linksTo' AND b.o = a.o)) AS retained UNION ALL SELECT 'cites_host', NOT EXISTS (SELECT 1 FROM c a WHERE p = ':cites' AND NOT EXISTS (SELECT 1 FROM c b WHERE b.p = ':host' AND b.s = a.s))",
)
