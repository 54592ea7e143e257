"""Queries on data: graphs of the tables, profiles, conformance, violations, rule application and closure."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tripleschema import fixtures
from tripleschema.model import Existential, Rule, atoms, existential
from tripleschema.operators import check, closure, schema
from tripleschema.plans.tables import settled
from tripleschema.queries import sql
from tripleschema.registry import register
from tripleschema.sources import tables

SENSES = ("a", ":senses")


def graph(name: str):
    return lambda spark, d: tables.GRAPHS[name](spark, d)


for _name in tables.GRAPHS:
    register(f"graph_{_name}", graph(_name), sql.GRAPHS[_name])


# -- profiles


def event_patterns(spark: SparkSession, d: str) -> DataFrame:
    return settled(schema.profile(tables.events(spark, d), SENSES), "profile")


register("schema_profile_events", lambda s, d: schema.profile(tables.events(s, d), SENSES), sql.profile(sql.EVENTS, "'a', ':senses'"))
register("schema_profile_star", lambda s, d: schema.profile(tables.star(s, d), ("a", ":status", ":priority", ":segment")), sql.profile(sql.STAR, "'a', ':status', ':priority', ':segment'"))
register("schema_profile_docs", lambda s, d: schema.profile(tables.documents(s, d), ("a", ":lang")), sql.profile(sql.DOCUMENTS, "'a', ':lang'"))


# -- violations, straight from the tables in SQL


def violated(name: str, e: Existential):
    return lambda s, d: check.violations(tables.GRAPHS[name](s, d, [e.a, e.c]), [e])


register("exist_violations_order_line", violated("star", fixtures.STAR_EXISTENTIALS[0]), "SELECT 'order_line' AS e_id, 'ord:' || o_orderkey AS s, 'a' AS p, ':Order' AS o, false AS o_lit FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
register("exist_violations_nation_supplier", violated("star", fixtures.STAR_EXISTENTIALS[2]), "SELECT 'nation_supplier' AS e_id, 'nat:' || n_nationkey AS s, 'a' AS p, ':Nation' AS o, false AS o_lit FROM nation WHERE NOT EXISTS (SELECT 1 FROM supplier WHERE s_nationkey = n_nationkey)")
register("exist_violations_doc_label", violated("documents", fixtures.DOC_EXISTENTIALS[0]), "SELECT 'doc_label' AS e_id, 'doc:' || d.doc_id AS s, 'a' AS p, ':Document' AS o, false AS o_lit FROM documents d WHERE NOT EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)")
register(
    "exist_violations_tag_holder",
    lambda s, d: check.violations(closed_events(s, d), fixtures.EVENT_EXISTENTIALS),
    "SELECT DISTINCT 'holder' AS e_id, 'tag:' || k AS s, 'a' AS p, ':BadgeTag' AS o, false AS o_lit FROM (SELECT json_extract_string(props, '$.k') AS k FROM events WHERE event_type = 'purchase') WHERE NOT EXISTS (SELECT 1 FROM supplier WHERE CAST(s_suppkey AS VARCHAR) = k AND s_acctbal > 0)",
)


# -- rules and closures


def applied(rule: Rule):
    return lambda s, d: closure.apply(rule, tables.events(s, d, rule.body))


register("rule_apply_tag", applied(fixtures.EVENT_RULES[0]), f"WITH {sql.EVENT_FACTS} SELECT * FROM derived WHERE o = ':BadgeTag' OR p = ':foundIn'")
register("rule_apply_hazard", applied(fixtures.EVENT_RULES[1]), f"WITH {sql.EVENT_FACTS} SELECT * FROM derived WHERE o = ':ClosedArea'")


def closed_events(spark: SparkSession, d: str) -> DataFrame:
    return closure.close(tables.events(spark, d), fixtures.EVENT_RULES).graph


def closed(name: str, rules, predicate: str, mode: str = "seminaive"):
    def query(spark: SparkSession, d: str) -> DataFrame:
        needed = [a for r in rules if predicate in closure.fed_by(r, rules) for a in r.body]
        return closure.close(tables.GRAPHS[name](spark, d, needed), [r for r in rules if predicate in closure.fed_by(r, rules)], mode).graph.where(F.col("p") == predicate)

    return query


register("closure_events", closed_events, f"WITH {sql.EVENT_FACTS} {sql.EVENTS} UNION SELECT * FROM derived")
register("closure_events_naive", lambda s, d: closure.close(tables.events(s, d), fixtures.EVENT_RULES, "naive").graph, f"WITH {sql.EVENT_FACTS} {sql.EVENTS} UNION SELECT * FROM derived")
register("closure_within", closed("star", fixtures.STAR_RULES[3:], ":within"), f"WITH RECURSIVE g AS ({sql.STAR}), w(s, o) AS (SELECT s, o FROM g WHERE p = ':within' UNION SELECT w.s, g.o FROM w JOIN g ON g.s = w.o AND g.p = ':within') SELECT s, ':within' AS p, o, false AS o_lit FROM w")
register(
    "closure_after",
    closed("conversations", fixtures.AFTER_RULES, ":after"),
    "SELECT DISTINCT 'turn:' || a.conv_id || '_' || a.turn AS s, ':after' AS p, 'turn:' || b.conv_id || '_' || b.turn AS o, false AS o_lit FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND a.turn < b.turn",
)
register(
    "closure_star",
    closed("star", fixtures.STAR_RULES, ":soldIn"),
    "SELECT DISTINCT 'ord:' || o_orderkey AS s, ':soldIn' AS p, x.o, false AS o_lit FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON n_nationkey = c_nationkey, LATERAL (SELECT unnest(['nat:' || n_nationkey, 'reg:' || n_regionkey]) AS o) x",
)


# -- conformance


def conformance(name: str, how: str):
    def query(spark: SparkSession, d: str) -> DataFrame:
        return check.conforming(closed_events(spark, d), event_patterns(spark, d), how)

    return query


_OUTSIDE = f"WITH {sql.EVENT_FACTS} SELECT * FROM derived WHERE p IN (':foundIn', ':intrudes') OR o = ':ClosedArea'"
register("conform_offenders_events", conformance("events", "left_anti"), _OUTSIDE)
register("conform_ok_events", conformance("events", "left_semi"), f"WITH {sql.EVENT_FACTS} SELECT * FROM ({sql.EVENTS} UNION SELECT * FROM derived) EXCEPT SELECT * FROM derived WHERE p IN (':foundIn', ':intrudes') OR o = ':ClosedArea'")
_HAND = ("* a :Document", "* :lang lang:en", "* :source *", '* :quality "1"', "* :toxic **")
register("conform_offenders_docs", lambda s, d: check.conforming(tables.documents(s, d), schema.frame(s, _HAND), "left_anti"), f"SELECT * FROM ({sql.DOCUMENTS}) WHERE p = ':chars' OR (p = ':lang' AND o <> 'lang:en') OR (p = ':quality' AND o <> '1')")
register("conform_ok_docs", lambda s, d: check.conforming(tables.documents(s, d), schema.frame(s, _HAND)), f"SELECT * FROM ({sql.DOCUMENTS}) WHERE NOT (p = ':chars' OR (p = ':lang' AND o <> 'lang:en') OR (p = ':quality' AND o <> '1'))")
register("closure_links", closed("pages", fixtures.LINK_RULES, ":cites"), sql.LINKS_ADDED)
_STAR_HAND = ("* a :Order", "* a :Line", "* :within nat:1", "* :placedBy *", "* :ofOrder *", "* :balance **", "* :total *", "cust:1 :segment *")
register(
    "conform_offenders_star",
    lambda s, d: check.conforming(tables.star(s, d), schema.frame(s, _STAR_HAND), "left_anti"),
    f"SELECT * FROM ({sql.STAR}) g WHERE NOT ((p = 'a' AND o IN (':Order', ':Line')) OR (p = ':within' AND o = 'nat:1') OR p IN (':placedBy', ':ofOrder', ':balance') OR (p = ':segment' AND s = 'cust:1'))",
)
register("conform_offenders_conversations", lambda s, d: check.conforming(tables.conversations(s, d), schema.frame(s, ("* a :Turn", "* :inConv *", "* :role role:user")), "left_anti"), f"SELECT * FROM ({sql.CONVERSATIONS}) g WHERE p = ':next' OR (p = ':role' AND o <> 'role:user')")
register("conform_offenders_pages", lambda s, d: check.conforming(tables.pages(s, d), schema.frame(s, ("* :host *", "* :linksTo path:/La")), "left_anti"), f"SELECT * FROM ({sql.PAGES}) g WHERE p = ':linksTo' AND o <> 'path:/La'")
register("exist_violations_turn_next", lambda s, d: check.violations(tables.conversations(s, d, atoms("?x a :Turn, ?x :next ?y")), [existential("turn_next", "?x a :Turn -> ?x :next ?y")]), "SELECT DISTINCT 'turn_next' AS e_id, 'turn:' || conv_id || '_' || turn AS s, 'a' AS p, ':Turn' AS o, false AS o_lit FROM conversations a WHERE NOT EXISTS (SELECT 1 FROM conversations b WHERE b.conv_id = a.conv_id AND b.turn = a.turn + 1)")
register("exist_violations_page_links", lambda s, d: check.violations(tables.pages(s, d), [existential("page_links", "?x :host ?h -> ?x :linksTo ?y")]), f"WITH g AS ({sql.PAGES}) SELECT 'page_links' AS e_id, s, p, o, o_lit FROM g WHERE p = ':host' AND s NOT IN (SELECT s FROM g WHERE p = ':linksTo')")
