"""Pieces of oracle SQL."""

from __future__ import annotations

from collections.abc import Sequence

EVENTS = """
SELECT 'ev:' || event_id AS s, ':senses' AS p, 'prop:' || event_type AS o, false AS o_lit FROM events
UNION SELECT 'ev:' || event_id, ':at', 'place:' || user_id, false FROM events
UNION SELECT 'ev:' || event_id, ':reads', CASE event_type WHEN 'purchase' THEN 'tag:' || json_extract_string(props, '$.k')
  WHEN 'error' THEN CASE WHEN value >= 100 THEN '1' ELSE '0' END ELSE CAST(CAST(value AS DECIMAL(18,2)) AS VARCHAR) END, event_type <> 'purchase' FROM events
UNION SELECT 'tag:' || s_suppkey, 'a', ':BadgeTag', false FROM supplier WHERE s_acctbal > 0
UNION SELECT 'tag:' || s_suppkey, ':heldBy', 'supp:' || s_suppkey, false FROM supplier WHERE s_acctbal > 0"""

STAR = """
SELECT 'reg:' || r_regionkey AS s, 'a' AS p, ':Region' AS o, false AS o_lit FROM region
UNION SELECT 'reg:' || r_regionkey, ':label', r_name, true FROM region
UNION SELECT 'nat:' || n_nationkey, 'a', ':Nation', false FROM nation
UNION SELECT 'nat:' || n_nationkey, ':label', n_name, true FROM nation
UNION SELECT 'nat:' || n_nationkey, ':within', 'reg:' || n_regionkey, false FROM nation
UNION SELECT 'cust:' || c_custkey, 'a', ':Customer', false FROM customer
UNION SELECT 'cust:' || c_custkey, ':within', 'nat:' || c_nationkey, false FROM customer
UNION SELECT 'cust:' || c_custkey, ':segment', 'seg:' || c_mktsegment, false FROM customer
UNION SELECT 'cust:' || c_custkey, ':balance', CAST(CAST(c_acctbal AS DECIMAL(18,2)) AS VARCHAR), true FROM customer
UNION SELECT 'supp:' || s_suppkey, 'a', ':Supplier', false FROM supplier
UNION SELECT 'supp:' || s_suppkey, ':within', 'nat:' || s_nationkey, false FROM supplier
UNION SELECT 'supp:' || s_suppkey, ':suppliedFrom', 'nat:' || s_nationkey, false FROM supplier
UNION SELECT 'supp:' || s_suppkey, ':balance', CAST(CAST(s_acctbal AS DECIMAL(18,2)) AS VARCHAR), true FROM supplier
UNION SELECT 'ord:' || o_orderkey, 'a', ':Order', false FROM orders
UNION SELECT 'ord:' || o_orderkey, ':placedBy', 'cust:' || o_custkey, false FROM orders
UNION SELECT 'ord:' || o_orderkey, ':status', 'st:' || o_orderstatus, false FROM orders
UNION SELECT 'ord:' || o_orderkey, ':priority', 'pr:' || o_orderpriority, false FROM orders
UNION SELECT 'ord:' || o_orderkey, ':total', CAST(CAST(o_totalprice AS DECIMAL(18,2)) AS VARCHAR), true FROM orders
UNION SELECT 'line:' || l_orderkey || '_' || l_linenumber, 'a', ':Line', false FROM lineitem
UNION SELECT 'line:' || l_orderkey || '_' || l_linenumber, ':ofOrder', 'ord:' || l_orderkey, false FROM lineitem
UNION SELECT 'line:' || l_orderkey || '_' || l_linenumber, ':fromSupplier', 'supp:' || l_suppkey, false FROM lineitem"""

DOCUMENTS = """
SELECT 'doc:' || doc_id AS s, 'a' AS p, ':Document' AS o, false AS o_lit FROM documents
UNION SELECT 'doc:' || doc_id, ':lang', 'lang:' || lang, false FROM documents
UNION SELECT 'doc:' || doc_id, ':source', 'src:' || source, false FROM documents
UNION SELECT 'doc:' || doc_id, ':chars', CAST(n_chars AS VARCHAR), true FROM documents
UNION SELECT 'doc:' || doc_id, ':quality', CAST(quality AS VARCHAR), true FROM labels
UNION SELECT 'doc:' || doc_id, ':toxic', CAST(toxic AS VARCHAR), true FROM labels"""

CONVERSATIONS = """
SELECT 'turn:' || conv_id || '_' || turn AS s, 'a' AS p, ':Turn' AS o, false AS o_lit FROM conversations
UNION SELECT 'turn:' || conv_id || '_' || turn, ':inConv', 'conv:' || conv_id, false FROM conversations
UNION SELECT 'turn:' || conv_id || '_' || turn, ':role', 'role:' || role, false FROM conversations
UNION SELECT 'turn:' || a.conv_id || '_' || a.turn, ':next', 'turn:' || b.conv_id || '_' || b.turn, false
  FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1"""

PAGES = """
SELECT 'page:' || page_id AS s, ':host' AS p, 'host:' || regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS o, false AS o_lit FROM pages
UNION SELECT 'page:' || page_id, ':linksTo', 'path:' || path, false FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href="(/[^"]*)"', 1)) AS path FROM pages)"""

GRAPHS = {"events": EVENTS, "star": STAR, "documents": DOCUMENTS, "conversations": CONVERSATIONS, "pages": PAGES}

#: Tags seen in purchases at places, places closed by errors, and tags that intrude.
EVENT_FACTS = """
found AS (SELECT DISTINCT 'tag:' || json_extract_string(props, '$.k') AS t, 'place:' || user_id AS p FROM events WHERE event_type = 'purchase'),
closed AS (SELECT DISTINCT 'place:' || user_id AS p FROM events WHERE event_type = 'error' AND value >= 100),
derived AS (
  SELECT t AS s, 'a' AS p, ':BadgeTag' AS o, false AS o_lit FROM found
  UNION SELECT t, ':foundIn', p, false FROM found
  UNION SELECT p, 'a', ':ClosedArea', false FROM closed
  UNION SELECT found.t, ':intrudes', found.p, false FROM found JOIN closed USING (p))"""


EVENTS_CLOSED = f"WITH {EVENT_FACTS} {EVENTS} UNION SELECT * FROM derived"

#: What the star rules add to lines and orders (the places of the within relation stay as they are in kind).
STAR_ADDED = """
SELECT 'ord:' || o_orderkey AS s, ':soldIn' AS p, x.o AS o, false AS o_lit FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON n_nationkey = c_nationkey, LATERAL (SELECT unnest(['nat:' || n_nationkey, 'reg:' || n_regionkey]) AS o) x
UNION SELECT 'line:' || l_orderkey || '_' || l_linenumber, ':boughtBy', 'cust:' || o_custkey, false FROM lineitem JOIN orders ON l_orderkey = o_orderkey"""

AFTER_ADDED = """SELECT 'turn:' || a.conv_id || '_' || a.turn AS s, ':after' AS p, 'turn:' || b.conv_id || '_' || b.turn AS o, false AS o_lit
  FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND a.turn < b.turn"""

LINKS_ADDED = """SELECT DISTINCT 'host:' || regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS s, ':cites' AS p, 'path:' || path AS o, false AS o_lit
  FROM (SELECT url, unnest(regexp_extract_all(html, 'href="(/[^"]*)"', 1)) AS path FROM pages)"""


def atoms_table(rows: Sequence[tuple]) -> str:
    """A VALUES list of terms; None is null."""
    return "VALUES " + ", ".join("(" + ", ".join("NULL" if v is None else str(v) if isinstance(v, int) else "'" + v.replace("'", "''") + "'" for v in r) + ")" for r in rows)


def profile(graph: str, classes: str) -> str:
    """Patterns of a graph: per predicate, and per object of the predicates ``classes``."""
    return f"""SELECT 'I' AS s_k, CAST(NULL AS VARCHAR) AS s_v, 'C' AS p_k, p AS p_v, CASE WHEN k IS NOT NULL THEN 'C' WHEN any_lit THEN 'A' ELSE 'I' END AS o_k, k AS o_v
  FROM (SELECT p, k, bool_or(o_lit) AS any_lit FROM (SELECT p, o_lit, CASE WHEN p IN ({classes}) AND NOT o_lit THEN o END AS k FROM ({graph}) g0) g1 GROUP BY p, k) g2"""
