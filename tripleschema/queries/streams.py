"""Streams drained over the events table, compared with the batch result."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tripleschema import fixtures
from tripleschema.operators import schema
from tripleschema.queries import sql
from tripleschema.registry import register
from tripleschema.sources import tables
from tripleschema.streaming import observations as o

_NARROW = ("* :at *", "* :reads *", "* :senses prop:view")


def stream_conformance(spark: SparkSession, d: str) -> DataFrame:
    return o.drained(o.offenders(o.readings(o.event_stream(spark, d)), schema.frame(spark, _NARROW))).select("s", "p", "o", "o_lit").distinct()


def stream_tumble(spark: SparkSession, d: str) -> DataFrame:
    rows = o.drained(o.tumbling(o.event_stream(spark, d)), "complete")
    return rows.select(F.date_format("window.start", "yyyy-MM-dd HH:mm").alias("start"), "event_type", "n")


def stream_closure(spark: SparkSession, d: str) -> DataFrame:
    held = tables.events(spark, d).where("p in ('a', ':heldBy')")
    return o.incremental_closure(o.readings(o.event_stream(spark, d)), fixtures.EVENT_RULES, held)


register("ops_stream_conformance", stream_conformance, f"SELECT * FROM ({sql.EVENTS}) g WHERE (p = ':senses' AND o <> 'prop:view') OR (p = ':reads' AND o_lit)")
register("ops_stream_tumble", stream_tumble, "SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M') AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
register("ops_stream_closure", stream_closure, f"WITH {sql.EVENT_FACTS} {sql.EVENTS} UNION SELECT * FROM derived")
register(
    "ops_stream_missing",
    lambda s, d: o.missing_whole(s, d),
    "SELECT DISTINCT event_id AS purchase, user_id AS place FROM events a WHERE event_type = 'purchase' AND NOT EXISTS (SELECT 1 FROM events b WHERE b.event_type = 'view' AND b.user_id = a.user_id AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 1 HOUR)",
)
register(
    "ops_stream_together",
    lambda s, d: o.drained(o.together(o.event_stream(s, d))).select("purchase", "error", "place"),
    "SELECT a.event_id AS purchase, b.event_id AS error, a.user_id AS place FROM events a JOIN events b ON a.event_type = 'purchase' AND b.event_type = 'error' AND b.user_id = a.user_id AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 1 HOUR",
)
register("ops_stream_distinct", lambda s, d: o.drained(o.distinct_events(o.event_stream(s, d))).select("event_id"), "SELECT event_id FROM events")
