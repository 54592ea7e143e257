"""One query for each operator class around the methods, in the role it plays there."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tripleschema import fixtures
from tripleschema.model import LAMBDA, atoms, pattern
from tripleschema.operators import bgp, check, schema
from tripleschema.plans import canon, rewrite
from tripleschema.plans.tables import local, written
from tripleschema.queries import sql
from tripleschema.queries.graphs import event_patterns
from tripleschema.queries.reasoning import _STAR, PROFILE, rendered_sql, sandbox_sql, star_patterns
from tripleschema.registry import register
from tripleschema.sources import tables
from tripleschema.sources.tables import table

EV, STAR, DOCS = (f"g AS ({sql.GRAPHS[n]})" for n in ("events", "star", "documents"))


def seconds(c: str) -> Column:
    return F.unix_micros(F.col(c).cast("timestamp")) / F.lit(1_000_000)


# -- scans, filters, projections

register("ops_scan_prune", lambda s, d: tables.star(s, d, atoms("?o :placedBy ?c, ?c :within ?n")), f"WITH {STAR} SELECT * FROM g WHERE p IN (':placedBy', ':within')")
register("ops_filter_terms", lambda s, d: tables.events(s, d).where("o_lit").select("s", "o"), f"WITH {EV} SELECT s, o FROM g WHERE o_lit")
register("ops_project_vars", lambda s, d: bgp.matches(atoms("?r :at ?p")[0], tables.events(s, d)).select(F.col("v_p").alias("place")).distinct(), f"WITH {EV} SELECT DISTINCT o AS place FROM g WHERE p = ':at'")

# -- joins

register("ops_join_body2", lambda s, d: bgp.evaluate(atoms("?r :senses prop:error, ?r :at ?p"), tables.events(s, d)), f"WITH {EV} SELECT DISTINCT a.s AS v_r, b.o AS v_p FROM g a JOIN g b ON a.s = b.s AND b.p = ':at' WHERE a.p = ':senses' AND a.o = 'prop:error'")
register("ops_join_body3", lambda s, d: bgp.evaluate(fixtures.EVENT_RULES[1].body, tables.events(s, d)), f"WITH {EV} SELECT DISTINCT a.s AS v_r, b.o AS v_p FROM g a JOIN g b ON a.s = b.s AND b.p = ':at' JOIN g c ON c.s = a.s AND c.p = ':reads' AND c.o = '1' AND c.o_lit WHERE a.p = ':senses' AND a.o = 'prop:error'")


def join_broadcast(spark: SparkSession, d: str) -> DataFrame:
    nations = table(spark, d, "nation")  # 25 rows by definition
    return table(spark, d, "customer").join(F.broadcast(nations), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("customers"))


register("ops_join_broadcast", join_broadcast, "SELECT n_name, count(*) AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
register("ops_join_sortmerge", lambda s, d: table(s, d, "lineitem").join(table(s, d, "orders").hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderstatus").agg(F.count("*").alias("lines")), "SELECT o_orderstatus, count(*) AS lines FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderstatus")
register("ops_join_wildcard", lambda s, d: rewrite.eightfold(atoms("?c :segment ?g, ?o :placedBy ?g"), canon.sandbox(star_patterns(s, d))).select("v_g"), f"WITH f AS ({_STAR}) SELECT DISTINCT o_v AS v_g FROM f WHERE p_v = ':segment' AND EXISTS (SELECT 1 FROM f WHERE p_v = ':placedBy')")
register("ops_join_cross_pool", lambda s, d: event_patterns(s, d).where("o_k = 'A'").select("p_v").crossJoin(canon.constants(event_patterns(s, d), ()).where("not lit").select("c")), f"WITH f AS ({PROFILE}) SELECT f.p_v, k.c FROM f CROSS JOIN (SELECT p_v AS c FROM f UNION SELECT o_v FROM f WHERE o_v IS NOT NULL UNION SELECT '{LAMBDA}') k WHERE f.o_k = 'A'")


def semi_applicable(spark: SparkSession, d: str) -> DataFrame:
    g = tables.events(spark, d)
    rules = local(spark, [(r.id,) for r in fixtures.EVENT_RULES], "rule_id string")
    met = reduce(DataFrame.unionByName, (bgp.evaluate(r.body, g, distinct=False).limit(1).select(F.lit(r.id).alias("rule_id")) for r in fixtures.EVENT_RULES))
    return rules.join(met, "rule_id", "left_semi")


register("ops_semi_applicable", semi_applicable, "SELECT 'k1' AS rule_id WHERE EXISTS (SELECT 1 FROM events WHERE event_type = 'purchase') UNION ALL SELECT 'k2' WHERE EXISTS (SELECT 1 FROM events WHERE event_type = 'error' AND value >= 100)")
register("ops_anti_violation", lambda s, d: table(s, d, "orders").join(table(s, d, "lineitem"), F.col("l_orderkey") == F.col("o_orderkey"), "left_anti").select("o_orderkey"), "SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")


def outer_report(spark: SparkSession, d: str) -> DataFrame:
    g = tables.documents(spark, d)
    docs, marks = g.where("p = 'a'").select("s"), g.where("p = ':quality'").select("s", F.col("o").alias("quality"))
    return docs.join(marks, "s", "left")


register("ops_outer_report", outer_report, f"WITH {DOCS} SELECT a.s, b.o AS quality FROM g a LEFT JOIN g b ON a.s = b.s AND b.p = ':quality' WHERE a.p = 'a'")


def schema_diff(spark: SparkSession, d: str) -> DataFrame:
    g = tables.documents(spark, d)
    of = lambda lang: g.join(g.where((F.col("p") == ":lang") & (F.col("o") == f"lang:{lang}")).select("s"), "s", "left_semi")
    change = schema.difference(schema.profile(of("en"), (":lang", ":source")), schema.profile(of("de"), (":lang", ":source")))
    return schema.rendered(change.where("change != 'kept'")).join(schema.rendered(change.where("change = 'added'")).withColumn("change", F.lit("added")), "pattern", "left").select("pattern", F.coalesce("change", F.lit("removed")).alias("change"))


def _of(lang: str) -> str:
    return rendered_sql(sql.profile(f"SELECT g.* FROM ({sql.DOCUMENTS}) g JOIN documents ON g.s = 'doc:' || doc_id WHERE lang = '{lang}'", "':lang', ':source'"))


register("ops_full_schema_diff", schema_diff, f"SELECT coalesce(a.pattern, b.pattern) AS pattern, CASE WHEN a.pattern IS NULL THEN 'added' ELSE 'removed' END AS change FROM ({_of('en')}) a FULL JOIN ({_of('de')}) b ON a.pattern = b.pattern WHERE a.pattern IS NULL OR b.pattern IS NULL")


def range_join(spark: SparkSession, d: str) -> DataFrame:
    """Readings within an hour of an error at the same place: equality on place and hour bucket, then the exact range."""
    e = table(spark, d, "events").select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    hour = 3_600_000_000
    errors = e.where("event_type = 'error'").select(F.col("event_id").alias("error_id"), F.col("user_id").alias("place"), F.col("us").alias("at"), F.explode(F.sequence(F.floor(F.col("us") / hour) - 1, F.floor(F.col("us") / hour) + 1)).alias("bucket"))
    reads = e.where("event_type = 'view'").withColumn("b", F.floor(F.col("us") / hour))
    return reads.join(errors, (F.col("user_id") == F.col("place")) & (F.col("b") == F.col("bucket"))).where(F.abs(F.col("us") - F.col("at")) <= hour).select("event_id", "error_id")


register("ops_range_join", range_join, "SELECT v.event_id, e.event_id AS error_id FROM events v JOIN events e ON v.user_id = e.user_id AND e.event_type = 'error' AND abs(epoch_us(v.ts) - epoch_us(e.ts)) <= 3600000000 WHERE v.event_type = 'view'")


def asof(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    e = table(spark, d, "events").withColumn("last_error", F.last(F.when(F.col("event_type") == "error", F.col("event_id")), ignorenulls=True).over(w))
    return e.where("event_type = 'purchase'").select("event_id", "last_error")


register("ops_asof_last_status", asof, "SELECT event_id, last_error FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'error' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_error FROM events) WHERE event_type = 'purchase'")


def interval_overlap(spark: SparkSession, d: str) -> DataFrame:
    """Orders by the months between their date and their last shipment."""
    last = table(spark, d, "lineitem").groupBy("l_orderkey").agg(F.max("l_shipdate").alias("last"))
    o = table(spark, d, "orders").join(last, F.col("o_orderkey") == F.col("l_orderkey")).where("last >= o_orderdate")
    months = F.sequence(F.trunc("o_orderdate", "month"), F.trunc("last", "month"), F.expr("interval 1 month"))
    return o.select(F.explode(months).alias("m")).groupBy(F.date_format("m", "yyyy-MM").alias("month")).agg(F.count("*").alias("orders"))


register("ops_interval_overlap", interval_overlap, "WITH o AS (SELECT date_trunc('month', o_orderdate) AS a, date_trunc('month', max(l_shipdate)) AS b FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderkey, o_orderdate HAVING max(l_shipdate) >= o_orderdate) SELECT strftime(m, '%Y-%m') AS month, count(*) AS orders FROM (SELECT unnest(generate_series(CAST(a AS TIMESTAMP), CAST(b AS TIMESTAMP), INTERVAL 1 MONTH)) AS m FROM o) GROUP BY 1")

# -- aggregates

register("ops_agg_predicate_profile", lambda s, d: tables.star(s, d).groupBy("p").agg(F.count("*").alias("triples"), F.countDistinct("s").alias("subjects"), F.countDistinct("o").alias("objects")), f"WITH {STAR} SELECT p, count(*) AS triples, count(DISTINCT s) AS subjects, count(DISTINCT o) AS objects FROM g GROUP BY p")
def approx_profile(spark: SparkSession, d: str) -> DataFrame:
    """Distinct subjects by predicate, and whether the sketch is within a tenth of them."""
    n = tables.star(spark, d).groupBy("p").agg(F.approx_count_distinct("s", 0.02).alias("about"), F.countDistinct("s").alias("subjects"))
    return n.select("p", "subjects", (F.abs(F.col("about") - F.col("subjects")) <= 0.1 * F.col("subjects")).alias("close"))


register("ops_agg_approx_profile", approx_profile, f"SELECT p, count(DISTINCT s) AS subjects, true AS close FROM ({sql.STAR}) g GROUP BY p")


def sensor(spark: SparkSession, d: str) -> DataFrame:
    """Readings summed to a derived fact: places with a busy hour."""
    e = table(spark, d, "events").groupBy("user_id", F.date_trunc("hour", "ts").alias("hour")).agg(F.count("*").alias("n"), F.max("value").alias("top"))
    return e.where("n >= 2").select(tables.iri("place", "user_id").alias("s"), F.lit("a").alias("p"), F.lit(":BusyPlace").alias("o")).distinct()


register("ops_agg_sensor", sensor, "SELECT DISTINCT 'place:' || user_id AS s, 'a' AS p, ':BusyPlace' AS o FROM events GROUP BY user_id, date_trunc('hour', ts) HAVING count(*) >= 2")
register("ops_agg_bool", lambda s, d: event_patterns(s, d).groupBy("p_v").agg(F.bool_or(F.col("o_k") == "A").alias("free"), F.bool_and(F.col("o_k") == "C").alias("fixed")), f"SELECT p_v, bool_or(o_k = 'A') AS free, bool_and(o_k = 'C') AS fixed FROM ({PROFILE}) f GROUP BY p_v")
register("ops_agg_collect", lambda s, d: schema.profile(tables.star(s, d), ("a", ":status")).groupBy("p_v").agg(F.array_join(F.sort_array(F.collect_set(F.coalesce("o_v", "o_k"))), ",").alias("objects")), f"SELECT p_v, string_agg(coalesce(o_v, o_k), ',' ORDER BY coalesce(o_v, o_k)) AS objects FROM ({sql.profile(sql.STAR, chr(39) + 'a' + chr(39) + ', ' + chr(39) + ':status' + chr(39))}) f GROUP BY p_v")

_KINDS = "SELECT split_part(s, ':', 1) AS class, p, o_lit FROM g"


def kinds(spark: SparkSession, d: str) -> DataFrame:
    return tables.star(spark, d).select(F.substring_index("s", ":", 1).alias("class"), "p", "o_lit")


register("ops_rollup_quality", lambda s, d: kinds(s, d).rollup("class", "p").agg(F.count("*").alias("n")), f"WITH {STAR} SELECT class, p, count(*) AS n FROM ({_KINDS}) k GROUP BY ROLLUP (class, p)")
register("ops_cube_quality", lambda s, d: kinds(s, d).cube("class", "o_lit").agg(F.count("*").alias("n")), f"WITH {STAR} SELECT class, o_lit, count(*) AS n FROM ({_KINDS}) k GROUP BY CUBE (class, o_lit)")


def grouping_sets(spark: SparkSession, d: str) -> DataFrame:
    kinds(spark, d).createOrReplaceTempView("triple_kinds")
    return spark.sql("SELECT class, p, count(*) AS n FROM triple_kinds GROUP BY GROUPING SETS ((class), (p))")


register("ops_grouping_sets", grouping_sets, f"WITH {STAR} SELECT class, p, count(*) AS n FROM ({_KINDS}) k GROUP BY GROUPING SETS ((class), (p))")


def pivot_wide(spark: SparkSession, d: str) -> DataFrame:
    from tripleschema.sources.store import to_wide

    wide = to_wide(tables.documents(spark, d), [":lang", ":quality"])
    return wide.select("s", F.col(":lang").alias("lang"), F.col(":quality").alias("quality"))


register("ops_pivot_wide", pivot_wide, f"WITH {DOCS} SELECT s, min(o) FILTER (WHERE p = ':lang') AS lang, min(o) FILTER (WHERE p = ':quality') AS quality FROM g WHERE p IN (':lang', ':quality') GROUP BY s")

# -- windows


def win_rank(spark: SparkSession, d: str) -> DataFrame:
    n = kinds(spark, d).groupBy("class", "p").agg(F.count("*").alias("n"))
    w = Window.partitionBy("class").orderBy(F.desc("n"))
    return n.select("class", "p", "n", F.rank().over(w).alias("rank"), F.dense_rank().over(w).alias("dense"), F.row_number().over(Window.partitionBy("class").orderBy(F.desc("n"), "p")).alias("row"))


register("ops_win_rank", win_rank, f"WITH {STAR} SELECT class, p, n, CAST(rank() OVER w AS INTEGER) AS rank, CAST(dense_rank() OVER w AS INTEGER) AS dense, CAST(row_number() OVER (PARTITION BY class ORDER BY n DESC, p) AS INTEGER) AS row FROM (SELECT class, p, count(*) AS n FROM ({_KINDS}) k GROUP BY class, p) WINDOW w AS (PARTITION BY class ORDER BY n DESC)")
register("ops_win_next_edge", lambda s, d: table(s, d, "conversations").select("conv_id", "turn", F.lead("turn").over(Window.partitionBy("conv_id").orderBy("turn")).alias("following")).where("following is not null"), "SELECT * FROM (SELECT conv_id, turn, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS following FROM conversations) WHERE following IS NOT NULL")


def running(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return table(spark, d, "events").select("event_id", F.sum(F.when((F.col("event_type") == "error") & (F.col("value") >= 100), 1).otherwise(0)).over(w).alias("hazards"))


register("ops_win_running", running, "SELECT event_id, CAST(sum(CASE WHEN event_type = 'error' AND value >= 100 THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS BIGINT) AS hazards FROM events")


def win_range(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    return e.select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("us").rangeBetween(-3_600_000_000, 0)).alias("n"))


register("ops_win_range", win_range, "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS n FROM events")

# -- sorts and sets


def sort_topk(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events")
    found = e.where("event_type = 'purchase'").select("user_id", F.get_json_object("props", "$.k").alias("k")).distinct()
    closed = e.where("event_type = 'error' and value >= 100").select("user_id").distinct()
    return found.join(closed, "user_id").groupBy("user_id").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "user_id").limit(10)


register("ops_sort_topk", sort_topk, "SELECT user_id, count(DISTINCT json_extract_string(props, '$.k')) AS n FROM events WHERE event_type = 'purchase' AND user_id IN (SELECT user_id FROM events WHERE event_type = 'error' AND value >= 100) GROUP BY user_id ORDER BY n DESC, user_id LIMIT 10")
register("ops_union_branches", lambda s, d: reduce(DataFrame.unionByName, (canon.sandbox(event_patterns(s, d)).where(F.col(c) == LAMBDA) for c in "so")).distinct(), f"SELECT * FROM ({sandbox_sql(PROFILE)}) x WHERE s = '{LAMBDA}' UNION SELECT * FROM ({sandbox_sql(PROFILE)}) y WHERE o = '{LAMBDA}'")
_OTHER = ("* :senses :Gas", "* a :BadgeTag", "* :heldBy **", "* :at *", "* :reads **")
register("ops_intersect_patterns", lambda s, d: schema.rendered(event_patterns(s, d)).intersect(schema.rendered(schema.frame(s, _OTHER))), f"{rendered_sql(PROFILE)} INTERSECT SELECT unnest(['{chr(39) + ', ' + chr(39)}'])".replace(f"['{chr(39) + ', ' + chr(39)}']", "[" + ", ".join(f"'{p}'" for p in _OTHER) + "]"))


def except_rules(spark: SparkSession, d: str) -> DataFrame:
    g = tables.star(spark, d)
    rules = local(spark, [(e.id,) for e in fixtures.STAR_EXISTENTIALS[:3]], "e_id string")
    return rules.exceptAll(check.violations(g, fixtures.STAR_EXISTENTIALS[:3]).select("e_id").distinct())


register("ops_except_rules", except_rules, "SELECT 'order_customer' AS e_id UNION ALL SELECT 'order_line' WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)) UNION ALL SELECT 'nation_supplier' WHERE NOT EXISTS (SELECT 1 FROM nation WHERE n_nationkey NOT IN (SELECT s_nationkey FROM supplier))")

# -- scalar functions

register("ops_string_terms", lambda s, d: table(s, d, "pages").select("page_id", F.upper(F.regexp_extract("url", r"^[a-z]+://([^/?#]+)", 1)).alias("host"), F.sha2("url", 256).alias("digest"), F.substring_index("url", ":", 1).alias("scheme")), "SELECT page_id, upper(regexp_extract(url, '^[a-z]+://([^/?#]+)', 1)) AS host, sha256(url) AS digest, split_part(url, ':', 1) AS scheme FROM pages")
register("ops_date_parts", lambda s, d: table(s, d, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.date_format("o_orderdate", "yyyy-MM-dd").alias("day")), "SELECT o_orderkey, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, strftime(o_orderdate, '%Y-%m-%d') AS day FROM orders")
register("ops_math_bucket", lambda s, d: table(s, d, "orders").select(F.pmod("o_custkey", F.lit(7)).alias("bucket"), F.floor("o_totalprice").cast("long").alias("whole")).groupBy("bucket").agg(F.sum("whole").alias("total")), "SELECT o_custkey % 7 AS bucket, CAST(sum(CAST(floor(o_totalprice) AS BIGINT)) AS BIGINT) AS total FROM orders GROUP BY 1")


def array_atoms(spark: SparkSession, d: str) -> DataFrame:
    a = F.array("s_k", "p_k", "o_k")
    return event_patterns(spark, d).select("p_v", "o_v", F.array_join(F.transform(a, lambda k: F.when(k.isin("I", "A"), LAMBDA).otherwise(k)), "").alias("shape"), F.size(F.filter(a, lambda k: k.isin("I", "A"))).alias("wild"))


register("ops_array_atoms", array_atoms, f"SELECT p_v, o_v, CASE WHEN s_k IN ('I', 'A') THEN '{LAMBDA}' ELSE s_k END || p_k || CASE WHEN o_k IN ('I', 'A') THEN '{LAMBDA}' ELSE o_k END AS shape, CAST((s_k IN ('I', 'A'))::INT + (o_k IN ('I', 'A'))::INT AS INTEGER) AS wild FROM ({PROFILE}) f")


def map_bindings(spark: SparkSession, d: str) -> DataFrame:
    rows = bgp.evaluate(fixtures.EVENT_RULES[1].body, tables.events(spark, d))
    m = F.map_concat(F.create_map(F.lit("r"), F.col("v_r")), F.create_map(F.lit("p"), F.col("v_p")))
    return rows.select(m.alias("m")).select(F.element_at("m", "r").alias("r"), F.element_at(F.map_filter("m", lambda k, v: v.startswith("place:")), "p").alias("p"))


register("ops_map_bindings", map_bindings, "SELECT DISTINCT 'ev:' || event_id AS r, 'place:' || user_id AS p FROM events WHERE event_type = 'error' AND value >= 100")
register("ops_json_props", lambda s, d: table(s, d, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k")), "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")

# -- time windows, as batches


def ts() -> Column:
    return F.col("ts").cast("timestamp")


def tumble(spark: SparkSession, d: str) -> DataFrame:
    w = table(spark, d, "events").groupBy(F.window(ts(), "1 hour"), "event_type").agg(F.count("*").alias("n"))
    return w.select(F.date_format("window.start", "yyyy-MM-dd HH:mm").alias("start"), "event_type", "n")


def slide(spark: SparkSession, d: str) -> DataFrame:
    w = table(spark, d, "events").groupBy(F.window(ts(), "1 hour", "15 minutes")).agg(F.count("*").alias("n"))
    return w.select(F.date_format("window.start", "yyyy-MM-dd HH:mm").alias("start"), "n")


def session(spark: SparkSession, d: str) -> DataFrame:
    w = table(spark, d, "events").groupBy(F.session_window(ts(), "30 minutes"), "user_id").agg(F.count("*").alias("n"))
    return w.select("user_id", F.date_format("session_window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


register("ops_tumble", tumble, "SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M') AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
register("ops_slide", slide, "SELECT strftime(make_timestamp((epoch_us(ts) // 900000000 - k) * 900000000), '%Y-%m-%d %H:%M') AS start, count(*) AS n FROM events, (SELECT unnest([0, 1, 2, 3]) AS k) x GROUP BY 1")
register("ops_session", session, "WITH a AS (SELECT user_id, ts, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER w < 1800000000 THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), b AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS k FROM a) SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM b GROUP BY user_id, k")

# -- SQL table function


def udtf_expand(spark: SparkSession, d: str) -> DataFrame:
    """The variants of each pattern of the events graph, as an atom with variables for its wildcards."""
    from tripleschema.functions.udtf import expand_pattern
    from tripleschema.plans.tables import prepare

    prepare(spark)
    spark.udtf.register("expand_pattern", expand_pattern())
    asked = event_patterns(spark, d).select(*(F.coalesce(f"{x}_v", F.lit(f"?{x}")).alias(x) for x in "spo"))
    return spark.sql("SELECT e.s, e.p, e.o FROM {asked} a, LATERAL expand_pattern(a.s, a.p, a.o) e", asked=asked)


_EXPANDED = ", ".join(f"CASE WHEN k // {bit} % 2 = 1 THEN '{LAMBDA}' ELSE coalesce({x}_v, '?{x}') END AS {x}" for x, bit in (("s", 4), ("p", 2), ("o", 1)))
register("ops_udtf_expand", udtf_expand, f"SELECT {_EXPANDED} FROM ({PROFILE}) f, range(8) r(k)")
register("ops_store_roundtrip", lambda s, d: _roundtrip(s, d), f"WITH {EV} SELECT s, p, o, o_lit FROM g WHERE p = ':heldBy'")


def _roundtrip(spark: SparkSession, d: str) -> DataFrame:
    """Through the dictionary and the store and back, one predicate read."""
    import uuid

    from tripleschema.plans.tables import shared_dir
    from tripleschema.sources import store

    ids, terms = store.encode(written(tables.events(spark, d), "events"))
    path = f"{shared_dir(spark)}/store-{uuid.uuid4().hex}"
    store.write_store(store.decode(ids, terms), path)
    return store.read_store(spark, path).where("p = ':heldBy'")


register("ops_pattern_filter", lambda s, d: tables.events(s, d).where(check.compiled(pattern("* :reads \"1\""))), f"WITH {EV} SELECT * FROM g WHERE p = ':reads' AND o = '1' AND o_lit")
