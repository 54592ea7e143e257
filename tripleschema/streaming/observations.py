"""Structured Streaming around the methods: observations arrive as rows, schemas and rules stand still."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tripleschema.model import Rule
from tripleschema.operators import bgp, check, closure, schema
from tripleschema.plans import consequence
from tripleschema.plans.tables import shared_dir, written
from tripleschema.sources.tables import edge, iri, money, table


def event_stream(spark: SparkSession, sf_dir: str, per_trigger: int = 4) -> DataFrame:
    """The events table as a stream; ``ts`` becomes a timestamp so that it can carry a watermark."""
    path = f"{sf_dir}/events.parquet"
    kind = spark.read.parquet(path).schema
    place = spark._jvm.org.apache.hadoop.fs.Path(path)
    folder = place.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(place).isDirectory()
    reader = spark.readStream.schema(kind).option("maxFilesPerTrigger", per_trigger)
    rows = reader.parquet(path) if folder else reader.option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def distinct_events(stream: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Replayed events dropped as long as the watermark remembers them."""
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def readings(stream: DataFrame) -> DataFrame:
    """Triples of event rows, as on the batch side but without a distinct, which a stream cannot hold for ever."""
    ev = iri("ev", "event_id")
    result = F.when(F.col("event_type") == "purchase", iri("tag", F.get_json_object("props", "$.k"))).when(F.col("event_type") == "error", F.when(F.col("value") >= 100, "1").otherwise("0")).otherwise(money("value"))
    edges = F.array(*(e.column() for e in (edge(ev, ":senses", iri("prop", "event_type")), edge(ev, ":at", iri("place", "user_id")), edge(ev, ":reads", result, F.col("event_type") != "purchase"))))
    return stream.select("ts", F.explode(edges).alias("t")).select("ts", "t.s", "t.p", "t.o", "t.o_lit").where("s is not null and o is not null")


def offenders(stream: DataFrame, patterns: DataFrame) -> DataFrame:
    """Arriving triples that no pattern admits: a stateless join with the standing schema."""
    return check.conforming(stream, patterns, "left_anti")


def tumbling(stream: DataFrame, size: str = "1 hour", delay: str = "10 minutes") -> DataFrame:
    return stream.withWatermark("ts", delay).groupBy(F.window("ts", size), "event_type").agg(F.count("*").alias("n"), F.max("value").alias("top"))


def together(stream: DataFrame, within: str = "1 hour", delay: str = "1 hour") -> DataFrame:
    """A rule body over two streams: a purchase and an error at one place within a time."""
    a = stream.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("place"), F.col("ts").alias("seen")).withWatermark("seen", delay)
    b = stream.where("event_type = 'error'").select(F.col("event_id").alias("error"), F.col("user_id").alias("spot"), F.col("ts").alias("failed")).withWatermark("failed", delay)
    return a.join(b, F.expr(f"place = spot AND failed BETWEEN seen AND seen + INTERVAL {within}"))


def missing(stream: DataFrame, within: str = "1 hour", delay: str = "1 hour") -> DataFrame:
    """Purchases after which no view comes at the same place in time: known once the watermark has passed."""
    a = stream.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("place"), F.col("ts").alias("seen")).withWatermark("seen", delay)
    b = stream.where("event_type = 'view'").select(F.col("event_id").alias("view"), F.col("user_id").alias("spot"), F.col("ts").alias("viewed")).withWatermark("viewed", delay)
    return a.join(b, F.expr(f"place = spot AND viewed BETWEEN seen AND seen + INTERVAL {within}"), "leftOuter").where("view is null").select("purchase", "place", "seen")


def missing_whole(spark: SparkSession, sf_dir: str, within: str = "1 hour", delay: str = "1 hour") -> DataFrame:
    """``missing`` for a stream that has ended: what its last watermark could not decide is looked up in the whole table."""
    decided = drained(missing(event_stream(spark, sf_dir), within, delay)).select("purchase", "place")
    rows = table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    last = rows.where("event_type in ('purchase', 'view')").groupBy("event_type").agg(F.max("ts").alias("ts")).agg(F.min("ts")).first()[0]
    a = rows.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("place"), F.col("ts").alias("seen"))
    b = rows.where("event_type = 'view'").select(F.col("user_id").alias("spot"), F.col("ts").alias("viewed"))
    open_ = a.where(F.lit(last is None) | (F.col("seen") >= F.lit(last) - F.expr(f"INTERVAL {within}") - F.expr(f"INTERVAL {delay}") - F.expr("INTERVAL 1 minute")))
    late = open_.join(b, F.expr(f"place = spot AND viewed BETWEEN seen AND seen + INTERVAL {within}"), "left_anti").select("purchase", "place")
    return decided.unionByName(late).distinct()


def late_rows(stream: DataFrame, delay: str = "10 minutes") -> list[int]:
    """For each batch, the rows that a window with this delay would have dropped: those older than the watermark that the
    batches before have set."""
    counts: list[int] = []

    def step(batch: DataFrame, before: DataFrame | None) -> DataFrame:
        top = before.agg(F.max("ts")).first()[0] if before is not None else None
        counts.append(0 if top is None else batch.where(F.col("ts") < F.lit(top) - F.expr(f"INTERVAL {delay}")).count())
        return batch.agg(F.max("ts").alias("ts"))

    drained(stream.select("ts"), each=step)
    return counts


def drained(stream: DataFrame, mode: str = "append", each: Callable[[DataFrame, DataFrame | None], DataFrame] | None = None, at: str | None = None) -> DataFrame:
    """Run a stream over what is there and give the result as a table.

    Batches are written under their number, so a repeated batch replaces itself.  ``each`` gets a batch and what the
    batches before have written (None at first): that is the only state, so a run that is started again under the same
    ``at`` goes on where the stream's checkpoint does."""
    spark = stream.sparkSession
    at = at or f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    columns = stream.schema
    place = spark._jvm.org.apache.hadoop.fs.Path(f"{at}/out")
    files = place.getFileSystem(spark._jsc.hadoopConfiguration())

    def results() -> DataFrame | None:
        if not files.exists(place):
            return None
        parts = files.globStatus(spark._jvm.org.apache.hadoop.fs.Path(f"{at}/out/*.parquet" if mode == "complete" else f"{at}/out/batch=*/*.parquet"))
        return spark.read.option("basePath", f"{at}/out").parquet(f"{at}/out") if len(parts) else None

    def sink(batch: DataFrame, number: int) -> None:
        if each:
            before = results()
            batch = each(batch, before.where(F.col("batch") < number).drop("batch") if before is not None else None)
        batch.write.mode("overwrite").parquet(f"{at}/out" if mode == "complete" else f"{at}/out/batch={number}")

    stream.writeStream.outputMode(mode).option("checkpointLocation", f"{at}/state").trigger(availableNow=True).foreachBatch(sink).start().awaitTermination()
    rows = results()
    if rows is None:
        return spark.createDataFrame([], columns)
    return rows.drop("batch") if mode != "complete" else rows


def incremental_closure(stream: DataFrame, rules: Sequence[Rule], start: DataFrame, at: str | None = None) -> DataFrame:
    """The closure of a growing graph: each batch of new triples is the delta of a semi-naive run on the store so far, which
    is ``start`` and what the batches before have added."""
    start = start.select(*closure.TRIPLE)

    def step(batch: DataFrame, before: DataFrame | None) -> DataFrame:
        old = start if before is None else start.unionByName(before.select(*closure.TRIPLE))
        delta = written(batch.select(*closure.TRIPLE).distinct().join(old, closure.TRIPLE, "left_anti"), "delta")
        fresh = delta
        while not delta.isEmpty():
            now = old.unionByName(delta)
            found = None
            for r in rules:
                for i in range(len(r.body)):
                    more = bgp.heads(r.head, bgp.evaluate(r.body, [now if j < i else delta if j == i else old for j in range(len(r.body))], distinct=False), r.no_literal)
                    found = more if found is None else found.unionByName(more)
            old = now
            delta = written(found.distinct().join(old, closure.TRIPLE, "left_anti"), "delta")
            fresh = fresh.unionByName(delta)
        return fresh

    return start.unionByName(drained(stream.select(*closure.TRIPLE), each=step, at=at))


def new_patterns(stream: DataFrame, known: DataFrame, rules: Sequence[Rule], classes: Sequence[str] = ("a",), at: str | None = None) -> list[tuple[int, DataFrame]]:
    """Schema alarms: for each batch that shows patterns outside the known ones, the consequence of the wider schema."""
    alarms: list[tuple[int, DataFrame]] = []
    number = iter(range(1 << 60))

    def step(batch: DataFrame, before: DataFrame | None) -> DataFrame:
        now = known.select(*schema.PLACES) if before is None else schema.minimised(known.select(*schema.PLACES).unionByName(before.select(*schema.PLACES)))
        fresh = written(schema.uncovered(schema.profile(batch, classes), now), "alarm")
        n = next(number)
        if not fresh.isEmpty():
            wider = written(schema.minimised(now.unionByName(fresh.select(*schema.PLACES))), "known")
            alarms.append((n, consequence.simple(wider, rules).patterns))
        return fresh

    drained(stream.select(*closure.TRIPLE), each=step, at=at)
    return alarms
