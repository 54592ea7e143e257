"""Stores and text formats for triples."""

from __future__ import annotations

import json
import re
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from tripleschema.model import TRIPLE_SCHEMA, Existential, Rule, existential, rule
from tripleschema.operators.schema import Schema, schema

_LINE = r'^\s*(?:<([^>]*)>|(_:\S+))\s+<([^>]*)>\s+(?:<([^>]*)>|(_:\S+)|"((?:[^"\\]|\\.)*)"(?:@[A-Za-z0-9-]+|\^\^<[^>]*>)?)\s*\.\s*(?:#.*)?$'


def read_ntriples(spark: SparkSession, path: str) -> tuple[DataFrame, DataFrame]:
    """Triples of a line-based text file, and the lines that are none (comments and blank lines aside)."""
    lines = spark.read.text(path).where(~F.col("value").rlike(r"^\s*(#.*)?$"))
    good = F.col("value").rlike(_LINE)
    part = lambda i: F.nullif(F.regexp_extract("value", _LINE, i), F.lit(""))
    lit = F.col("value").rlike(r'^\s*\S+\s+<[^>]*>\s+"')
    plain = F.regexp_replace(F.regexp_replace(F.regexp_extract("value", _LINE, 6), r'\\(["\\])', "$1"), r"\\n", "\n")
    rows = lines.where(good).select(F.coalesce(part(1), part(2)).alias("s"), part(3).alias("p"), F.when(lit, plain).otherwise(F.coalesce(part(4), part(5))).alias("o"), lit.alias("o_lit"))
    return rows, lines.where(~good)


def write_ntriples(triples: DataFrame, path: str) -> None:
    place = lambda c: F.when(F.col(c).startswith("_:"), F.col(c)).otherwise(F.concat(F.lit("<"), F.col(c), F.lit(">")))
    text = F.regexp_replace(F.regexp_replace("o", r'(["\\])', r"\\$1"), "\n", r"\\n")
    o = F.when(F.col("o_lit"), F.concat(F.lit('"'), text, F.lit('"'))).otherwise(place("o"))
    triples.select(F.concat_ws(" ", place("s"), place("p"), o, F.lit(".")).alias("value")).write.text(path)


def write_store(triples: DataFrame, path: str, salt: int = 8) -> None:
    """Parquet by predicate, sorted by subject.  Large predicates are dealt to ``salt`` tasks by a hash of the subject."""
    dealt = triples.withColumn("__salt", F.pmod(F.xxhash64("s"), F.lit(salt)))
    dealt.repartition("p", "__salt").drop("__salt").sortWithinPartitions("p", "s").write.partitionBy("p").parquet(path)


def read_store(spark: SparkSession, path: str) -> DataFrame:
    """A store as a graph; a filter on ``p`` reads those folders only."""
    return spark.read.schema("s string, o string, o_lit boolean, p string").parquet(path).select("s", "p", "o", "o_lit")


def encode(triples: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Triples with 64-bit ids in place of terms, and the dictionary ``id, term``.

    Ids are hashes, so no global numbering is needed; two terms with one id are reported as an error."""
    t = F.when(F.col("o_lit"), F.concat(F.lit('"'), F.col("o"), F.lit('"'))).otherwise(F.col("o"))
    terms = triples.select(F.explode(F.array("s", "p", t)).alias("term")).distinct().select(F.xxhash64("term").alias("id"), "term")
    clash = terms.groupBy("id").agg(F.count("*").alias("n"), F.min("term").alias("a"), F.max("term").alias("b")).where("n > 1").first()
    if clash:
        raise ValueError(f"terms {clash.a!r} and {clash.b!r} have the same id")
    return triples.select(F.xxhash64("s").alias("s"), F.xxhash64("p").alias("p"), F.xxhash64(t).alias("o"), "o_lit"), terms


def decode(ids: DataFrame, terms: DataFrame) -> DataFrame:
    out = ids
    for c in "spo":
        out = out.join(terms.select(F.col("id").alias(c), F.col("term").alias(f"{c}_t")), c)
    text = F.when(F.col("o_lit"), F.expr("substring(o_t, 2, length(o_t) - 2)")).otherwise(F.col("o_t"))
    return out.select(F.col("s_t").alias("s"), F.col("p_t").alias("p"), text.alias("o"), "o_lit")


def to_wide(triples: DataFrame, predicates: list[str]) -> DataFrame:
    """A row per subject with a column per predicate: its least object."""
    return triples.where(F.col("p").isin(*predicates)).groupBy("s").pivot("p", predicates).agg(F.min("o"))


def load_rules(text: str) -> tuple[list[Rule], list[Existential], list[str]]:
    """Rules, existential rules and patterns from a JSON document with these three lists of strings."""
    spec = json.loads(text)
    return [rule(k, v) for k, v in spec.get("rules", {}).items()], [existential(k, v) for k, v in spec.get("existentials", {}).items()], list(spec.get("patterns", []))


def load_schema(spark: SparkSession, text: str) -> Schema:
    _, e, p = load_rules(text)
    return schema(spark, p, e)


class TripleSource(DataSource):
    """``spark.read.format("triples").option("text", ...)``: triples written as rules write them, three terms a line."""

    @classmethod
    def name(cls) -> str:
        return "triples"

    def schema(self) -> str:
        return TRIPLE_SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return _TripleReader(self.options.get("text", ""), int(self.options.get("partitions", "1")))


class _TripleReader(DataSourceReader):
    def __init__(self, text: str, n: int):
        self.lines = [x for x in text.splitlines() if x.strip() and not x.lstrip().startswith("#")]
        self.n = max(1, n)

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(i) for i in range(self.n)]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        for line in self.lines[partition.value :: self.n]:
            found = re.findall(r'"(?:[^"\\]|\\.)*"|\S+', line)
            if len(found) < 3:
                raise ValueError(f"no triple: {line}")
            s, p, o = found[:3]
            yield (s, p, o[1:-1], True) if o.startswith('"') else (s, p, o, False)
