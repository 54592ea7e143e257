"""Canonical graphs of a schema: the sandbox and the critical instance."""

from __future__ import annotations

from collections.abc import Mapping, Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tripleschema.model import LAMBDA, Atom, is_literal, is_var
from tripleschema.plans.tables import local


class CriticalInstanceTooLarge(ValueError):
    """The critical instance would have more triples than allowed."""


def sandbox(patterns: DataFrame, fresh: str | None = LAMBDA) -> DataFrame:
    """One triple ``s, p, o`` per pattern, the fresh IRI for each wildcard (null for it if ``fresh`` is None)."""
    place = lambda k, v: F.when(F.col(k).isin("I", "A"), F.lit(fresh)).otherwise(F.col(v)).cast("string")
    return patterns.select(place("s_k", "s_v").alias("s"), place("p_k", "p_v").alias("p"), place("o_k", "o_v").alias("o")).distinct()


def body_constants(atoms: Sequence[Atom]) -> list[str]:
    return list(dict.fromkeys(t for a in atoms for t in a if not is_var(t)))


def constants(patterns: DataFrame, atoms: Sequence[Atom]) -> DataFrame:
    """``c, lit`` of all constants of the patterns and atoms, and the fresh IRI."""
    return _pools(patterns, {"": atoms}).drop("case_id")


def _pools(patterns: DataFrame, bodies: Mapping[str, Sequence[Atom]]) -> DataFrame:
    """``case_id, c, lit``: the constants of the patterns, of each body, and the fresh IRI."""
    spark = patterns.sparkSession
    cases = local(spark, [(k,) for k in bodies], "case_id string")
    own = local(spark, [(k, t) for k, a in bodies.items() for t in [*body_constants(a), LAMBDA]], "case_id string, c string")
    shared = patterns.select(F.explode(F.array("s_v", "p_v", "o_v")).alias("c")).where("c is not null").distinct()
    return cases.crossJoin(shared).unionByName(own).distinct().withColumn("lit", F.col("c").startswith('"'))


def critical_sizes(patterns: DataFrame, bodies: Mapping[str, Sequence[Atom]]) -> dict[str, int]:
    """Triples that the patterns give for each body, before equal ones meet: an upper bound, without building any."""
    n = _pools(patterns, bodies).groupBy("case_id").agg(F.sum((~F.col("lit")).cast("double")).alias("iris"), F.count("*").cast("double").alias("everything"))
    of = lambda k: F.when(F.col(k) == "I", F.col("iris")).when(F.col(k) == "A", F.col("everything")).otherwise(1.0)
    sizes = patterns.crossJoin(n).groupBy("case_id").agg(F.sum(of("s_k") * of("p_k") * of("o_k")).alias("n"))
    return dict.fromkeys(bodies, 0) | {r.case_id: int(r.n) for r in sizes.collect()}


def critical_instances(patterns: DataFrame, bodies: Mapping[str, Sequence[Atom]], limit: int | None = 5_000_000) -> DataFrame:
    """``case_id, s, p, o`` with every wildcard replaced by every admissible constant, literals only where they are free.

    Refused beyond ``limit`` triples for a body: the size is a power of the number of constants."""
    if limit is not None and bodies and (size := max(critical_sizes(patterns, bodies).values())) > limit:
        raise CriticalInstanceTooLarge(f"{size} triples; the limit is {limit}")
    pool = _pools(patterns, bodies)
    out = patterns.crossJoin(local(patterns.sparkSession, [(k,) for k in bodies], "case_id string"))
    for k in "spo":
        choice = pool.select("case_id", F.col("c").alias(f"{k}_c"), F.col("lit").alias(f"{k}_l"))
        wild = out.where(F.col(f"{k}_k").isin("I", "A")).join(choice, "case_id").where(~F.col(f"{k}_l") | (F.col(f"{k}_k") == "A")).drop(f"{k}_l")
        kept = out.where(~F.col(f"{k}_k").isin("I", "A")).withColumn(f"{k}_c", F.col(f"{k}_v"))
        out = kept.unionByName(wild)
    return out.select("case_id", F.col("s_c").alias("s"), F.col("p_c").alias("p"), F.col("o_c").alias("o")).distinct()


def critical_size(patterns: DataFrame, atoms: Sequence[Atom]) -> int:
    return critical_sizes(patterns, {"": atoms})[""]


def critical_instance(patterns: DataFrame, atoms: Sequence[Atom], limit: int | None = 5_000_000) -> DataFrame:
    """The critical instance for one body: ``s, p, o``."""
    return critical_instances(patterns, {"": atoms}, limit).drop("case_id")


def literal_constants(atoms: Sequence[Atom]) -> list[str]:
    return [t for t in body_constants(atoms) if is_literal(t)]
