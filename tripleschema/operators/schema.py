"""Schemas as data: pattern tables, their order, normal form and differences."""

from __future__ import annotations

from collections.abc import Iterable, Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tripleschema.model import PATTERN_SCHEMA, Existential, Pattern, pattern
from tripleschema.plans.tables import local

PLACES = ["s_k", "s_v", "p_k", "p_v", "o_k", "o_v"]


@dataclass(frozen=True)
class Schema:
    """Patterns, each with its no-literal places, and existential rules."""

    patterns: DataFrame
    existentials: tuple[Existential, ...] = ()
    undecided: tuple[str, ...] = ()

    def vocabulary(self) -> DataFrame:
        """The predicates that triples may have (null for any)."""
        return self.patterns.select(F.when(F.col("p_k") == "C", F.col("p_v")).alias("p")).distinct()


def frame(spark: SparkSession, patterns: Iterable[Pattern | str]) -> DataFrame:
    rows = [tuple(pattern(p) if isinstance(p, str) else p) for p in patterns]
    return local(spark, list(dict.fromkeys(rows)), PATTERN_SCHEMA)


def schema(spark: SparkSession, patterns: Iterable[Pattern | str], existentials: Sequence[Existential] = ()) -> Schema:
    return Schema(frame(spark, patterns), tuple(existentials))


def below(a: str = "a", b: str = "b") -> Column:
    """Whether pattern row ``a`` lies below ``b``, predicates aside."""
    subject = (F.col(f"{b}.s_k") == "I") | (F.col(f"{a}.s_v") == F.col(f"{b}.s_v"))
    obj = (F.col(f"{b}.o_k") == "A") | ((F.col(f"{b}.o_k") == "I") & F.col(f"{a}.o_k").isin("C", "I")) | (F.col(f"{a}.o_v") == F.col(f"{b}.o_v"))
    return subject & obj


def has_free_predicates(patterns: DataFrame) -> bool:
    return not patterns.where("p_k != 'C'").isEmpty()


def uncovered(patterns: DataFrame, by: DataFrame, strictly: bool = False, free: bool | None = None) -> DataFrame:
    """The patterns that lie below no single pattern of ``by``: an anti-join within each predicate.

    ``free`` tells whether ``by`` has patterns with any predicate (looked up, if not given).  Those are met by equal
    subjects or objects; the few without either constant are broadcast, as there are two of them at most."""
    a = patterns.alias("a")
    differs = F.lit(True) if not strictly else ~(F.struct(*(F.col(f"a.{c}") for c in PLACES)).eqNullSafe(F.struct(*(F.col(f"b.{c}") for c in PLACES))))
    left = a.join(by.where("p_k = 'C'").alias("b"), (F.col("a.p_v") == F.col("b.p_v")) & below() & differs, "left_anti")
    if not (has_free_predicates(by) if free is None else free):
        return left
    rest = by.where("p_k != 'C'")
    for some, on in ((rest.where("s_k = 'C'"), "s_v"), (rest.where("s_k != 'C' and o_k in ('C', 'L')"), "o_v")):
        left = left.alias("a").join(some.alias("b"), (F.col(f"a.{on}") == F.col(f"b.{on}")) & below() & differs, "left_anti")
    wild = F.broadcast(rest.where("s_k != 'C' and o_k not in ('C', 'L')").select(*PLACES).distinct())
    return left.alias("a").join(wild.alias("b"), below() & differs, "left_anti")


def minimised(patterns: DataFrame, free: bool | None = None) -> DataFrame:
    """The patterns that are not strictly below another: a unique normal form."""
    distinct = patterns.select(*PLACES).distinct()
    return uncovered(distinct, distinct, strictly=True, free=free)


def covers(a: DataFrame, b: DataFrame) -> bool:
    """Whether every instance of the patterns ``b`` is one of ``a``."""
    return uncovered(b, a).isEmpty()


def equivalent(a: DataFrame, b: DataFrame) -> bool:
    """Whether two pattern tables model the same graphs."""
    return covers(a, b) and covers(b, a)


def difference(old: DataFrame, new: DataFrame) -> DataFrame:
    """All patterns of both with ``change``: added, removed or kept."""
    a, b = old.select(*PLACES).distinct(), new.select(*PLACES).distinct()
    key = lambda d: F.concat_ws("\x01", *(F.coalesce(d[c], F.lit("\x02")) for c in PLACES))
    a, b = a.withColumn("k", key(a)).alias("a"), b.withColumn("k", key(b)).alias("b")
    both = a.join(b, F.col("a.k") == F.col("b.k"), "full")
    change = F.when(F.col("a.k").isNull(), "added").when(F.col("b.k").isNull(), "removed").otherwise("kept")
    return both.select(*(F.when(F.col("b.k").isNull(), F.col(f"a.{c}")).otherwise(F.col(f"b.{c}")).alias(c) for c in PLACES), change.alias("change"))


def rendered(patterns: DataFrame) -> DataFrame:
    """``pattern`` as text, ``*`` for any IRI and ``**`` for any term."""
    place = lambda k, v: F.when(F.col(k) == "I", "*").when(F.col(k) == "A", "**").otherwise(F.col(v))
    return patterns.select(F.concat_ws(" ", place("s_k", "s_v"), place("p_k", "p_v"), place("o_k", "o_v")).alias("pattern"))


def profile(triples: DataFrame, classes: Sequence[str] = ("a",)) -> DataFrame:
    """The schema of a graph: a pattern per predicate, per predicate and object for the predicates ``classes``.

    A predicate's objects are free if any of them is a literal.  One aggregation, pre-summed in each task."""
    constant = F.when(F.col("p").isin(*classes) & ~F.col("o_lit"), F.col("o"))
    rows = triples.groupBy("p", constant.alias("o_v")).agg(F.bool_or("o_lit").alias("lit"))
    kind = F.when(F.col("o_v").isNotNull(), "C").when(F.col("lit"), "A").otherwise("I")
    return rows.select(F.lit("I").alias("s_k"), F.lit(None).cast("string").alias("s_v"), F.lit("C").alias("p_k"), F.col("p").alias("p_v"), kind.alias("o_k"), "o_v")
