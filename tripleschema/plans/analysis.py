"""Questions that a consequence answers."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tripleschema.model import Pattern, Rule
from tripleschema.operators.schema import PLACES, Schema, uncovered
from tripleschema.plans import consequence, existential
from tripleschema.plans.tables import local, settled


def applicable(patterns: DataFrame, rules: Sequence[Rule], approach: str = "sandbox") -> DataFrame:
    """``rule_id`` of the rules that some instance triggers, directly or after others."""
    found = consequence.simple(patterns, rules, approach).derived
    spark = patterns.sparkSession
    if found is None:
        return local(spark, [], "rule_id string")
    return found.select(F.col("case_id").alias("rule_id")).distinct()


def applicability_diff(old: DataFrame, new: DataFrame, rules: Sequence[Rule]) -> DataFrame:
    """``rule_id, change``: rules that a schema change makes (in)applicable."""
    a, b = applicable(old, rules).withColumn("x", F.lit(1)), applicable(new, rules).withColumn("y", F.lit(1))
    both = a.join(b, "rule_id", "full").where("x is null or y is null")
    return both.select("rule_id", F.when(F.col("x").isNull(), "gained").otherwise("lost").alias("change"))


def can_derive(patterns: DataFrame, rules: Sequence[Rule], wanted: Pattern) -> DataFrame:
    """``rule_id`` of the rules that can give a triple of a pattern; no rows if none can."""
    found = consequence.simple(patterns, rules).derived
    if found is None:
        return local(patterns.sparkSession, [], "rule_id string")
    meets = F.lit(True)
    for (k, v), (kc, vc) in zip(wanted.places, (("s_k", "s_v"), ("p_k", "p_v"), ("o_k", "o_v")), strict=True):
        if k in "CL":
            meets &= (F.col(vc) == v) | ((F.col(kc) == "I") & F.lit(k == "C")) | (F.col(kc) == "A")
        elif k == "I":
            meets &= F.col(kc) != "L"
    return found.where(meets).select(F.col("case_id").alias("rule_id")).distinct()


@dataclass
class Policy:
    patterns: DataFrame
    kept: tuple[Rule, ...]
    rejected: dict[str, str]


def with_policy(schema: Schema, rules: Sequence[Rule], policy: str = "update_schema") -> Policy:
    """``update_schema`` keeps all rules and changes the schema; ``reject_rules`` keeps the schema and names the rules that
    add a pattern it does not cover or feed a violation."""
    if policy == "update_schema":
        return Policy(consequence.simple(schema.patterns, rules).patterns, tuple(rules), {})
    if policy != "reject_rules":
        raise ValueError(policy)
    derived = consequence.simple(schema.patterns, rules).derived
    rejected: dict[str, str] = {}
    if derived is not None:
        outside = uncovered(derived.select(*PLACES), schema.patterns).distinct()
        key = F.concat_ws("\x01", *(F.coalesce(c, F.lit("\x02")) for c in PLACES))
        adding = derived.select("case_id", key.alias("k")).join(outside.select(key.alias("k")), "k", "left_semi").select("case_id").distinct()
        rejected = {r.case_id: "adds a pattern" for r in adding.collect()}
    for r in existential.explained(schema, rules).select("rule_id", "e_id").distinct().collect():
        rejected[r.rule_id] = "; ".join(filter(None, [rejected.get(r.rule_id), f"breaks {r.e_id}"]))
    return Policy(schema.patterns, tuple(r for r in rules if r.id not in rejected), dict(sorted(rejected.items())))


@dataclass
class Tightness:
    """Predicted patterns that are new, those of them without a witness graph, and whether all bodies were looked at."""

    predicted: DataFrame
    unwitnessed: DataFrame
    complete: bool


def tightness(patterns: DataFrame, rules: Sequence[Rule], approach: str = "sandbox") -> Tightness:
    """Whether each predicted pattern is needed: some graph within the original patterns must give a triple of it.

    Every rule is unfolded to bodies over the original graph.  A mapping of such a body on the canonical graph, grounded
    with fresh IRIs, is an instance whose closure holds the head, so what one application of the unfolded rules gives
    has witnesses; predicted patterns that do not lie below one of those have none."""
    predicted = settled(uncovered(consequence.simple(patterns, rules, approach).patterns, patterns), "predicted")
    unfolded, complete = [], True
    for r in rules:
        more, whole = existential.unfolded_rules(r, rules)
        unfolded += more
        complete &= whole
    if not unfolded:
        return Tightness(predicted, predicted, complete)
    shown = settled(consequence.step(patterns, unfolded).heads.select(*PLACES).distinct(), "witnessed")
    return Tightness(predicted, uncovered(predicted, shown), complete)
