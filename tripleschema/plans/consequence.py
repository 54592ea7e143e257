"""Schema consequences: what closed instances of a schema can contain."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field

from pyspark.sql import DataFrame

from tripleschema.model import Rule
from tripleschema.operators.schema import PLACES, Schema, has_free_predicates, minimised, uncovered
from tripleschema.plans import batch, canon
from tripleschema.plans.tables import settled, written


@dataclass
class Step:
    """One evaluation of all rules on a schema."""

    cases: batch.Cases
    mappings: DataFrame
    kept: DataFrame
    heads: DataFrame


def step(patterns: DataFrame, rules: Sequence[Rule], approach: str = "sandbox", limit: int | None = 5_000_000) -> Step:
    """Mappings of all rules on the canonical graph, the filtered ones, and the patterns they give.

    ``sandbox`` evaluates on one graph with a triple per pattern, wildcards matching anything; ``critical`` evaluates each
    rule plainly on its own graph with every wildcard replaced in all ways, and is refused beyond ``limit`` triples."""
    c = batch.cases(patterns.sparkSession, rules)
    if approach == "sandbox":
        mappings = batch.evaluate(c, canon.sandbox(patterns, None))
    elif approach == "critical":
        graph = written(canon.critical_instances(patterns, {r.id: r.body for r in rules}, limit), "critical")
        mappings = batch.as_null(batch.evaluate(c, graph, by_case=True))
    else:
        raise ValueError(approach)
    kept = batch.filtered(c, mappings, patterns)
    return Step(c, mappings, kept, batch.expanded(c, kept))


def basic(patterns: DataFrame, rule: Rule, approach: str = "sandbox", limit: int | None = 5_000_000) -> DataFrame:
    """The patterns of the instances of ``patterns`` after one application of a rule."""
    return patterns.select(*PLACES).unionByName(step(patterns, [rule], approach, limit).heads.select(*PLACES)).distinct()


@dataclass
class Consequence:
    patterns: DataFrame
    rounds: int
    counters: list[dict[str, int]] = field(default_factory=list)
    derived: DataFrame | None = None  # case_id and the patterns it gave, of all rounds


def simple(patterns: DataFrame, rules: Sequence[Rule], approach: str = "sandbox", limit: int | None = 5_000_000, max_rounds: int = 10_000, counted: bool = False) -> Consequence:
    """The patterns of all subsets of all closures of instances, minimised.

    Each round evaluates all rules at once and keeps what no single pattern covers yet; it ends when nothing is left.
    Covered patterns are dropped in every round, so both approaches stay as small as they can and end alike.  With
    ``counted`` the counters of each round also hold the mappings before and after the filter."""
    free = has_free_predicates(patterns)  # heads have none
    now = settled(minimised(patterns, free), "patterns")
    out = Consequence(now, 0)
    if not rules:
        return out
    while out.rounds < max_rounds:
        done = step(now, rules, approach, limit)
        if counted:
            mappings, kept = settled(done.mappings, "mappings"), settled(done.kept, "kept")
            counters = {"mappings": mappings.count(), "kept": kept.count()}
        heads = settled(done.heads, "heads")
        new = settled(minimised(uncovered(heads.select(*PLACES).distinct(), now, free=free), False), "new-patterns")
        n = new.count()
        out.rounds += 1
        out.counters.append({"round": out.rounds, "added": n} | (counters if counted else {}))
        out.derived = heads if out.derived is None else settled(out.derived.unionByName(heads).distinct(), "derived")
        if not n:
            break
        now = settled(minimised(now.unionByName(new), free), "patterns")
        out.patterns = now
    return out


def existential_preserving(schema: Schema, rules: Sequence[Rule], approach: str = "sandbox", **options) -> Schema:
    """The consequence with the existential rules that no closure can break; ``undecided`` names those that are left out
    because no bounded search could tell (see ``existential.retained``)."""
    from tripleschema.plans import existential

    found = simple(schema.patterns, rules, approach)
    kept = existential.retained(schema, rules, **options)
    return Schema(found.patterns, kept.retained, kept.undecided)
