"""The two published sweeps, and two more, on generated schemas."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

from pyspark.sql import DataFrame, SparkSession

from tripleschema.operators.schema import frame, schema
from tripleschema.plans import canon, consequence, existential
from tripleschema.plans.gen import Config, Generated, generate, repeated
from tripleschema.plans.metrics import Timing, timed
from tripleschema.plans.tables import local, written


def growing_schema(n: int, n_body: int = 2) -> Config:
    """First sweep: 1.5 predicates a pattern, a tenth constants, four rules, no existential rules."""
    return Config(pi_c=0.1, n_preds=max(1, 3 * n // 2), n_iris=n, n_lits=n, n_patterns=n, n_rules=4, n_exist=0, n_body=n_body)


def growing_existentials(n: int, size: int = 100) -> Config:
    """Second sweep: 100 patterns, 110 predicates, 20 rules."""
    return Config(pi_c=0.1, n_preds=size * 11 // 10, n_iris=size, n_lits=size, n_patterns=size, n_rules=20, n_exist=n, n_body=2)


def _patterns(spark: SparkSession, g: Generated):
    return written(frame(spark, g.patterns), "generated")


def schema_sweep(spark: SparkSession, sizes: Sequence[int], approaches: Sequence[str] = ("sandbox", "critical"), seed: int = 0, runs: int = 1, n_body: int = 2, timeout_s: float = 600, limit: int | None = 5_000_000, counted: bool = False) -> Iterator[tuple[int, str, Timing]]:
    """Time of the simple consequence as the schema grows.  An approach that was cut off or refused is left out after."""
    out: set[str] = set()
    for n in sizes:
        g = generate(growing_schema(n, n_body), seed)
        p = _patterns(spark, g)
        for a in approaches:
            if a in out:
                continue
            try:
                t = timed(f"{a} n={n}", lambda p=p, g=g, a=a: consequence.simple(p, g.rules, a, limit, counted=counted), runs, timeout_s, spark)
            except canon.CriticalInstanceTooLarge:
                t = Timing(f"{a} n={n}", None, 0)
            if t.seconds is None:
                out.add(a)
            yield n, a, t


def existential_sweep(spark: SparkSession, counts: Sequence[int], seed: int = 0, runs: int = 1, size: int = 100, drawn: Sequence[int] | None = None) -> Iterator[tuple[int, str, Timing]]:
    """Time of the simple consequence, and of what existential rules add to it, as their number grows.

    Schemas and rules come from the integers ``drawn`` from a table's rows, if given, else from the seed."""
    for n in counts:
        g = generate(growing_existentials(n, size), seed if drawn is None else repeated(drawn))
        s = schema(spark, g.patterns, g.existentials)
        yield n, "con", timed(f"con e={n}", lambda s=s, g=g: consequence.simple(s.patterns, g.rules), runs, spark=spark)
        yield n, "con_ex", timed(f"con_ex e={n}", lambda s=s, g=g: (consequence.simple(s.patterns, g.rules), existential.retained(s, g.rules)), runs, spark=spark)


def body_sweep(spark: SparkSession, atoms: Sequence[int], n: int = 30, seed: int = 0) -> Iterator[tuple[int, str, Timing]]:
    for k in atoms:
        for row in schema_sweep(spark, [n], ("sandbox",), seed, n_body=k):
            yield k, row[1], row[2]


def schema_sweep_table(spark: SparkSession, sizes: Sequence[int] = (5, 20, 35), runs: int = 2, timeout_s: float = 600) -> DataFrame:
    """The first published experiment: mean seconds by size and approach (null beyond the cut-off), with the rounds, the
    mappings before and after the filter, and the patterns."""
    rows = []
    for n, approach, t in schema_sweep(spark, sizes, runs=runs, timeout_s=timeout_s, counted=True):
        c = t.result
        of = lambda k, c=c: sum(x[k] for x in c.counters) if c else None
        rows.append((n, approach, t.runs, t.seconds, c.rounds if c else None, of("mappings"), of("kept"), c.patterns.count() if c else None))
    return local(spark, rows, "size int, approach string, runs int, seconds double, rounds int, mappings long, kept long, patterns long")


def existential_sweep_table(spark: SparkSession, counts: Sequence[int] = (0, 100, 200), runs: int = 2, size: int = 100, drawn: Sequence[int] | None = None) -> DataFrame:
    """The second published experiment: mean seconds without and with existential rules, the bodies and witnesses looked at,
    and the rules that are lost."""
    rows = []
    for n, kind, t in existential_sweep(spark, counts, runs=runs, size=size, drawn=drawn):
        found = t.result[1] if kind == "con_ex" and t.result else None
        rows.append((n, kind, t.runs, t.seconds, *((found.bodies, found.witnesses, len(found.violated), len(found.undecided)) if found else (None,) * 4)))
    return local(spark, rows, "existentials int, kind string, runs int, seconds double, bodies long, witnesses long, violated long, undecided long")
