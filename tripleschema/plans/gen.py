"""Synthetic schemas and rules from a stream of integers.

Draws are integer arithmetic on table rows in key order, so any engine can repeat them, and the same functions take
pseudo-random integers for sweeps.  Rules are chains; a head goes from the first subject to the last object; half of the
patterns are bodies of random rules, the others random; existential rules lead from a head to a body atom.
"""

from __future__ import annotations

import random
from collections.abc import Iterator, Sequence
from dataclasses import dataclass
from itertools import count

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tripleschema.model import Atom, Existential, Pattern, Rule, weak_acyclicity
from tripleschema.plans.tables import local


@dataclass(frozen=True)
class Config:
    """pi_c: share of constants; the other figures are numbers of predicates, IRIs, literals, patterns, rules,
    existential rules and body atoms."""

    pi_c: float = 0.1
    n_preds: int = 15
    n_iris: int = 10
    n_lits: int = 10
    n_patterns: int = 10
    n_rules: int = 4
    n_exist: int = 0
    n_body: int = 2


@dataclass(frozen=True)
class Generated:
    patterns: tuple[Pattern, ...]
    rules: tuple[Rule, ...]
    existentials: tuple[Existential, ...]


def numbers(seed: int) -> Iterator[int]:
    rng = random.Random(seed)
    while True:
        yield rng.getrandbits(40)


def repeated(rows: Sequence[int]) -> Iterator[int]:
    """The integers of table rows without an end: each further round multiplies them by the next odd number."""
    if not rows:
        raise ValueError("there are no rows to draw from")
    return (x * k for k in count(1, 2) for x in rows)


def random_pattern(x: int, c: Config) -> Pattern:
    share = round(100 * c.pi_c)
    s = ("C", f"cust:{x // 5 % c.n_iris}") if x // 3 % 100 < share else ("I", None)
    if x // 7 % 100 < share:
        o = ("C", f"cust:{x // 13 % c.n_iris}") if x // 11 % 2 == 0 else ("L", f'"x{x // 13 % c.n_lits}"')
    else:
        o = ("A", None)
    return Pattern(*s, "C", f"m{x % c.n_preds}", *o)


def chain(rule_id: str, preds: list[str]) -> Rule:
    body = tuple(Atom(f"?v{k}", p, f"?v{k + 1}") for k, p in enumerate(preds[:-1]))
    return Rule(rule_id, body, (Atom("?v0", preds[-1], f"?v{len(preds) - 1}"),))


def generate(c: Config, seed: int | Iterator[int] = 0) -> Generated:
    draw = numbers(seed) if isinstance(seed, int) else seed
    rules = tuple(chain(f"r{j}", [f"m{next(draw) % c.n_preds}" for _ in range(c.n_body + 1)]) for j in range(c.n_rules))
    patterns: dict[Pattern, None] = {}
    own = len({a.p for r in rules for a in r.body})  # different patterns that antecedents can give
    while len(patterns) < min(c.n_patterns // 2, own):
        for a in rules[next(draw) % len(rules)].body:
            if len(patterns) < c.n_patterns // 2:
                patterns[Pattern("I", None, "C", a.p, "A", None)] = None
    for _ in range(1000 * c.n_patterns):
        if len(patterns) >= c.n_patterns:
            break
        patterns[random_pattern(next(draw), c)] = None
    existentials: list[Existential] = []
    for _ in range(200 * c.n_exist if rules else 0):
        if len(existentials) >= c.n_exist:
            break
        head = rules[next(draw) % len(rules)].head[0]
        body = rules[next(draw) % len(rules)].body
        e = Existential(f"e{len(existentials)}", head, body[next(draw) % len(body)])
        if weak_acyclicity([*existentials, e])[0]:
            existentials.append(e)
    if len(patterns) < c.n_patterns or len(existentials) < c.n_exist:
        raise ValueError(f"only {len(patterns)} patterns and {len(existentials)} existential rules are possible: {c}")
    return Generated(tuple(patterns), rules, tuple(existentials))


# -- from table rows


def draws(lineitem: DataFrame, n: int) -> DataFrame:
    """``i, x``: an integer from each of the first ``n`` rows in key order."""
    key = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]
    first = lineitem.select(*key).orderBy(*key).limit(n)
    from pyspark.sql import Window

    x = F.col("l_orderkey") * 7919 + F.col("l_partkey") * 104729 + F.col("l_suppkey") * 1299709 + F.col("l_linenumber") * 15485863
    return first.select((F.row_number().over(Window.orderBy(*key)) - 1).cast("long").alias("i"), x.alias("x"))


def pattern_rows(drawn: DataFrame, c: Config) -> DataFrame:
    """Random patterns as a table, one for each draw, by the same arithmetic."""
    share, x = round(100 * c.pi_c), F.col("x")
    over = lambda k, n: F.expr(f"(x div {k}) % {n}")
    fixed_s, fixed_o, is_iri = over(3, 100) < share, over(7, 100) < share, over(11, 2) == 0
    name = lambda prefix, n, tail="": F.concat(F.lit(prefix), over(n[0], n[1]).cast("string"), F.lit(tail))
    return drawn.select(
        "i",
        F.when(fixed_s, "C").otherwise("I").alias("s_k"),
        F.when(fixed_s, name("cust:", (5, c.n_iris))).alias("s_v"),
        F.lit("C").alias("p_k"),
        F.concat(F.lit("m"), (x % c.n_preds).cast("string")).alias("p_v"),
        F.when(fixed_o & is_iri, "C").when(fixed_o, "L").otherwise("A").alias("o_k"),
        F.when(fixed_o & is_iri, name("cust:", (13, c.n_iris))).when(fixed_o, name('"x', (13, c.n_lits), '"')).alias("o_v"),
    )


def rule_rows(spark: SparkSession, rules: tuple[Rule, ...]) -> DataFrame:
    return local(spark, [(r.id, str(r)) for r in rules], "rule_id string, rule string")
