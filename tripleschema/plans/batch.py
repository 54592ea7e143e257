"""Many bodies at once on a small canonical graph.

Bodies are rows: each atom has its constants, the numbers of its variables and one variable that it shares with the
atoms before.  One plan then evaluates all bodies of a rule set, however many there are, with one join per atom place.
A mapping is an array with a binding per variable; null stands for the fresh IRI.  A join on something that may be a
wildcard (equal, or either side null) becomes an equality join: one side has a key, the value or a star, and the other
has a row for each key that it fits.  Only an atom whose predicate is a variable meets every triple, as it has to; the
atoms of a rule set are then broadcast, up to BROADCAST of them.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tripleschema.model import LAMBDA, Atom, Rule, is_var
from tripleschema.operators.bgp import ordered
from tripleschema.plans.tables import local, settled

ATOMS = "case_id string, k int, n int, width int, link int, s_c string, s_i int, p_c string, p_i int, o_c string, o_i int"
#: Atoms up to which they are broadcast to the triples that they all meet; more of them are shuffled by subject.
BROADCAST = 20_000
ANY = "*"
HEADS = "case_id string, s_c string, s_i int, p_c string, o_c string, o_i int"


@dataclass
class Cases:
    """Bodies and heads of rules as tables."""

    atoms: DataFrame
    heads: DataFrame
    firm: DataFrame  # case_id, firm: numbers of the variables that cannot be literals
    longest: int
    variables: dict[str, list[str]]
    n_free: int  # atoms with a variable predicate


def cases(spark: SparkSession, rules: Sequence[Rule]) -> Cases:
    atoms, heads, firm, variables = [], [], [], {}
    for r in rules:
        names = r.variables()
        number = {v: i for i, v in enumerate(names)}
        variables[r.id] = names
        place = lambda t, number=number: (None, number[t]) if is_var(t) else (t, -1)
        bound: set[str] = set()
        for k, i in enumerate(ordered(r.body)):
            a = r.body[i]
            link = next((number[v] for v in a.variables() if v in bound), -1)
            atoms.append((r.id, k, len(r.body), len(names), link, *place(a.s), *place(a.p), *place(a.o)))
            bound |= set(a.variables())
        heads += [(r.id, *place(h.s), h.p, *place(h.o)) for h in r.head]
        firm.append((r.id, sorted(number[v] for v in r.firm() if v in number)))
    return Cases(local(spark, atoms, ATOMS), local(spark, heads, HEADS), local(spark, firm, "case_id string, firm array<int>"), max((len(r.body) for r in rules), default=0), variables, sum(is_var(a.p) for r in rules for a in r.body))


def _matches(atoms: DataFrame, graph: DataFrame, by_case: bool, n_free: int) -> DataFrame:
    """Bindings of single atoms; a null place of a triple stands for anything that an atom asks."""
    g = graph.withColumn("key", F.coalesce("p", F.lit(ANY))).alias("g")
    a = atoms.alias("a")
    same = (F.col("a.case_id") == F.col("g.case_id")) if by_case else F.lit(True)
    fits = lambda c: F.col(f"a.{c}_c").isNull() | F.col(f"g.{c}").isNull() | (F.col(f"a.{c}_c") == F.col(f"g.{c}"))
    agree = lambda x, y: (F.col(f"a.{x}_i") < 0) | (F.col(f"a.{x}_i") != F.col(f"a.{y}_i")) | F.col(f"g.{x}").isNull() | F.col(f"g.{y}").isNull() | (F.col(f"g.{x}") == F.col(f"g.{y}"))
    rest = same & fits("s") & fits("o") & agree("s", "p") & agree("s", "o") & agree("p", "o")
    fixed = atoms.where("p_c is not null").withColumn("key", F.explode(F.array("p_c", F.lit(ANY)))).alias("a")
    parts = [fixed.join(g, (F.col("a.key") == F.col("g.key")) & rest)]
    if n_free:
        free = a.where(F.col("a.p_c").isNull())
        parts.append((F.broadcast(free) if n_free <= BROADCAST else free).join(g, rest))
    bind = F.transform(F.sequence(F.lit(0), F.col("a.width") - 1), lambda i: F.coalesce(*(F.when(F.col(f"a.{c}_i") == i, F.col(f"g.{c}")) for c in "spo")))
    bind = F.when(F.col("a.width") > 0, bind).otherwise(F.array().cast("array<string>"))
    chosen = [p.select(F.col("a.case_id").alias("case_id"), F.col("a.k").alias("k"), F.col("a.n").alias("n"), F.col("a.link").alias("link"), bind.alias("b")) for p in parts]
    return reduce(DataFrame.unionByName, chosen).distinct()


def evaluate(c: Cases, graph: DataFrame, by_case: bool = False) -> DataFrame:
    """``case_id, b`` of all mappings of all bodies.  ``graph`` has ``s, p, o``; with ``by_case`` one graph per case."""
    found = _matches(c.atoms, graph, by_case, c.n_free)
    found = settled(found, "matches") if c.longest > 1 else found
    state = found.where("k = 0").select("case_id", "n", "b")
    for k in range(1, c.longest):
        # equal or either side null: the right has a key, the left each key that it fits; a null on the left fits all, so
        # both sides have a second row under a common key for those
        right = found.where(F.col("k") == k).select(F.col("case_id").alias("c2"), F.col("b").alias("b2"), F.when(F.col("link") >= 0, F.get("b", F.col("link"))).alias("key"))
        left = state.where(F.col("n") > k)
        link = c.atoms.where(F.col("k") == k).select(F.col("case_id").alias("c2"), "link")
        left = left.join(link, F.col("case_id") == F.col("c2")).select("case_id", "n", "b", F.when(F.col("link") >= 0, F.get("b", F.col("link"))).alias("own"))
        right = right.withColumn("rk", F.explode(F.array(F.concat(F.lit("="), F.coalesce("key", F.lit(""))), F.lit(ANY))))
        left = left.withColumn("lk", F.explode(F.when(F.col("own").isNull(), F.array(F.lit(ANY))).otherwise(F.array(F.concat(F.lit("="), "own"), F.lit("=")))))
        joined = left.join(right, (F.col("case_id") == F.col("c2")) & (F.col("lk") == F.col("rk")))
        agree = F.forall(F.zip_with("b", "b2", lambda x, y: x.isNull() | y.isNull() | (x == y)), lambda x: x)
        merged = joined.where(agree).select("case_id", "n", F.zip_with("b", "b2", lambda x, y: F.coalesce(x, y)).alias("b"))
        state = state.where(F.col("n") <= k).unionByName(merged).distinct()
        if k < c.longest - 1:
            state = settled(state, "mappings")  # else the plan would triple with each atom
    return state.select("case_id", "b").distinct()


def as_null(mappings: DataFrame) -> DataFrame:
    """Mappings on a graph that holds the fresh IRI itself, with null for it."""
    return mappings.withColumn("b", F.transform("b", lambda x: F.when(x != LAMBDA, x))).distinct()


def filtered(c: Cases, mappings: DataFrame, patterns: DataFrame) -> DataFrame:
    """``case_id, b, firm`` of the mappings that respect where literals may stand.

    For each atom the patterns that could have enabled it under the mapping are found.  A literal needs one with that
    literal or a free object; a variable at the fresh IRI stays free only if every atom that has it as its object is
    enabled by a free object.  ``firm`` holds the variables that cannot be literals."""
    value = lambda x: F.coalesce(F.col(f"{x}_c"), F.when(F.col(f"{x}_i") >= 0, F.get("b", F.col(f"{x}_i"))))
    asked = mappings.join(c.atoms, "case_id").select("case_id", "b", "k", "o_i", value("s").alias("ms"), value("p").alias("mp"), value("o").alias("mo"))
    place = lambda k, v, m: F.col(k).isin("I", "A") | (F.col(v) == F.col(m))
    rest = place("s_k", "s_v", "ms") & place("o_k", "o_v", "mo")
    asked = asked.withColumn("ak", F.explode(F.when(F.col("mp").isNull(), F.array(F.lit(ANY))).otherwise(F.array("mp", F.lit(ANY)))))
    enabled = asked.join(patterns.withColumn("pk", F.when(F.col("p_k") == "C", F.col("p_v")).otherwise(ANY)), (F.col("ak") == F.col("pk")) & rest)
    free = enabled.groupBy("case_id", "b", "k", "o_i", "mo").agg(F.bool_or((F.col("o_k") == "A") | ((F.col("o_k") == "L") & (F.col("o_v") == F.col("mo")))).alias("ok"), F.bool_or(F.col("o_k") == "A").alias("any"))
    per = free.groupBy("case_id", "b").agg(
        F.bool_or(F.coalesce(F.col("mo").startswith('"'), F.lit(False)) & ~F.coalesce("ok", F.lit(False))).alias("barred"),
        F.collect_set(F.when(F.col("mo").isNull() & (F.col("o_i") >= 0) & ~F.col("any"), F.col("o_i"))).alias("bound"),
    )
    kept = per.where("not barred").join(c.firm, "case_id").withColumn("firm", F.array_sort(F.array_distinct(F.concat("firm", "bound"))))
    return kept.where(~F.exists("firm", lambda i: F.coalesce(F.get("b", i).startswith('"'), F.lit(False)))).select("case_id", "b", "firm")


def expanded(c: Cases, kept: DataFrame) -> DataFrame:
    """``case_id`` and the head patterns of filtered mappings; the fresh IRI becomes a wildcard again."""
    bound = lambda x: F.when(F.col(f"{x}_i") >= 0, F.get("b", F.col(f"{x}_i"))).otherwise(F.col(f"{x}_c"))
    rows = kept.join(c.heads, "case_id").select("case_id", bound("s").alias("s_v"), F.col("p_c").alias("p_v"), bound("o").alias("o_v"), F.array_contains("firm", F.col("o_i")).alias("no_literal"))
    o_kind = F.when(F.col("o_v").isNull(), F.when(F.col("no_literal"), "I").otherwise("A")).when(F.col("o_v").startswith('"'), "L").otherwise("C")
    return rows.select("case_id", F.when(F.col("s_v").isNull(), "I").otherwise("C").alias("s_k"), "s_v", F.lit("C").alias("p_k"), "p_v", o_kind.alias("o_k"), "o_v").distinct()


def body_rule(case_id: str, body: Sequence[Atom]) -> Rule:
    """A body alone, as a case."""
    return Rule(case_id, tuple(body), ())
