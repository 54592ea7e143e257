"""Quality rules: text statistics as SQL expressions and a learned decision list over them.

The list is learned by sequential covering.  A rule is a conjunction of thresholds that grows by the condition with the
most gain on two thirds of a bounded labelled sample, is pruned on the other third, and is taken if it is precise
there; what it covers is set aside and the next rule is grown.  The rules become ordered conditional expressions.
All rows are judged by DataFrame expressions alone; the driver sees only the statistics of the sample.
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

WHITE = " \t\n\x0b\f\r"
SYMBOLS = "#*$%&|<>"  # fixed value
LEAST_WORDS = 50  # fixed value of the base rule
SAMPLE = 4000  # labelled rows that rules are learned from, at most
PRECISE = 0.95  # of a rule on the rows it is pruned on
COVERS = 0.004  # least share of the sample that a rule covers
CUTS = 24  # thresholds tried for each statistic
CONDITIONS = 4  # of a rule at most
RULES = 12  # in a list at most

#: The statistics that rules may test.
TESTED = ("n_words", "mean_word", "symbol_share", "dup_line_share", "repeat_share", "upper_share", "loud_share", "digit_share")


# -- statistics


def with_statistics(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """``docs`` with the base statistics of each whole text and the shares that rules test.

    Three-word windows are compared by a 64-bit hash of their words; sorting them with their places finds the repeated
    ones in n log n, and a text without repeats is told by the number of distinct ones.  A null text has no words."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    out = docs.withColumn("__t", text)
    out = out.withColumn("__w", F.when(F.btrim("__t", F.lit(WHITE)) == "", F.array().cast("array<string>")).otherwise(F.split(F.btrim("__t", F.lit(WHITE)), "[\\x20\\x09-\\x0D]+")))
    out = out.withColumn("n_words", F.size("__w").cast("long"))
    out = out.withColumn("__g", F.when(F.col("n_words") >= 3, F.transform(F.sequence(F.lit(0), F.greatest(F.lit(0), F.size("__w") - 3)), lambda i: F.xxhash64(F.get("__w", i), F.get("__w", i + 1), F.get("__w", i + 2)))).otherwise(F.array().cast("array<long>")))
    out = out.withColumn("__s", F.when(F.size(F.array_distinct("__g")) < F.size("__g"), F.sort_array(F.transform("__g", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))))
    again = F.filter("__s", lambda x, i: (F.get("__s", i - 1)["h"] == x["h"]) | (F.get("__s", i + 1)["h"] == x["h"]))
    places = F.flatten(F.transform(again, lambda x: F.array(x["i"], x["i"] + 1, x["i"] + 2)))
    out = out.withColumn("n_repeat_words", F.coalesce(F.size(F.array_distinct(places)), F.lit(0)).cast("long"))
    lines = F.filter(F.split("__t", "\n"), lambda x: F.btrim(x, F.lit(WHITE)) != "")
    out = out.withColumn("__l", lines)
    out = out.withColumn("n_dup_lines", (F.size("__l") - F.size(F.array_distinct("__l"))).cast("long"))
    gone = lambda chars: F.length(F.translate("__t", chars, ""))
    out = out.withColumn("__n", F.length("__t"))
    out = out.withColumns({"word_chars": gone(WHITE).cast("long"), "n_symbols": (F.col("__n") - gone(SYMBOLS)).cast("long"), "__loud": F.col("__n") - gone("!?"), "__digits": F.col("__n") - gone("0123456789"), "__upper": F.col("__n") - F.length(F.regexp_replace("__t", "\\p{Lu}", ""))})
    of = lambda a, b: F.col(a).cast("double") / F.greatest(F.lit(1), F.col(b))
    shares = {"mean_word": of("word_chars", "n_words"), "symbol_share": of("n_symbols", "word_chars"), "dup_line_share": F.col("n_dup_lines").cast("double") / F.greatest(F.lit(1), F.size("__l")), "repeat_share": of("n_repeat_words", "n_words"), "upper_share": of("__upper", "word_chars"), "loud_share": of("__loud", "word_chars"), "digit_share": of("__digits", "word_chars")}
    return out.withColumns(shares).drop("__t", "__w", "__g", "__s", "__l", "__n", "__loud", "__digits", "__upper")


def base_failed() -> Column:
    return (F.col("n_words") < LEAST_WORDS) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))


# -- learning


@dataclass(frozen=True)
class Condition:
    name: str
    above: bool  # value > at, else value <= at
    at: float

    def holds(self, row: dict) -> bool:
        return (row[self.name] > self.at) == self.above

    def column(self) -> Column:
        return F.col(self.name) > F.lit(self.at) if self.above else F.col(self.name) <= F.lit(self.at)

    def __str__(self) -> str:
        return f"{self.name} {'>' if self.above else '<='} {self.at:.6g}"


Rule = tuple[Condition, ...]


def covers(rule: Rule, row: dict) -> bool:
    return all(c.holds(row) for c in rule)


def _counts(rule: Rule, rows: list[dict]) -> tuple[int, int]:
    hit = [r["bad"] for r in rows if covers(rule, r)]
    return sum(hit), len(hit) - sum(hit)


def _cuts(rows: list[dict], name: str) -> list[float]:
    values = sorted(r[name] for r in rows)
    return sorted({values[len(values) * i // CUTS] for i in range(1, CUTS)}) if values else []


def _best(rows: list[dict], names: tuple[str, ...] = TESTED) -> Condition | None:
    """The condition with the most information gain on the rows."""
    p0 = sum(r["bad"] for r in rows)
    if not p0 or p0 == len(rows):
        return None
    now = math.log2(p0 / len(rows))
    best: tuple[float, Condition | None] = (0.0, None)
    for name in names:
        for cut in _cuts(rows, name):
            p = n = 0  # above the cut
            for r in rows:
                if r[name] > cut:
                    p, n = p + r["bad"], n + 1
            for above, a, b in ((True, p, n), (False, p0 - p, len(rows) - n)):
                if a and (gain := a * (math.log2(a / b) - now)) > best[0]:
                    best = (gain, Condition(name, above, float(cut)))
    return best[1]


def grow(rows: list[dict], first: Condition) -> Rule:
    """Add the condition with the most gain until no good row is covered."""
    rule: Rule = (first,)
    rows = [r for r in rows if first.holds(r)]
    while len(rule) < CONDITIONS and (more := _best(rows)):
        rule = (*rule, more)
        rows = [r for r in rows if more.holds(r)]
    return rule


def prune(rule: Rule, rows: list[dict]) -> Rule:
    """The shortest beginning of the rule that is worth most on other rows."""

    def worth(r: Rule) -> float:
        p, n = _counts(r, rows)
        return (p - n) / (p + n) if p + n else -1.0

    return max((rule[:k] for k in range(1, len(rule) + 1)), key=lambda r: (worth(r), -len(r)), default=())


def learn(rows: list[dict]) -> list[Rule]:
    """An ordered list of rules that mark bad rows (``bad`` is 0 or 1); rows must come in a stable order."""
    rules: list[Rule] = []
    total = len(rows)
    while len(rules) < RULES:
        growing, pruning = [r for i, r in enumerate(rows) if i % 3], [r for i, r in enumerate(rows) if i % 3 == 0]
        taken: tuple[int, Rule] = (0, ())
        for name in TESTED:  # one rule grown from each statistic; the precise one that covers most is taken
            if first := _best(growing, (name,)):
                rule = prune(grow(growing, first), pruning)
                (p, n), (a, b) = _counts(rule, pruning), _counts(rule, rows)
                if rule and p and p >= PRECISE * (p + n) and a >= PRECISE * (a + b) and a + b >= COVERS * total and a > taken[0]:
                    taken = (a, rule)
        rule = taken[1]
        if not rule:
            break
        rules.append(rule)
        rows = [r for r in rows if not covers(rule, r)]
    return rules


def verdict(rules: list[Rule]) -> Column:
    """The number of the first rule that holds, from 1; null if none does."""
    out = F.lit(None).cast("int")
    for k in range(len(rules), 0, -1):
        out = F.when(reduce(lambda a, b: a & b, (c.column() for c in rules[k - 1])), F.lit(k)).otherwise(out)
    return out


def sampled(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", sample: int = SAMPLE) -> list[dict]:
    """Statistics and marks of at most ``sample`` labelled ids, those with the least hashes (one text of each)."""
    marks = labels.where("doc_id is not null and quality is not null").groupBy(F.col("doc_id").alias("label_id")).agg(F.min("quality").alias("quality"))
    some = marks.orderBy(F.xxhash64("label_id"), "label_id").limit(sample)
    rows = docs.select(F.col(id_col).alias("label_id"), F.col(text_col).alias("text")).join(F.broadcast(some), "label_id").groupBy("label_id", "quality").agg(F.min("text").alias("text"))
    rows = with_statistics(rows).select("label_id", "quality", *TESTED).orderBy(F.xxhash64("label_id"), "label_id", *TESTED)
    return [r.asDict() | {"bad": int(r.quality == 0)} for r in rows.collect()]


def judged(docs: DataFrame, labels: DataFrame, keep: list[str], id_col: str = "doc_id", text_col: str = "text", sample: int = SAMPLE) -> DataFrame:
    """The columns ``keep`` of each row with its statistics, ``base_failed``, the ``rule`` that marks it and ``kept``.

    A narrow pass without shuffle; columns of ``docs`` that are not named are not read, so clashing names do no harm.
    Null and empty texts have no words and fail the base rule; null ids and repeated rows stay; without usable labels
    the list is empty and only the base rule counts; an empty table gives no rows.
    """
    rules = learn(sampled(docs, labels, id_col, text_col, sample))
    rows = docs.select(*(F.col(c).alias(f"c{i}") for i, c in enumerate(keep)), F.col(text_col).alias("text"))
    rows = with_statistics(rows).withColumn("base_failed", base_failed()).withColumn("rule", verdict(rules))
    statistics = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "rule"]
    return rows.select(*(F.col(f"c{i}").alias(c) for i, c in enumerate(keep)), *statistics, (~F.col("base_failed") & F.col("rule").isNull()).alias("kept"))
