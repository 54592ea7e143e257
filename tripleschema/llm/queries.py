"""The registered queries of the training-data operators: each reads whole tables and derives digests from its operator."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tripleschema.llm import bpe, decontam, html_layout, passages, quality, rules, secrets, simhash, tokenfile
from tripleschema.llm.common import shared_dir, table

Query = Callable[[SparkSession, str], DataFrame]


def tokenizer_file(name: str = "byte_bpe_50k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_html_layout(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_layout.extracted(table(spark, sf_dir, "pages"))


def op2_bpe_trie(spark: SparkSession, sf_dir: str) -> DataFrame:
    ids = bpe.encode(table(spark, sf_dir, "documents"), tokenizer_file(), decoded=True)
    return ids.select("doc_id", "n_tokens", F.sha2("ids", 256).alias("ids_sha256"), F.sha2(F.col("decoded").cast("binary"), 256).alias("decoded_sha256"))


def op7_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def _named(spans) -> Column:
    """kind:start:end of each span, comma-joined."""
    kinds = F.array(*map(F.lit, secrets.KINDS))
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.element_at(kinds, s["kind"] + 1), s["start"], s["stop"])), ",")


def op8_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").withColumn("repo", F.concat_ws("/", "source", "lang"))
    found = secrets.scan(docs, repo_col="repo")
    of_kind = lambda k: F.size(F.filter("spans", lambda s: s["kind"] == k)).cast("long")
    number = [of_kind(k).alias(f"n_{name}") for k, name in enumerate(secrets.BASE)]
    base = F.filter("spans", lambda s: s["kind"] < len(secrets.BASE))
    live = F.size(F.filter("spans", lambda s: s["verdict"] == "live")).cast("long").alias("n_live")
    return found.select("doc_id", *number, F.sha2(_named(base).cast("binary"), 256).alias("base_sha256"), _named(F.col("spans")).alias("spans"), live)


def op9_huffman(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = f"{shared_dir(spark)}/huffman-{uuid.uuid4().hex}"
    tokenfile.write_tokens(table(spark, sf_dir, "documents"), tokenizer_file(), path, end_id=2)
    return tokenfile.read_tokens(spark, path)


def op10_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = f"{shared_dir(spark)}/flat-{uuid.uuid4().hex}"
    found = tokenfile.token_counts(table(spark, sf_dir, "documents"), tokenizer_file(), path, end_id=50256)
    return found.select("doc_id", "n_tokens")


def op3_passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return passages.shared_passages(table(spark, sf_dir, "documents"))


def op4_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.contaminated(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op5_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.scored(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), ["doc_id"])


def op6_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = rules.judged(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), ["doc_id"])
    return found.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "rule")


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


# -- parts of the operators that SQL can express


def rule_statistics(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The statistics of op6 before any rule is learned."""
    rows = rules.with_statistics(table(spark, sf_dir, "documents")).withColumn("base_failed", rules.base_failed())
    return rows.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed")


_WORDS = "SELECT doc_id, coalesce(text, '') AS t, list_filter(regexp_split_to_array(coalesce(text, ''), '[ \\t\\n\\x0B\\f\\r]+'), lambda x: x <> '') AS w FROM documents"
_RULE_STATISTICS = f"""WITH d AS ({_WORDS}), e AS (SELECT doc_id, unnest(w) AS x, generate_subscripts(w, 1) AS i FROM d),
g AS (SELECT doc_id, i, x || ' ' || lead(x) OVER o || ' ' || lead(x, 2) OVER o AS k FROM e WINDOW o AS (PARTITION BY doc_id ORDER BY i)),
again AS (SELECT doc_id, i FROM (SELECT *, count(*) OVER (PARTITION BY doc_id, k) AS c FROM g WHERE k IS NOT NULL) WHERE c > 1),
covered AS (SELECT doc_id, count(DISTINCT i + j) AS n FROM again, (VALUES (0), (1), (2)) v(j) GROUP BY doc_id),
l AS (SELECT doc_id, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^ \t\n\x0B\f\r]')) AS lines FROM d),
s AS (SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(list_sum(list_transform(w, lambda x: length(x))), 0) AS BIGINT) AS word_chars,
  CAST(length(regexp_replace(t, '[^#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols, CAST(len(lines) - len(list_distinct(lines)) AS BIGINT) AS n_dup_lines, coalesce(n, 0) AS n_repeat_words
  FROM d JOIN l USING (doc_id) LEFT JOIN covered USING (doc_id))
SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM s"""


def secret_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The numbers of base spans of op8."""
    return op8_secrets(spark, sf_dir).select("doc_id", "n_assign", "n_access", "n_hex")


_LONGER = lambda pattern, group, least: f"CAST(len(list_filter(regexp_extract_all(coalesce(text, ''), '{pattern}', {group}), lambda x: length(x) >= {least})) AS BIGINT)"
_ASSIGN = '(?i:password|passwd|secret|token|api_?key)["\'\']?\\x20*[:=]\\x20*["\'\']?([A-Za-z0-9+/_.=-]+)'
_SECRET_COUNTS = f"SELECT doc_id, {_LONGER(_ASSIGN, 1, 12)} AS n_assign, {_LONGER('AKIA[A-Z0-9]+', 0, 18)} AS n_access, {_LONGER('[0-9a-f]+', 0, 16)} AS n_hex FROM documents"


def near_copies(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The documents that the near-dedup stage of the pipeline leaves of the whole table."""
    from tripleschema.llm import nearcopies

    return nearcopies.representatives(table(spark, sf_dir, "documents")).select("doc_id")


_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_NEAR_COPIES = f"""WITH RECURSIVE d AS ({_WORDS.replace("coalesce(text, '')", f"translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}')")}),
e AS (SELECT doc_id, unnest(w) AS x, generate_subscripts(w, 1) AS i FROM d WHERE len(w) >= 5),
s AS (SELECT DISTINCT doc_id, k FROM (SELECT doc_id, x || ' ' || lead(x) OVER o || ' ' || lead(x, 2) OVER o || ' ' || lead(x, 3) OVER o || ' ' || lead(x, 4) OVER o AS k FROM e WINDOW o AS (PARTITION BY doc_id ORDER BY i)) WHERE k IS NOT NULL
  UNION ALL SELECT doc_id, list_aggregate(w, 'string_agg', ' ') FROM d WHERE len(w) BETWEEN 1 AND 4 UNION ALL SELECT doc_id, '' FROM d WHERE len(w) = 0),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
pairs AS (SELECT x, y FROM (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM s a JOIN s b ON a.k = b.k AND a.doc_id < b.doc_id GROUP BY 1, 2) JOIN n p ON p.doc_id = x JOIN n q ON q.doc_id = y WHERE 5 * c >= 4 * (p.n + q.n - c)),
met AS (SELECT x, y FROM pairs UNION SELECT y, x FROM pairs),
reach(a, b) AS (SELECT x, y FROM met UNION SELECT r.a, m.y FROM reach r JOIN met m ON m.x = r.b)
SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT a FROM reach WHERE b < a)"""


_QUERIES: dict[str, Query] = {
    "op1_html_layout": op1_html_layout,
    "op2_bpe_trie": op2_bpe_trie,
    "op3_passages": op3_passages,
    "op4_decontamination": op4_decontamination,
    "op5_quality": op5_quality,
    "op6_quality_rules": op6_quality_rules,
    "op7_simhash": op7_simhash,
    "op8_secrets": op8_secrets,
    "op9_huffman": op9_huffman,
    "op10_token_counts": op10_token_counts,
    "pipeline": pipeline,
    "rule_statistics": rule_statistics,
    "secret_counts": secret_counts,
    "near_copies": near_copies,
}
_ORACLES: dict[str, str] = {"rule_statistics": _RULE_STATISTICS, "secret_counts": _SECRET_COUNTS, "near_copies": _NEAR_COPIES}


def queries() -> dict[str, Query]:
    return dict(_QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(_ORACLES)
