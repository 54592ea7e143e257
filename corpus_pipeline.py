"""A corpus from raw documents in five stages, each over all that the stage before kept.

quality classifier -> near-duplicates by SimHash and exact shingle similarity -> benchmark decontamination -> secret scan -> BPE encoding.
Every stage is written as Parquet and read again as the next one's documents.

Odd rows have defined results in every stage.  A null text counts as empty: it has no evidence against it, is a near copy
of other empty ones, holds no benchmark text and no secret, and has no tokens.  Rows without an id or with a repeated one
are rows of their own; of near copies the one with the least id stays, one with an id before one without, and one of
several with the same.  Null hosts and paths are groups of their own.  Further columns pass through, whatever their names,
up to the last stage.  Empty tables give empty results; without labels nothing is rejected.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tripleschema.llm import bpe, decontam, nearcopies, quality, secrets, simhash
from tripleschema.llm.common import delete, relieve, scratch, shared_dir, table
from tripleschema.llm.queries import tokenizer_file

#: SQL cannot express a learned classifier or byte-pair merges; tests/llm compares the stages with brute force.
ORACLE_SQL = None


def quality_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejected documents go: low quality or toxic by the combined evidence."""
    return quality.accepted(docs, table(spark, sf_dir, "labels"))


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays: the one with the least id (one of them, if ids repeat).

    Links are those of op7 (SimHash fingerprints at three bits or fewer, compared in bit slices), and those that an exact
    comparison finds beyond (five-word shingles, Jaccard similarity of 0.8 or more)."""
    return nearcopies.representatives(docs, radius=simhash.RADIUS)


def benchmark_decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark text go."""
    return decontam.decontaminated(docs, table(spark, sf_dir, "benchmark"))


def secret_scan(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets are masked; further candidates unless so many sources have them that they are examples."""
    return secrets.redacted(docs).withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))


def bpe_encoding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """``doc_id, n_tokens, ids, decoded_sha256``: packed ids of whole texts, and the digest of the text they decode to."""
    ids = bpe.encode(docs, tokenizer_file(), decoded=True)
    return ids.select("doc_id", "n_tokens", "ids", F.sha2(F.col("decoded").cast("binary"), 256).alias("decoded_sha256"))


STAGES = [
    ("quality classifier", quality_classifier),
    ("SimHash near-dedup", near_dedup),
    ("benchmark decontamination", benchmark_decontamination),
    ("secret scans", secret_scan),
    ("BPE encoding and decoding", bpe_encoding),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rows of the last stage.  What a stage has written for itself, and its input, go when its result is written."""
    docs, before = table(spark, sf_dir, "documents"), None
    at = f"{shared_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    for k, (_, stage) in enumerate(STAGES):
        with scratch(spark):
            out = stage(spark, docs, sf_dir)
            out.write.parquet(f"{at}/{k}")
        if before:
            delete(spark, before)
        relieve(spark, collect=True)
        before = f"{at}/{k}"
        docs = spark.read.schema(out.schema).parquet(before)
    return docs
