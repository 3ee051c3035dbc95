"""From raw documents to tokens: language, near duplicates, benchmark copies, secrets, pieces."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from xlsql.llm import decontaminate, langid, pieces, secret_scan, simhash
from xlsql.llm.columns import fresh
from xlsql.session import load_table, materialize


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop documents that language identification rejects; models are fitted on this stage's own labelled input."""
    return langid.keep_identified(docs, langid.fit(docs))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep of each group of near duplicates the document with the least doc_id."""
    return simhash.dedup_keep(docs)


def drop_benchmark_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop documents that hold a copy of a benchmark item, edited ones included."""
    return decontaminate.decontaminate(docs, load_table(spark, sf_dir, "benchmark"))


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Replace secrets in the texts, and count the characters of changed ones anew; every document stays."""
    (given,) = fresh(docs, "given")
    done = secret_scan.redact(docs.withColumn(given, F.col("text")))
    changed = ~F.col("text").eqNullSafe(F.col(given))
    return done.withColumn("n_chars", F.when(changed, F.length("text").cast("long")).otherwise(F.col("n_chars"))).drop(given)


def encode_pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Add (in place of columns of these names) the pieces' ids, their number, the hash of the decoded text and the bytes that the pieces' spans cover."""
    added = ("n_tokens", "ids", "decoded_sha256", "covered_bytes")
    (mark,) = fresh(docs, "pieces")
    held = pieces.with_pieces(docs, out=mark, fields=added)
    return held.select(*[F.col(f"`{c}`") for c in docs.columns if c not in added], *[f"{mark}.{c}" for c in added])


STAGES = [
    ("language_id", identify_language),
    ("simhash_near_dedup", drop_near_duplicates),
    ("benchmark_decontamination", drop_benchmark_copies),
    ("secret_scan", redact_secrets),
    ("sentencepiece", encode_pieces),
]

#: No stage but the fourth can be written in SQL; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each written as Parquet into the shared folder and read again."""
    docs = load_table(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = materialize(docs, name)
    return docs
