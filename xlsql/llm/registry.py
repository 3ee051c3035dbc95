"""The thin queries over whole tables, one for each operator, and the SQL of those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from xlsql.llm import decontaminate, embeddings, langid, licences, pieces, secret_scan, simhash, token_files, toxicity, warc
from xlsql.session import load_table


def _remainder(n: int):
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % n


def op1_embedding_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embeddings.cosine_groups(load_table(spark, sf_dir, "embeddings"))


def op2_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    records = warc.warc_round_trip(spark, load_table(spark, sf_dir, "pages"))
    return records.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "digest_ok")


def op3_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.simhash_groups(load_table(spark, sf_dir, "documents"))


def op4_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = pieces.with_pieces(load_table(spark, sf_dir, "documents").select("doc_id", "text"), fields=("n_tokens", "ids_sha256", "decoded_sha256", "covered_bytes"))
    return docs.select("doc_id", "pieces.n_tokens", "pieces.ids_sha256", "pieces.decoded_sha256", "pieces.covered_bytes")


def op5_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_files.token_counts(load_table(spark, sf_dir, "documents"))


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = load_table(spark, sf_dir, "documents").select("doc_id", "text"), load_table(spark, sf_dir, "labels").select("doc_id", "toxic")
    machine = toxicity.fit(toxicity.labelled_rows(docs, labels.where(_remainder(5) != 0)))
    scored = toxicity.with_toxicity(docs, machine)
    return scored.select("doc_id", (_remainder(5) == 0).alias("held_out"), "toxicity.score", (F.col("toxicity.score") >= 0.5).cast("int").alias("predicted"))


def op7_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, benchmark = load_table(spark, sf_dir, "documents"), load_table(spark, sf_dir, "benchmark")
    return decontaminate.leaked_items(docs, benchmark).withColumn("similarity", F.round("similarity", 6))


def op8_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load_table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    models = langid.fit(docs.where(_remainder(4) != 2))
    marked = langid.with_language(docs.select("doc_id", "text"), models)
    return marked.select("doc_id", (_remainder(4) == 2).alias("held_out"), F.col("language.lang").alias("lang_pred"), "language.score", "language.rejected")


def op9_licence_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licences.licence_report(load_table(spark, sf_dir, "documents"))


def op10_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    held = secret_scan.secret_spans(load_table(spark, sf_dir, "documents").select("doc_id", "text"))
    spans = F.col("spans")
    counts = [secret_scan.count_kind(spans, k).alias(f"n_{k}") for k in secret_scan.KINDS]
    return held.select("doc_id", *counts[:3], F.sha2(secret_scan.digest(spans, secret_scan.KINDS[:3]), 256).alias("base_sha256"), secret_scan.digest(spans).alias("spans"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (
        op1_embedding_near_dedup, op2_warc, op3_simhash_near_dedup, op4_sentencepiece, op5_token_counts, op6_toxicity,
        op7_decontamination, op8_language_id, op9_licence_scan, op10_secret_scan,
    )
}


def _licence_sql() -> str:
    quote = lambda s: "'" + s.replace("'", "''") + "'"
    values = ", ".join(f"({quote(k)}, {quote(v)})" for k, v in licences.TEMPLATES.items())
    normal = lambda c: f"string_split(replace(trim(regexp_replace(lower(coalesce({c}, '')), '[^\\p{{L}}\\p{{N}}]+', ' ', 'g')), 'licence', 'license'), ' ')"
    pairs = "list_distinct(CASE WHEN len(w) > 1 THEN list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1]) ELSE list_filter(w, lambda x: x <> '') END)"
    return f"""
        WITH t AS (SELECT licence, {pairs} AS g FROM (SELECT licence, {normal('txt')} AS w FROM (VALUES {values}) v(licence, txt))),
        d AS (SELECT row_number() OVER () AS r, doc_id, text FROM documents),
        u AS (
            SELECT r, doc_id, -1 AS part, text AS unit FROM d
            UNION ALL
            SELECT r, doc_id, unnest(range(0, len(l))) AS part, unnest(l) AS unit
            FROM (SELECT r, doc_id, string_split(coalesce(text, ''), chr(10)) AS l FROM d) WHERE len(l) > 1
        ),
        g AS (SELECT r, doc_id, part, {pairs} AS g FROM (SELECT r, doc_id, part, {normal('unit')} AS w FROM u)),
        s AS (
            SELECT r, doc_id, part, licence, 2.0 * len(list_intersect(g.g, t.g)) / (len(g.g) + len(t.g)) AS score
            FROM g, t WHERE len(g.g) BETWEEN len(t.g) * 0.6 AND len(t.g) * 1.6 AND len(g.g) + len(t.g) > 0
        ),
        b AS (SELECT *, row_number() OVER (PARTITION BY r, part ORDER BY score DESC, licence) AS n FROM s WHERE score >= {licences.DICE})
        SELECT doc_id, licence, count(*) AS n_matches, round(max(CAST(score AS DOUBLE)), 6) AS best_score FROM b WHERE n = 1 GROUP BY doc_id, licence
    """


ORACLES: dict[str, str] = {
    "op1_embedding_near_dedup": """
        WITH RECURSIVE v AS (
            SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings
        ), u AS (
            SELECT vec_id, e FROM v
            WHERE e IS NOT NULL AND len(list_filter(e, lambda x: x IS NULL OR isnan(x) OR isinf(x))) = 0 AND len(list_filter(e, lambda x: x <> 0)) > 0
        ), l AS (
            SELECT a.vec_id AS a, b.vec_id AS b FROM u a JOIN u b ON a.vec_id <> b.vec_id AND len(a.e) = len(b.e) AND list_cosine_similarity(a.e, b.e) >= 0.95
        ), c AS (
            SELECT vec_id AS n, vec_id AS m FROM u
            UNION
            SELECT c.n, l.b FROM c JOIN l ON l.a = c.m
        ), m AS (SELECT n, min(m) AS component_id FROM c GROUP BY n), k AS (SELECT a, count(*) AS n_links FROM l GROUP BY a)
        SELECT v.vec_id, coalesce(k.n_links, 0) AS n_links, coalesce(m.component_id, v.vec_id) AS component_id, v.vec_id = coalesce(m.component_id, v.vec_id) AS kept
        FROM v LEFT JOIN m ON m.n = v.vec_id LEFT JOIN k ON k.a = v.vec_id
    """,
    "op2_warc": """
        WITH p AS (SELECT page_id, octet_length(encode(coalesce(html, ''))) AS payload_bytes, sha1(coalesce(html, '')) AS payload_digest FROM pages),
        m AS (SELECT payload_digest, max(page_id) AS first FROM p WHERE payload_bytes >= 1000 GROUP BY payload_digest)
        SELECT page_id, payload_bytes, p.payload_digest, CASE WHEN first <> page_id THEN 'revisit' ELSE 'response' END AS record_type,
               CASE WHEN first <> page_id THEN first END AS refers_to, true AS digest_ok
        FROM p LEFT JOIN m ON m.payload_digest = p.payload_digest AND p.payload_bytes >= 1000
    """,
    "op9_licence_scan": _licence_sql(),
}
