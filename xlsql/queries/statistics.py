"""Sampling, intervals and corpus statistics."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from xlsql.queries import query, values
from xlsql.session import load_table
from xlsql.stats import corpus as cs
from xlsql.stats import sampling as sm
from xlsql.workloads import items as wi
from xlsql.workloads import published as pub

TOK = r"[\p{L}\p{N}]+|[^\s\p{L}\p{N}]"
GRID = [(z, e, p, n) for z in (1.645, 1.96, 2.576) for e in (0.01, 0.03, 0.05) for p in (0.5, 0.9) for n in (399, 1534, 10962, 1000000)]


@query(f"""
    SELECT z, e, p, CAST(pop AS BIGINT) AS pop, CAST(n0 AS BIGINT) AS n0, CAST(ceil(round(n0 / (1 + (n0 - 1) / pop), 9)) AS BIGINT) AS n
    FROM (SELECT *, ceil(round(z * z * p * (1 - p) / (e * e), 9)) AS n0 FROM {values(GRID, 'z, e, p, pop')})""")
def q35_sample_size(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = spark.createDataFrame(GRID, "z double, e double, p double, pop long")
    return g.withColumn("n0", sm.sample_size_infinite(F.col("z"), F.col("e"), F.col("p"))).withColumn("n", sm.sample_size_finite(F.col("n0"), F.col("pop")))


@query("""
    SELECT d.doc_id, quality FROM documents d JOIN labels l ON d.doc_id = l.doc_id
    WHERE d.doc_id IN (SELECT doc_id FROM documents ORDER BY md5(CAST(doc_id AS VARCHAR) || ':42'), doc_id LIMIT 100)""")
def q36_sample_draw(spark: SparkSession, sf_dir: str) -> DataFrame:
    drawn = sm.draw_sample(load_table(spark, sf_dir, "documents").select("doc_id"), 100, "doc_id")
    return drawn.join(load_table(spark, sf_dir, "labels").select("doc_id", "quality"), "doc_id")


PLAN = """
    WITH s AS (SELECT lang, count(*) AS population FROM documents GROUP BY lang), t AS (SELECT *, sum(population) OVER () AS total FROM s),
    p AS (SELECT lang, population, 1068 AS n0, CAST(ceil(round(1068 / (1 + 1067 / CAST(total AS DOUBLE)), 9)) AS BIGINT) AS n, total FROM t),
    q AS (SELECT *, floor(n * population / CAST(total AS DOUBLE)) AS low, round(n * population / CAST(total AS DOUBLE) - floor(n * population / CAST(total AS DOUBLE)), 9) AS rest FROM p),
    f AS (SELECT lang, population, CAST(n0 AS BIGINT) AS n0, n, CAST(low + CASE WHEN row_number() OVER (ORDER BY rest DESC, lang) <= n - sum(low) OVER () THEN 1 ELSE 0 END AS BIGINT) AS n_stratum FROM q)"""


@query(PLAN + """
    SELECT r.lang, count(*) AS drawn, sum(CAST(doc_id AS BIGINT))::BIGINT AS ids
    FROM (SELECT lang, doc_id, row_number() OVER (PARTITION BY lang ORDER BY md5(CAST(doc_id AS VARCHAR) || ':42'), doc_id) AS nth FROM documents) r JOIN f ON f.lang = r.lang
    WHERE nth <= n_stratum GROUP BY r.lang""")
def q37_sample_stratified(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load_table(spark, sf_dir, "documents").select("doc_id", "lang")
    drawn = sm.draw_sample(docs, sm.plan_sample(docs, "lang"), "doc_id", by="lang")
    return drawn.groupBy("lang").agg(F.count("*").alias("drawn"), F.sum("doc_id").alias("ids"))


@query(PLAN + " SELECT * FROM f")
def q37a_sample_plan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sm.plan_sample(load_table(spark, sf_dir, "documents").select("lang"), "lang")


INTERVALS = """
    SELECT k, n, round(p, 6) AS accuracy, round(1.96::DOUBLE * sqrt(p * (1 - p) / n), 6) AS wald, round(1.96::DOUBLE * sqrt(p * (1 - p) / n) * sqrt((pop - n) / CAST(pop - 1 AS DOUBLE)), 6) AS wald_fpc,
           round(1.96::DOUBLE * sqrt(0.25 / n) * sqrt((pop - n) / CAST(pop - 1 AS DOUBLE)), 6) AS planned,
           round((p + z2 / (2 * n)) / (1 + z2 / n) - 1.96::DOUBLE * sqrt(p * (1 - p) / n + z2 / (4 * n * n)) / (1 + z2 / n), 6) AS wilson_low,
           round((p + z2 / (2 * n)) / (1 + z2 / n) + 1.96::DOUBLE * sqrt(p * (1 - p) / n + z2 / (4 * n * n)) / (1 + z2 / n), 6) AS wilson_high
    FROM (SELECT k, n, pop, k / CAST(n AS DOUBLE) AS p, 1.96::DOUBLE * 1.96::DOUBLE AS z2 FROM base)"""


def _intervals(base: DataFrame) -> DataFrame:
    k, n, pop = F.col("k"), F.col("n"), F.col("pop")
    half = lambda *a, **b: F.round(sm.accuracy_interval(k, n, *a, **b)["half"], 6)
    wilson = sm.accuracy_interval(k, n, method="wilson")
    return base.select("k", "n", F.round(k / n, 6).alias("accuracy"), half().alias("wald"), half(pop).alias("wald_fpc"), half(pop, method="planned").alias("planned"), F.round(wilson["low"], 6).alias("wilson_low"), F.round(wilson["high"], 6).alias("wilson_high"))


@query("""
    WITH s AS (SELECT quality FROM labels ORDER BY md5(CAST(doc_id AS VARCHAR) || ':42'), doc_id LIMIT 291),
    base AS (SELECT CAST(sum(quality) AS BIGINT) AS k, count(*) AS n, (SELECT count(*) FROM labels) AS pop FROM s)""" + INTERVALS)
def q38_accuracy_ci(spark: SparkSession, sf_dir: str) -> DataFrame:
    labels = load_table(spark, sf_dir, "labels").select("doc_id", "quality")
    seen = sm.observed_accuracy(sm.draw_sample(labels, 291, "doc_id"), "quality")
    return _intervals(seen.crossJoin(labels.agg(F.count("*").alias("pop"))))


@query("""
    WITH e AS (SELECT event_id, CAST(value <= 98 AS INTEGER) AS correct FROM events), s AS (SELECT correct FROM e ORDER BY md5(CAST(event_id AS VARCHAR) || ':42'), event_id LIMIT (SELECT CAST(ceil(round(1068 / (1 + 1067 / CAST(count(*) AS DOUBLE)), 9)) AS BIGINT) FROM events)),
    base AS (SELECT CAST(sum(correct) AS BIGINT) AS k, count(*) AS n, (SELECT count(*) FROM e) AS pop FROM s)""" + INTERVALS)
def q38a_accuracy_at_scale(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The validation over a population of the published size: size, draw, accuracy, intervals."""
    e = load_table(spark, sf_dir, "events").select("event_id", (F.col("value") <= 98).cast("int").alias("correct"))
    n = sm.plan_sample(e).first()["n"]
    seen = sm.observed_accuracy(sm.draw_sample(e, n, "event_id"))
    return _intervals(seen.crossJoin(e.agg(F.count("*").alias("pop"))))


@query(f"WITH base AS (SELECT CAST({pub.CORRECT} AS BIGINT) AS k, CAST({pub.JUDGED} AS BIGINT) AS n, CAST({sum(pub.QUESTIONS.values())} AS BIGINT) AS pop)" + INTERVALS)
def q39_accuracy_published(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _intervals(spark.createDataFrame([(pub.CORRECT, pub.JUDGED, sum(pub.QUESTIONS.values()))], "k long, n long, pop long"))


@query("""
    WITH d AS (SELECT seed, quality, row_number() OVER (PARTITION BY seed ORDER BY md5(CAST(doc_id AS VARCHAR) || ':' || CAST(seed AS VARCHAR)), doc_id) AS nth FROM labels, range(0, 50) r(seed)),
    p AS (SELECT seed, avg(quality) AS p, count(*) AS n FROM d WHERE nth <= 200 GROUP BY seed), c AS (SELECT avg(quality) AS census, count(*) AS pop FROM labels),
    h AS (SELECT CASE WHEN abs(p - census) <= 1.96::DOUBLE * sqrt(p * (1 - p) / n) * sqrt((pop - n) / CAST(pop - 1 AS DOUBLE)) + 1e-12 THEN 1 ELSE 0 END AS hit FROM p, c)
    SELECT count(*) AS seeds, CAST(sum(hit) AS BIGINT) AS hits, round(avg(hit), 6) AS rate FROM h""")
def q40_coverage_sim(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sm.coverage(load_table(spark, sf_dir, "labels"), "doc_id", "quality", 200, 50)


@query("""
    WITH s AS (SELECT count(*) AS n, avg(CASE WHEN quality = 1 - toxic THEN 1.0::DOUBLE ELSE 0.0 END) AS raw, avg(quality) AS pa, avg(1 - toxic) AS pb FROM labels), c AS (SELECT *, pa * pb + (1 - pa) * (1 - pb) AS chance FROM s)
    SELECT n, round(raw, 6) AS raw, round((raw - chance) / (1 - chance), 6) AS kappa FROM c""")
def q41_rater_agreement(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sm.agreement(load_table(spark, sf_dir, "labels").withColumn("second", 1 - F.col("toxic")), "quality", "second")


def stats_sql(source: str, by: str) -> str:
    """Corpus statistics of rows (by columns, text)."""
    return f"""
        SELECT l.*, vocab, round(vocab / CAST(tokens AS DOUBLE), 6) AS ttr FROM (
            SELECT {by}, count(*) AS n, round(avg(len(list_filter(regexp_split_to_array(trim(text, E' \\t\\n\\r'), '\\s+'), lambda x: x <> ''))), 6) AS avg_words, round(avg(length(text)), 6) AS avg_chars,
                   round(avg(len(regexp_extract_all(text, '{TOK}'))), 6) AS avg_tokens, CAST(sum(len(regexp_extract_all(text, '{TOK}'))) AS BIGINT) AS tokens
            FROM {source} GROUP BY {by}) l
        JOIN (SELECT {by}, count(DISTINCT token) AS vocab FROM (SELECT {by}, unnest(regexp_extract_all(lower(text), '{TOK}')) AS token FROM {source}) GROUP BY {by}) v USING ({by})"""


@query(stats_sql("documents", "lang"))
def q42_corpus_stats_lang(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cs.corpus_stats(load_table(spark, sf_dir, "documents"), "text", ["lang"])


SPLIT = "CASE WHEN substr(md5(CAST({0} AS VARCHAR)), 32, 1) < 'd' THEN 'train' ELSE 'dev' END"


def _split(column: str):
    return F.when(F.substring(F.md5(F.col(column).cast("string")), 32, 1) < "d", "train").otherwise("dev")


@query("WITH c AS (SELECT " + SPLIT.format("conv_id") + " AS split, role AS kind, text FROM conversations UNION ALL SELECT " + SPLIT.format("item_id") + ", 'question', text FROM benchmark) " + stats_sql("c", "split, kind"))
def q43_corpus_stats_split(spark: SparkSession, sf_dir: str) -> DataFrame:
    a = load_table(spark, sf_dir, "conversations").select(_split("conv_id").alias("split"), F.col("role").alias("kind"), "text")
    b = load_table(spark, sf_dir, "benchmark").select(_split("item_id").alias("split"), F.lit("question").alias("kind"), "text")
    return cs.corpus_stats(a.unionByName(b), "text", ["split", "kind"])


@query("WITH s AS (" + stats_sql("documents", "lang") + """), m AS (
    UNPIVOT (SELECT lang, avg_words, avg_chars, avg_tokens, CAST(vocab AS DOUBLE) AS vocab, ttr FROM s) ON avg_words, avg_chars, avg_tokens, vocab, ttr INTO NAME measure VALUE value)
    SELECT a.lang, a.measure, b.value AS base_value, a.value, round(100 * (a.value / b.value - 1), 4) AS change FROM m a JOIN m b ON a.measure = b.measure AND b.lang = 'en' WHERE a.lang <> 'en'""")
def q44_corpus_change(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cs.percent_change(cs.corpus_stats(load_table(spark, sf_dir, "documents"), "text", ["lang"]), "lang", "en")


@query(f"""
    WITH t AS (SELECT lang, unnest(regexp_extract_all(lower(text), '{TOK}')) AS token FROM documents), f AS (SELECT lang, token, count(*) AS n FROM t GROUP BY lang, token),
    r AS (SELECT *, row_number() OVER (PARTITION BY lang ORDER BY n DESC, token) AS nth FROM f) SELECT lang, token, n, nth FROM r WHERE nth <= 10""")
def q45_vocab_top(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pyspark.sql import Window

    f = cs.token_frequencies(load_table(spark, sf_dir, "documents"), "text", ["lang"])
    return f.withColumn("nth", F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "token")).cast("long")).where("nth <= 10")


@query(f"""
    WITH t AS (SELECT lang, unnest(regexp_extract_all(lower(text), '{TOK}')) AS token FROM documents), f AS (SELECT lang, token, count(*) AS n FROM t GROUP BY lang, token)
    SELECT lang, count(*) AS types, round(avg(CASE WHEN n = 1 THEN 1.0::DOUBLE ELSE 0.0 END), 6) AS hapax_share, round(sum(CASE WHEN n <= 2 THEN n ELSE 0 END) / CAST(sum(n) AS DOUBLE), 6) AS tail_share FROM f GROUP BY lang""")
def q46_hapax_sparsity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cs.sparsity(load_table(spark, sf_dir, "documents"), "text", ["lang"])


WORDS = "len(list_filter(regexp_split_to_array(trim(text, E' \\t\\n\\r'), '\\s+'), lambda x: x <> ''))"


@query(" UNION ALL ".join(f"SELECT lang, '{k}' AS tokenizer, round(sum({t}) / CAST(sum({WORDS}) AS DOUBLE), 6) AS fertility, round(sum(length(text)) / CAST(sum({t}) AS DOUBLE), 6) AS compression FROM documents GROUP BY lang"
                          for k, t in (("word_punct", f"len(regexp_extract_all(text, '{TOK}'))"), ("whitespace", WORDS), ("char_ngram", "greatest(length(text) - 2, 0)"))))
def q47_fertility(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load_table(spark, sf_dir, "documents")
    a, b, c = (cs.fertility(docs, "text", ["lang"], t) for t in ("word_punct", "whitespace", "char_ngram"))
    return a.unionByName(b).unionByName(c)


@query()
def q47a_bpe_fertility(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Merges learnt on the source language, applied to all languages."""
    docs = load_table(spark, sf_dir, "documents").select("lang", "text")
    merges = cs.train_bpe(docs.where("lang = 'en'"), "text", 12)
    return cs.bpe_fertility(docs, "text", ["lang"], merges)


SQL_TOKEN = r"""'[^']*'|[A-Za-z_][A-Za-z_0-9]*|[0-9]+(?:\.[0-9]+)?|<=|>=|<>|[^\s]"""
ROWS = values([(i.item_id, i.db_id, i.sql, i.evidence) for i in wi.ITEMS], "item_id, db_id, sql, evidence")


@query("SELECT db_id, count(*) AS n, round(avg(len(regexp_extract_all(sql, '" + SQL_TOKEN.replace("'", "''") + f"'))), 6) AS avg_sql_tokens FROM {ROWS} GROUP BY db_id")
def q48_sql_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    from xlsql.localize.sql_tree import sql_tokens

    rows = [(i.db_id, len(sql_tokens(i.sql))) for i in wi.ITEMS]
    return spark.createDataFrame(rows, "db_id string, t int").groupBy("db_id").agg(F.count("*").alias("n"), F.round(F.avg("t"), 6).alias("avg_sql_tokens"))


@query(f"SELECT db_id, count(*) AS n, round(avg(len(regexp_extract_all(evidence, '{TOK}'))), 6) AS avg_evidence_tokens FROM {ROWS} GROUP BY db_id")
def q49_evidence_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    from xlsql.functions.text import tokens

    return wi.core_items(spark).groupBy("db_id").agg(F.count("*").alias("n"), F.round(F.avg(F.size(tokens(F.col("evidence")))), 6).alias("avg_evidence_tokens"))


def _both_languages(spark: SparkSession, sf_dir: str, n: int = 400) -> DataFrame:
    """lang, split, question, evidence, sql of made and core items, and of their localized forms."""
    from xlsql.localize.pipeline import build_localized

    items = wi.make_items(spark, sf_dir, n).unionByName(wi.core_items(spark))
    made = build_localized(spark, sf_dir, items)
    target = made.select(F.lit("target").alias("lang"), "split", F.col("question_loc").alias("question"), F.col("evidence_loc").alias("evidence"), F.col("sql_loc").alias("sql"))
    return items.select(F.lit("source").alias("lang"), "split", "question", "evidence", "sql").unionByName(target)


@query()
def q49a_parallel_shift(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Questions against their localized forms: measure, base_value, value, change. Words fall, the type-token ratio rises."""
    both = _both_languages(spark, sf_dir).withColumnRenamed("question", "text")
    return cs.percent_change(cs.corpus_stats(both, "text", ["lang"]), "lang", "source")


@query()
def q49b_parallel_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    """split, measure, source, target, change: tokens of SQL and of evidence in both languages. Only names change, so SQL keeps its number of tokens."""
    from xlsql.functions.text import tokens

    sql = F.size(F.regexp_extract_all("sql", F.lit(SQL_TOKEN), F.lit(0)))
    both = _both_languages(spark, sf_dir).select("lang", "split", sql.alias("sql_tokens"), F.size(tokens(F.col("evidence"))).alias("evidence_tokens"))
    rows = both.unpivot(["lang", "split"], ["sql_tokens", "evidence_tokens"], "measure", "value").groupBy("split", "measure").pivot("lang", ["source", "target"]).agg(F.round(F.avg("value"), 6))
    return rows.withColumn("change", F.round(100 * (F.col("target") / F.col("source") - 1), 4))


@query(f"SELECT split, measure, source, target, round(100 * (target / source - 1), 1) AS change FROM {values(pub.CORPUS, 'split, measure, source, target')}")
def q50_t1_replay(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pub.corpus_rows(spark).withColumn("change", F.round(100 * (F.col("target") / F.col("source") - 1), 1))
