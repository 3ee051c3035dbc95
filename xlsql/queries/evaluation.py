"""Scores, comparisons, generators and dataset facts."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from xlsql.catalog.spec import DATABASES, TABLES, columns_of, extract_all, open_database
from xlsql.generate import baselines as gb
from xlsql.metrics import scores as ms
from xlsql.queries import query, quote, values
from xlsql.queries.construction import COLUMNS, OWNER, bag_equal, list_equal
from xlsql.session import load_table
from xlsql.stats import corpus as cs
from xlsql.workloads import items as wi
from xlsql.workloads import published as pub

COMMERCE = [i for i in wi.ITEMS if i.db_id == "commerce"]


def _spaced(sql: str) -> str:
    """The same query, differently written."""
    return "  " + sql.replace("SELECT", "select").replace(" FROM ", "\n from ").replace("count(*)", "COUNT( * )").replace("<>", "!=") + " ;"


PREDICTED = [("echo", i.item_id, _spaced(i.sql)) for i in COMMERCE] + [("constant", i.item_id, "SELECT 1") for i in COMMERCE] + [("mutant", item, sql) for _, item, sql in wi.MUTANTS if _ != "same"][:7]
NORMAL = "regexp_replace(regexp_replace(regexp_replace(lower({0}), '!=', '<>', 'g'), '\\s+', '', 'g'), ';$', '')"


@query(f"""
    SELECT method, count(*) AS n, avg(CASE WHEN {NORMAL.format('p.sql')} = {NORMAL.format('g.sql')} THEN 1.0::DOUBLE ELSE 0.0 END) AS em
    FROM {values(PREDICTED, 'method, item_id, sql', 'p')} JOIN {values([(i.item_id, i.sql) for i in COMMERCE], 'item_id, sql', 'g')} USING (item_id) GROUP BY method""")
def q51_em_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    preds = spark.createDataFrame(PREDICTED, "method string, item_id long, sql string")
    return ms.exact_match(preds, wi.core_items(spark), ["method"])


EXECUTED = (
    [("echo", i.item_id, i.sql) for i in COMMERCE]
    + [("mutant", item, sql) for _, item, sql in wi.MUTANTS]
    + [("reordered", 4, wi.BY_ID[4].sql.replace("DESC, o_orderkey", "DESC, o_orderkey + 0")), ("reordered", 4, wi.BY_ID[4].sql.replace("o_totalprice DESC", "o_totalprice ASC")), ("reordered", 12, wi.BY_ID[12].sql.replace("ORDER BY n, ", "ORDER BY n DESC, "))]
)


# Columns of the ordered gold queries' results.
WIDE = {4: 2, 12: 2}


def agrees(item: int, gold: str, predicted: str) -> str:
    """SQL of execution accuracy: rows in order where gold asks for one, else as a bag; a query that is not valid is wrong."""
    if "no_such" in predicted:
        return "false"
    return list_equal(gold, predicted, WIDE[item]) if " ORDER BY " in gold and item in WIDE else bag_equal(gold, predicted)


def _ex_sql() -> str:
    gold = {i.item_id: i.sql for i in COMMERCE}
    rows = " UNION ALL ".join(f"SELECT {quote(m)} AS method, CAST({agrees(k, gold[k], s)} AS INTEGER) AS hit" for m, k, s in EXECUTED)
    return f"SELECT method, count(*) AS n, round(avg(hit), 6) AS ex FROM ({rows}) GROUP BY method"


@query(_ex_sql)
def q52_ex_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Predictions are executed, each distinct pair once; invalid ones score zero."""
    session = open_database(spark, sf_dir, DATABASES["commerce"])
    rows = ms.execution_accuracy(EXECUTED, {i.item_id: i.sql for i in COMMERCE}, session)
    log = spark.createDataFrame(rows, "method string, item_id long, correct boolean")
    return log.groupBy("method").agg(F.count("*").alias("n"), F.round(F.avg(F.col("correct").cast("double")), 6).alias("ex"))


LOG = """
    WITH e AS (SELECT event_type AS method, user_id AS item, CAST(regexp_extract(props, '"k": *([0-9]+)', 1) AS BIGINT) % 3 AS run, value FROM events),
    r AS (SELECT method, item, run, avg(value) AS time_pred FROM e GROUP BY method, item, run),
    g AS (SELECT item, avg(value) AS time_gold FROM e GROUP BY item),
    l AS (SELECT method, r.item, run, time_pred, time_gold, CAST(floor(time_pred) AS BIGINT) % 3 <> 0 AS correct FROM r JOIN g ON g.item = r.item),
    w AS (SELECT *, sqrt(greatest(time_gold, 0.001::DOUBLE) / greatest(time_pred, 0.001::DOUBLE)) AS reward FROM l)"""


def event_run_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events as the log of a large evaluation: method, item, run, time_pred, time_gold, correct."""
    e = load_table(spark, sf_dir, "events").select(F.col("event_type").alias("method"), F.col("user_id").alias("item"), (F.get_json_object("props", "$.k").cast("long") % 3).alias("run"), "value")
    r = e.groupBy("method", "item", "run").agg(F.avg("value").alias("time_pred"))
    g = e.groupBy("item").agg(F.avg("value").alias("time_gold"))
    return r.join(g, "item").withColumn("correct", F.floor("time_pred") % 3 != 0)


@query(LOG + """
    SELECT method, run, count(*) AS n, round(avg(CAST(correct AS INTEGER)), 6) AS ex, round(avg(CASE WHEN correct THEN reward ELSE 0.0 END), 6) AS ves, round(avg(reward) FILTER (correct), 6) AS ratio FROM w GROUP BY method, run""")
def q53_ves_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ms.score(event_run_log(spark, sf_dir), ["method", "run"])


@query("""
    WITH s AS (SELECT event_type, avg(value) AS m, stddev_pop(value) AS d, count(*) AS n FROM events GROUP BY event_type)
    SELECT e.event_type, max(n) AS n, count(*) AS n_kept, round(avg(value), 6) AS mean FROM events e JOIN s ON s.event_type = e.event_type WHERE abs(value - m) <= 1.5::DOUBLE * d + 1e-12 GROUP BY e.event_type""")
def q54_ves_trimmed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Times within 1.5 deviations; 3, the usual bound, would keep all of these."""
    return ms.trim_times(load_table(spark, sf_dir, "events").select("event_type", "value"), ["event_type"], "value", 1.5)


@query(LOG + """, s AS (SELECT method, run, round(avg(CAST(correct AS INTEGER)), 6) AS ex, round(avg(CASE WHEN correct THEN reward ELSE 0.0 END), 6) AS ves FROM w GROUP BY method, run)
    SELECT method, count(*) AS runs, round(avg(ex), 6) AS ex_mean, round(stddev_samp(ex), 6) AS ex_sd, round(avg(ves), 6) AS ves_mean, round(stddev_samp(ves), 6) AS ves_sd FROM s GROUP BY method""")
def q55_three_run_mean(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ms.average_runs(ms.score(event_run_log(spark, sf_dir), ["method", "run"]), ["method"], ["ex", "ves"])


INFER = values([(m, lang, k, v) for m, lang, *vs in pub.INFERENCE for k, v in zip(pub.MEASURES, vs)], "method, lang, measure, value", "s")
TUNED = values([(f, m, o, k, v) for f, m, o, *vs in pub.TUNED for k, v in zip(pub.MEASURES, vs)], "family, model, size_order, measure, value", "s")


@query(f"""SELECT a.lang, a.measure, a.value AS first_value, b.value AS second_value, round(b.value - a.value, 4) AS gain, round(100 * (b.value - a.value) / a.value, 4) AS relative
    FROM {INFER.replace(' s(', ' a(')} JOIN {INFER.replace(' s(', ' b(')} ON a.lang = b.lang AND a.measure = b.measure AND a.method = 'direct' AND b.method = 'staged'""")
def q56_method_gain(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ms.method_gain(pub.inference_scores(spark))


@query(f"""SELECT a.method, a.measure, a.value AS first_value, b.value AS second_value, round(b.value - a.value, 4) AS gain, round(100 * (b.value - a.value) / a.value, 4) AS relative
    FROM {INFER.replace(' s(', ' a(')} JOIN {INFER.replace(' s(', ' b(')} ON a.method = b.method AND a.measure = b.measure AND a.lang = 'target' AND b.lang = 'source'""")
def q57_language_gap(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ms.language_gap(pub.inference_scores(spark))


@query(f"""WITH r AS (SELECT *, rank() OVER (PARTITION BY lang, measure ORDER BY value DESC) AS k FROM {INFER}), d AS (SELECT measure, method, count(DISTINCT k) AS d FROM r GROUP BY measure, method)
    SELECT measure, max(d) = 1 AS stable FROM d GROUP BY measure""")
def q58_rank_stability(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ms.rank_stability(pub.inference_scores(spark))


@query(f"""WITH s2 AS (SELECT *, value - lag(value) OVER (PARTITION BY family, measure ORDER BY size_order) AS step FROM {TUNED})
    SELECT family, measure, coalesce(min(step) > 0, true) AS monotone, round(max(value) - min(value), 4) AS spread FROM s2 GROUP BY family, measure""")
def q59_size_scaling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ms.scaling_trend(pub.tuned_scores(spark))


@query(f"""SELECT a.measure, a.model AS better_model, b.model AS worse_model, a.value > b.value AS holds
    FROM {TUNED.replace(' s(', ' a(')} JOIN {TUNED.replace(' s(', ' b(')} ON a.measure = b.measure AND a.family = 'code' AND b.family = 'multilingual'""")
def q59a_cross_family(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ms.cross_family(pub.tuned_scores(spark), "code", "multilingual")


def generate(spark: SparkSession, sf_dir: str, method: str, items: list[wi.Item] | None = None, stages=("link", "intent", "correct")) -> list[tuple[int, str, int, bool]]:
    """(item, SQL, rounds, valid) of a generator over the core items; linking and intents are DataFrame plans, their short results come here."""
    items = items or list(wi.ITEMS)
    schemas = {d: columns_of(spark, sf_dir, DATABASES[d]) for d in DATABASES}
    links: dict[int, list[tuple[str, str]]] = {}
    intents: dict[int, str] = {}
    if method == "staged":
        core = wi.core_items(spark)
        for r in gb.link_schema(core, extract_all(spark, sf_dir), 4).orderBy("item_id", "nth").collect():
            links.setdefault(r["item_id"], []).append((r["table_name"], r["column_name"]))
        intents = {r[0]: r[1] for r in core.select("item_id", gb.intent_of(F.col("question"))).collect()}
    sessions = {d: open_database(spark, sf_dir, DATABASES[d]) for d in {i.db_id for i in items}}
    out = []
    for i in items:
        if method == "direct":
            sql = gb.direct(i.question, i.evidence, schemas[i.db_id])
        else:
            sql = gb.staged(i.question, i.evidence, schemas[i.db_id], links.get(i.item_id, []), intents[i.item_id], stages)
        rounds = 2 if method == "staged" and "correct" in stages else 0
        out.append((i.item_id, *gb.self_correct(sessions[i.db_id], sql, schemas[i.db_id], rounds)))
    return out


def known_schemas(db: str) -> dict[str, list[str]]:
    """Columns of the given tables that the core items' questions and evidence touch, in the tables' order; enough for the direct generator of SQL text."""
    return {t: list(c) for t, c in wi.COLUMNS[db].items()}


def _direct_sql() -> str:
    """Gold and the direct generator's queries, both executed there."""
    rows = []
    for i in COMMERCE:
        made = gb.direct(i.question, i.evidence, known_schemas("commerce"))
        hit = "false" if len(re.findall(r"\bFROM\b", made)) == 0 else f"({_width_of(made)} = {_width_of(i.sql)} AND {_guarded(i, made)})"
        rows.append(f"SELECT CAST({i.item_id} AS BIGINT) AS item_id, {quote(made)} AS sql, {hit} AS correct")
    return " UNION ALL ".join(rows)


def _width_of(sql: str) -> str:
    return str(wi.width_of(sql))


def _guarded(i: wi.Item, made: str) -> str:
    """Agreement of results; queries of other widths cannot agree and are not compared."""
    return agrees(i.item_id, i.sql, made) if wi.width_of(made) == wi.width_of(i.sql) else "false"


@query(_direct_sql)
def q60_direct_baseline(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The direct generator's query of each core item of ``commerce``, and whether its execution agrees with gold."""
    made = {k: s for k, s, _, _ in generate(spark, sf_dir, "direct", COMMERCE)}
    session = open_database(spark, sf_dir, DATABASES["commerce"])
    right = ms.execution_accuracy(list(made.items()), {i.item_id: i.sql for i in COMMERCE}, session)
    return spark.createDataFrame([(k, made[k], ok) for k, ok in right], "item_id long, sql string, correct boolean")


@query()
def q61_staged_baseline(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.createDataFrame([(k, s, v) for k, s, _, v in generate(spark, sf_dir, "staged")], "item_id long, sql string, valid boolean")


#: Scores of the inference experiment by application and folder, so that the comparisons need not run it again.
INFERRED: dict[tuple[str, str], DataFrame] = {}


def inference_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    from xlsql.session import materialize
    from xlsql.workloads import experiments as ex

    key = (spark.sparkContext.applicationId, sf_dir)
    if key not in INFERRED:
        INFERRED[key] = materialize(ex.run_inference(ex.make_bench(spark, sf_dir)), "inferred")
    return INFERRED[key]


@query()
def q61a_inference_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """method, lang, run, n, ex, ves, ratio, em: direct and staged in both languages, three runs each, on the dev items of 340."""
    from xlsql.workloads import experiments as ex

    return ex.score_log(inference_log(spark, sf_dir), ["method", "lang", "run"])


@query()
def q61d_inference_comparison(spark: SparkSession, sf_dir: str) -> DataFrame:
    """comparison, key, measure, first_value, second_value, gain, relative: gains of the method and gaps of the language, from means over runs."""
    from xlsql.workloads import experiments as ex

    means = ms.average_runs(ex.score_log(inference_log(spark, sf_dir), ["method", "lang", "run"]), ["method", "lang"], ["em", "ex", "ves"])
    rows = ex.measure_rows(means.select("method", "lang", *[F.col(f"{m}_mean").alias(m) for m in ("em", "ex", "ves")]), ["method", "lang"])
    gain = ms.method_gain(rows).select(F.lit("method_gain").alias("comparison"), F.col("lang").alias("key"), "measure", "first_value", "second_value", "gain", "relative")
    gap = ms.language_gap(rows).select(F.lit("language_gap").alias("comparison"), F.col("method").alias("key"), "measure", "first_value", "second_value", "gain", "relative")
    none = F.lit(None).cast("double")
    stable = ms.rank_stability(rows).select(F.lit("rank_stability").alias("comparison"), F.col("stable").cast("string").alias("key"), "measure", *[none.alias(c) for c in ("first_value", "second_value", "gain", "relative")])
    return gain.unionByName(gap).unionByName(stable)


@query()
def q61e_prompt_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """evidence, method, n, ex, em: both methods on the source dev items with and without evidence."""
    from xlsql.workloads import experiments as ex

    bench = ex.make_bench(spark, sf_dir, 104)
    rows = bench.items.where("lang = 'source' and split = 'dev'").orderBy("item_id").collect()
    gold, out = {("source", r["item_id"]): r["sql"] for r in rows}, None
    for evidence in (True, False):
        config = gb.ExperimentConfig("offline", evidence=evidence)
        preds = [p for method in ("direct", "staged") for p in ex.infer(bench, rows, "source", method, 0, config)]
        part = ex.score_log(ex.run_log(bench, preds, gold, timed=False), ["method"]).select(F.lit(evidence).alias("evidence"), "method", "n", "ex", "em")
        out = part if out is None else out.unionByName(part)
    return out


@query()
def q61b_stage_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """stages, n_valid, n: the staged generator with each stage off."""
    rows = []
    for off in (None, "link", "intent", "correct"):
        stages = tuple(s for s in ("link", "intent", "correct") if s != off)
        made = generate(spark, sf_dir, "staged", stages=stages)
        rows.append(("all" if off is None else f"without {off}", sum(v for *_, v in made), len(made)))
    return spark.createDataFrame(rows, "stages string, n_valid long, n long")


def _prompt_sql() -> str:
    """Prompts put together there: tables by name, columns in order, with their types and descriptions."""
    told = values([(d.db_id, k, v) for d in DATABASES.values() for k, v in d.descriptions.items()], "db_id, c, note", "n")
    kind = "CASE k WHEN 'BIGINT' THEN 'bigint' WHEN 'INTEGER' THEN 'int' WHEN 'VARCHAR' THEN 'string' WHEN 'DOUBLE' THEN 'double' WHEN 'TIMESTAMP' THEN 'timestamp_ntz' WHEN 'FLOAT[]' THEN 'array<float>' ELSE k END"
    line = "chr(10)"
    return f"""
        WITH i AS (SELECT * FROM {values([(i.item_id, i.db_id, i.question, i.evidence) for i in wi.ITEMS], 'item_id, db_id, question, evidence')}),
        t AS (SELECT x.db_id, 'table ' || t || {line} || string_agg('  ' || x.c || ' ' || {kind} || coalesce(' -- ' || note, ''), {line} ORDER BY o) AS one FROM {COLUMNS} x LEFT JOIN {told} ON n.db_id = x.db_id AND n.c = x.c GROUP BY x.db_id, t),
        d AS (SELECT db_id, string_agg(one, {line} ORDER BY one) AS txt FROM t GROUP BY db_id),
        p AS (SELECT item_id, '# Schema' || {line} || txt || {line} || '# Question' || {line} || question || {line} || '# Hint' || {line} || evidence || {line} || '# SQL' || {line} AS prompt FROM i JOIN d ON d.db_id = i.db_id)
        SELECT CAST(item_id AS BIGINT) AS item_id, CAST(length(prompt) AS INTEGER) AS chars, md5(prompt) AS digest FROM p"""


@query(_prompt_sql)
def q61c_prompts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """item_id and size of each prompt: schema, question and evidence."""
    prompts = gb.render_prompt(wi.core_items(spark), gb.schema_text(extract_all(spark, sf_dir)))
    return prompts.select("item_id", F.length("prompt").alias("chars"), F.md5("prompt").alias("digest"))


def _links_sql() -> str:
    """Tokens of questions (1) and spans of evidence (5) against the words of columns, tables and descriptions."""
    stop = "(" + ", ".join(quote(w) for w in gb.STOP) + ")"
    told = values([(d.db_id, k, v) for d in DATABASES.values() for k, v in d.descriptions.items()], "db_id, c, note", "n")
    tokens = lambda c: f"list_distinct(list_filter(string_split(lower(regexp_replace({c}, '[^\\p{{L}}\\p{{N}}_]+', ' ', 'g')), ' '), lambda w: w <> '' AND w NOT IN {stop}))"
    singular = "regexp_replace(w, '^(.{3,})s$', '\\1')"
    return f"""
        WITH i AS (SELECT * FROM {values([(i.item_id, i.db_id, i.question, i.evidence) for i in wi.ITEMS], 'item_id, db_id, question, evidence')}),
        q AS (SELECT item_id, db_id, unnest({tokens('question')}) AS w, 1 AS weight FROM i UNION ALL SELECT item_id, db_id, unnest(regexp_extract_all(lower(evidence), '`([^`]+)`', 1)), 5 FROM i),
        m AS (SELECT DISTINCT db_id, t, c, o, {singular} AS w FROM (
            SELECT x.db_id, t, x.c, o, unnest(list_concat(list_concat([lower(x.c)], list_concat(string_split(x.c, '_'), string_split(t, '_'))), coalesce({tokens('note')}, []))) AS w
            FROM {COLUMNS} x LEFT JOIN {told} ON n.db_id = x.db_id AND n.c = x.c) WHERE w <> ''),
        s AS (SELECT item_id, t, c, o, CAST(sum(weight) AS BIGINT) AS score FROM (SELECT item_id, db_id, {singular} AS w, weight FROM q) q JOIN m ON m.db_id = q.db_id AND m.w = q.w GROUP BY item_id, t, c, o),
        r AS (SELECT *, row_number() OVER (PARTITION BY item_id ORDER BY score DESC, t, o) AS nth FROM s)
        SELECT CAST(item_id AS BIGINT) AS item_id, t AS table_name, c AS column_name, score, CAST(nth AS INTEGER) AS nth FROM r WHERE nth <= 3"""


@query(_links_sql)
def q62_schema_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    return gb.link_schema(wi.core_items(spark), extract_all(spark, sf_dir))


def _intent_sql() -> str:
    text = "' ' || trim(regexp_replace(lower(question), '[^a-z0-9-]+', ' ', 'g')) || ' '"
    cases = " ".join(f"WHEN {' OR '.join(f'contains({text}, {quote(f' {c} ')})' for c in cues)} THEN '{name}'" for name, cues in gb.INTENTS)
    return f"SELECT CAST(item_id AS BIGINT) AS item_id, CASE {cases} ELSE 'lookup' END AS intent FROM {values([(i.item_id, i.question) for i in wi.ITEMS], 'item_id, question')}"


@query(_intent_sql)
def q63_intent_classes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return wi.core_items(spark).select("item_id", gb.intent_of(F.col("question")).alias("intent"))


#: Broken queries, the question asked, and the query that mends them.
BROKEN = (
    (1, "", "SELECT c_nme FROM customer", "SELECT c_name FROM customer"),
    (2, "", "SELECT count(*) FROM order", "SELECT count(*) FROM orders"),
    (3, "", "SELECT o_totalprize, o_orderkee FROM orders", "SELECT o_totalprice, o_orderkey FROM orders"),
    (4, "", "SELECT c_name FROM customer", "SELECT c_name FROM customer"),
    (6, "", "SELECT count(*) AS n FROM orders WHERE o_orderpriority = '1-URGENTT' GROUP BY o_orderpriority", "SELECT count(*) AS n FROM orders WHERE o_orderpriority = '1-URGENT' GROUP BY o_orderpriority"),
    (7, "How many orders have the status F ?", "SELECT o_orderkey FROM orders WHERE o_orderstatus = 'F'", "SELECT count(*) FROM orders WHERE o_orderstatus = 'F'"),
)


@query(" UNION ALL ".join(f"SELECT CAST({k} AS BIGINT) AS item_id, {0 if a == b else 2 if k == 3 else 1} AS rounds, (SELECT count(*) FROM ({b}) t) AS n_rows FROM (SELECT 1)" for k, _, a, b in BROKEN))
def q64_self_correct_trace(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rounds of correction by analysis, by empty results and by results of the wrong shape, and the rows that the mended query gives; the oracle runs the right one."""
    db = DATABASES["commerce"]
    session, schema = open_database(spark, sf_dir, db), columns_of(spark, sf_dir, db)
    rows = []
    for k, question, sql, _ in BROKEN:
        made, rounds, valid = gb.self_correct(session, sql, schema, 2, question, execute=True)
        rows.append((k, rounds, session.sql(made).count() if valid else -1))
    return spark.createDataFrame(rows, "item_id long, rounds int, n_rows long")


@query()
def q65_finetuned_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """family, size, tuned, n, accuracy of query classes, ex, ves, em on the target locale's dev items, of six trained stand-ins and their untuned forms."""
    from xlsql.workloads import experiments as ex

    log = ex.run_trained(ex.make_bench(spark, sf_dir))
    right = log.groupBy("family", "size", "tuned").agg(F.round(F.avg(F.col("class_right").cast("double")), 6).alias("accuracy"))
    return ex.score_log(log, ["family", "size", "tuned"]).join(right, ["family", "size", "tuned"]).select("family", "size", "tuned", "n", "accuracy", "ex", "ves", "em")


def _links() -> list[tuple[int, int, int]]:
    """(item, place in the evidence, place in the SQL) of each back-ticked name."""
    import re

    out = []
    for i in wi.ITEMS:
        for m in re.finditer(r"`(\w+)`", i.evidence):
            at = i.sql.find(m.group(1))
            if at >= 0:
                out.append((i.item_id, m.start(), at))
    return out


@query(f"""WITH l AS (SELECT * FROM {values(_links(), 'item_id, pos_text, pos_sql')}), s AS (SELECT item_id, count(*) AS links FROM l GROUP BY item_id),
    x AS (SELECT a.item_id, count(*) AS inversions FROM l a JOIN l b ON a.item_id = b.item_id AND a.pos_text < b.pos_text AND a.pos_sql > b.pos_sql GROUP BY a.item_id)
    SELECT CAST(s.item_id AS BIGINT) AS item_id, CAST(links AS INTEGER) AS links, CAST(coalesce(inversions, 0) AS INTEGER) AS inversions FROM s LEFT JOIN x ON x.item_id = s.item_id""")
def q66_inversions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cs.order_inversions(spark.createDataFrame(_links(), "item_id long, pos_text int, pos_sql int"))


@query(" UNION ALL ".join(f"SELECT '{OWNER[t]}' AS db_id, '{t}' AS table_name, count(*) AS n FROM {t}" for t in TABLES))
def q67_dataset_scale(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows of each table; counts come from the files' footers."""
    out = None
    for t in TABLES:
        part = load_table(spark, sf_dir, t).agg(F.count("*").alias("n")).select(F.lit(OWNER[t]).alias("db_id"), F.lit(t).alias("table_name"), "n")
        out = part if out is None else out.unionByName(part)
    return out


@query("WITH t AS (" + " UNION ALL ".join(f"SELECT '{OWNER[t]}' AS db_id, '{t}' AS table_name, count(*) AS n FROM {t}" for t in TABLES) + """)
    SELECT db_id, count(*) AS tables, CAST(sum(n) AS BIGINT) AS total, round(avg(n), 4) AS per_table, arg_max(table_name, n) AS largest FROM t GROUP BY db_id""")
def q67b_database_scale(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = q67_dataset_scale(spark, sf_dir)
    return t.groupBy("db_id").agg(F.count("*").alias("tables"), F.sum("n").alias("total"), F.round(F.avg("n"), 4).alias("per_table"), F.max_by("table_name", "n").alias("largest"))


@query()
def q67a_measured_times(spark: SparkSession, sf_dir: str) -> DataFrame:
    """item_id, ms_gold, ms_pred, correct: times measured here of gold and of an equal query, for the efficiency measure."""
    session = open_database(spark, sf_dir, DATABASES["commerce"])
    rows = []
    for kind, item, sql in wi.MUTANTS:
        if kind == "same":
            gold = wi.BY_ID[item].sql
            rows.append((item, ms.measure(session, gold, 3), ms.measure(session, sql, 3), True))
    return spark.createDataFrame(rows, "item_id long, ms_gold double, ms_pred double, correct boolean")
