"""The experiments: inference methods by language and run, trained families in the target locale, scored by EM, EX and VES from executions."""

from __future__ import annotations

import re
import time
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from xlsql.catalog.spec import DATABASES, columns_of, extract_all
from xlsql.generate import baselines as gb
from xlsql.localize.pipeline import Maps, build_localized, open_both
from xlsql.mapping import names as nm
from xlsql.mapping.lexicon import lexicon_table
from xlsql.metrics import scores as ms
from xlsql.providers.base import InventedLocaleProvider
from xlsql.session import materialize
from xlsql.verify.exec_equal import run_pairs
from xlsql.workloads import items as wi

LANGUAGES, RUNS = ("source", "target"), 3
LOG = "method string, lang string, run int, config_hash string, item_id long, correct boolean, same boolean, time_gold double, time_pred double"


@dataclass
class Bench:
    """Items in both languages (item_id, db_id, split, intent, lang, question, evidence, sql), and for each language the databases' sessions and schemas."""

    items: DataFrame
    maps: Maps
    sessions: dict[tuple[str, str], SparkSession]
    schemas: dict[tuple[str, str], dict[str, list[str]]]
    meta: dict[str, DataFrame]


def make_bench(spark: SparkSession, sf_dir: str, n: int = 320, locale: str = "es") -> Bench:
    """``n`` made items and the core items, localized and verified; only pairs whose execution agrees are kept."""
    source = wi.make_items(spark, sf_dir, n).unionByName(wi.core_items(spark))
    made = build_localized(spark, sf_dir, source, locale).where("verdict = 'equal'")
    cols = ["item_id", "db_id", "split", "intent", "lang", "question", "evidence", "sql"]
    kept = source.join(made.select("item_id", "question_loc", "evidence_loc", "sql_loc"), "item_id")
    target = kept.select("item_id", "db_id", "split", "intent", F.lit("target").alias("lang"), F.col("question_loc").alias("question"), F.col("evidence_loc").alias("evidence"), F.col("sql_loc").alias("sql"))
    items = materialize(kept.withColumn("lang", F.lit("source")).select(*cols).unionByName(target.select(*cols)), "bench")
    meta = extract_all(spark, sf_dir)
    table = nm.build_name_map(meta, lexicon_table(spark, locale))
    maps = Maps.of(spark, sf_dir, table, list(DATABASES))
    sessions, schemas = {}, {}
    for d in DATABASES:
        sessions["source", d], sessions["target", d] = open_both(spark, sf_dir, d, maps.names[d])
        schemas["source", d], schemas["target", d] = columns_of(spark, sf_dir, DATABASES[d]), maps.localized[d]
    return Bench(items, maps, sessions, schemas, {"source": meta, "target": localized_meta(meta, table)})


def localized_meta(meta: DataFrame, table: DataFrame) -> DataFrame:
    """Schema metadata under localized names; descriptions in the invented locale."""
    phrase = InventedLocaleProvider().phrase
    told = {r[0]: phrase(r[0]) for r in meta.where("description is not null").select("description").distinct().collect()}
    image = lambda kind: F.broadcast(table.where(F.col("kind") == kind).select("db_id", F.col("source_name").alias(f"{kind}_name"), F.col("localized").alias(f"_{kind}")))
    out = meta.join(image("table"), ["db_id", "table_name"], "left").join(image("column"), ["db_id", "column_name"], "left")
    note = F.element_at(F.create_map(*[F.lit(x) for kv in told.items() for x in kv]), F.col("description")) if told else F.col("description")
    return out.select("db_id", F.col("_table").alias("table_name"), F.col("_column").alias("column_name"), "ordinal", "data_type", "is_key", "ref_table", "ref_column", note.alias("description"))


def infer(bench: Bench, rows: list, lang: str, method: str, run: int, config: gb.ExperimentConfig, stages=("link", "intent", "correct")) -> list[tuple]:
    """(method, lang, run, config, item_id, db_id, SQL) of one method in one language. Linking and intents are DataFrame plans; their short results come here."""
    links: dict[int, list[tuple[str, str]]] = {}
    intents: dict[int, str] = {}
    asked = {r["item_id"]: gb.canonical_question(r["question"], lang, config.coverage) for r in rows}
    if method == "staged":
        spark = bench.items.sparkSession
        mine = spark.createDataFrame([(r["item_id"], r["db_id"], asked[r["item_id"]], r["evidence"]) for r in rows], "item_id long, db_id string, question string, evidence string")
        for r in gb.link_schema(mine, bench.meta[lang], 4, config.evidence).orderBy("item_id", "nth").collect():
            links.setdefault(r["item_id"], []).append((r["table_name"], r["column_name"]))
        intents = {r[0]: r[1] for r in mine.select("item_id", gb.intent_of(F.col("question"))).collect()}
    out = []
    for r in rows:
        k, schema, evidence = r["item_id"], bench.schemas[lang, r["db_id"]], r["evidence"] if config.evidence else ""
        if method == "direct":
            sql = gb.direct(asked[k], evidence, schema, run)
        else:
            sql = gb.staged(asked[k], evidence, schema, links.get(k, []), intents[k], stages, run)
            if "correct" in stages:
                sql = gb.self_correct(bench.sessions[lang, r["db_id"]], sql, schema, 2, asked[k], execute=True)[0]
        out.append((method, lang, run, config.hash, k, r["db_id"], sql))
    return out


def run_log(bench: Bench, preds: list[tuple], gold: dict[tuple[str, int], str], timed: bool = True) -> DataFrame:
    """``LOG``: every prediction executed against gold, each distinct pair once, several at a time; then the texts of right ones timed one by one.

    A pair of equal texts has equal times, so only different texts that are right are run for time, gold and prediction in turn.
    """
    pairs = list(dict.fromkeys((lang, db, gold[lang, k], sql) for _, lang, _, _, k, db, sql in preds))
    asked = [(bench.sessions[lang, db], a, bench.sessions[lang, db], b) for lang, db, a, b in pairs]
    right = {p: r.equal for p, r in zip(pairs, run_pairs(asked, snapshots=("", "")))}
    known: dict[tuple, float] = {}

    def cost(lang: str, db: str, sql: str) -> float:
        if (lang, db, sql) not in known:
            best = []
            for _ in range(2):
                began = time.perf_counter()
                bench.sessions[lang, db].sql(sql).write.format("noop").mode("overwrite").save()
                best.append((time.perf_counter() - began) * 1000)
            known[lang, db, sql] = min(best)
        return known[lang, db, sql]

    rows = []
    for method, lang, run, config, k, db, sql in preds:
        a = gold[lang, k]
        ok, same = right[lang, db, a, sql], ms.normalize_sql(sql) == ms.normalize_sql(a)
        times = (cost(lang, db, a), cost(lang, db, sql)) if ok and timed and not same else (1.0, 1.0)
        rows.append((method, lang, run, config, k, ok, same, *map(float, times)))
    return bench.items.sparkSession.createDataFrame(rows, LOG)


def score_log(log: DataFrame, by: list[str]) -> DataFrame:
    """by, n, ex, ves, ratio, em."""
    em = log.groupBy(*by).agg(F.round(F.avg(F.col("same").cast("double")), 6).alias("em"))
    return ms.score(log, by).join(em, by)


def run_inference(bench: Bench, runs: int = RUNS, config: gb.ExperimentConfig | None = None, split: str = "dev") -> DataFrame:
    """``LOG`` of both methods in both languages, ``runs`` times each, under one configuration."""
    config = config or gb.ExperimentConfig("offline")
    rows = {lang: bench.items.where((F.col("lang") == lang) & (F.col("split") == split)).orderBy("item_id").collect() for lang in LANGUAGES}
    gold = {(lang, r["item_id"]): r["sql"] for lang in LANGUAGES for r in rows[lang]}
    preds = [p for method in ("direct", "staged") for lang in LANGUAGES for run in range(runs) for p in infer(bench, rows[lang], lang, method, run, config)]
    return run_log(bench, preds, gold)


def measure_rows(scores: DataFrame, keys: list[str]) -> DataFrame:
    """keys, measure, value from columns em, ex, ves."""
    return scores.unpivot(keys, ["em", "ex", "ves"], "measure", "value")


FORMS = {"filtered_count": "filter_count", "group_aggregate": "group", "multi_join": "group", "scalar_subquery": "nested"}


def fill_template(r, intent: str, family: str, schema: dict[str, list[str]]) -> str:
    """A query of the predicted class. The code family fills it from the evidence's spans; the multilingual family knows tables only."""
    question = gb.canonical_question(r["question"], r["lang"])
    named = re.findall(r"`(\w+)`", r["evidence"]) if family == "code" else []
    table = next((t for t, cols in schema.items() if any(c in cols for c in named)), None) or next((t for t in sorted(schema) if t.rstrip("s") in question.lower()), sorted(schema)[0])
    return gb._template(FORMS.get(intent, intent), table, [c for c in named if c in schema[table]], question, r["evidence"] if family == "code" else "")


def run_trained(bench: Bench, lang: str = "target") -> DataFrame:
    """family, size, tuned, accuracy of query classes, and ``LOG`` of six stand-ins and their untuned forms, fitted on train and scored on dev in one language."""
    spark = bench.items.sparkSession
    items = bench.items.where(F.col("lang") == lang)
    train, dev = items.where("split = 'train'"), items.where("split = 'dev'")
    held = {r["item_id"]: r for r in dev.collect()}
    gold, preds, hits = {(lang, k): r["sql"] for k, r in held.items()}, [], []
    for family, sizes in (("multilingual", "S M L"), ("code", "0.5 1.5 3")):
        for size in sizes.split():
            for tuned in (False, True):
                fitted = gb.fit_template_model(train, family, size) if tuned else None
                for r in gb.predict_intents(dev, fitted, family, size).collect():
                    item = held[r["item_id"]]
                    method = f"{family} {size} {'tuned' if tuned else 'base'}"
                    preds.append((method, lang, 0, gb.ExperimentConfig(f"{family} {size}").hash, r["item_id"], item["db_id"], fill_template(item, r["predicted"], family, bench.schemas[lang, item["db_id"]])))
                    hits.append((method, r["item_id"], r["intent"] == r["predicted"]))
    told = spark.createDataFrame(hits, "method string, item_id long, class_right boolean")
    parts = F.split("method", " ")
    return run_log(bench, preds, gold).join(told, ["method", "item_id"]).withColumn("family", parts[0]).withColumn("size", parts[1]).withColumn("tuned", parts[2] == "tuned")
