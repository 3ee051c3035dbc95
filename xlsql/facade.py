"""One object for the usual course of work: register, map, localize, verify, sample, report, generate, evaluate, compare."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from xlsql.catalog.spec import DATABASES, DatabaseSpec, columns_of, extract_schema, open_database
from xlsql.generate import baselines as gb
from xlsql.localize.pipeline import build_localized
from xlsql.mapping import names as nm
from xlsql.mapping.lexicon import lexicon_table
from xlsql.metrics import scores as ms
from xlsql.providers.base import Provider
from xlsql.stats import corpus as cs
from xlsql.stats import sampling as sm


class XlSession:
    """Work on the databases in one folder of Parquet tables."""

    def __init__(self, spark: SparkSession, folder: str, locale: str = "es"):
        self.spark, self.folder, self.locale = spark, folder, locale
        self.databases: dict[str, DatabaseSpec] = {}
        self.maps: dict[str, dict[str, dict[str, str]]] = {}

    def register_database(self, db: DatabaseSpec | str) -> "XlSession":
        db = DATABASES[db] if isinstance(db, str) else db
        self.databases[db.db_id] = db
        return self

    def build_map(self, rule: str = "suffix") -> DataFrame:
        """The name map of all registered databases, checked to be one-to-one."""
        meta = None
        for db in self.databases.values():
            part = extract_schema(self.spark, self.folder, db)
            meta = part if meta is None else meta.unionByName(part)
        made = nm.build_name_map(meta, lexicon_table(self.spark, self.locale), rule)
        bad = nm.check_bijection(made, meta).limit(5).collect()
        if bad:
            raise ValueError(f"not one-to-one: {bad}")
        self.maps = {d: nm.as_dict(made, d) for d in self.databases}
        return made

    def localize(self, items: DataFrame, provider: Provider | None = None) -> DataFrame:
        """Localized items with verdict and flags of each."""
        return build_localized(self.spark, self.folder, items, self.locale, provider)

    def verify(self, localized: DataFrame) -> DataFrame:
        """verdict, rung, n."""
        return localized.groupBy("verdict", "rung").agg(F.count("*").alias("n"))

    def plan_sample(self, population: DataFrame, **options) -> DataFrame:
        return sm.plan_sample(population, **options)

    def estimate(self, verdicts: DataFrame, population: int, verdict: str = "correct", method: str = "wald") -> DataFrame:
        """k, n, accuracy and interval."""
        seen = sm.observed_accuracy(verdicts, verdict)
        return seen.withColumn("interval", sm.accuracy_interval(F.col("k"), F.col("n"), None if method == "wilson" else F.lit(population), method=method))

    def corpus_report(self, texts: DataFrame, text: str = "text", by: str = "lang", base: str = "en") -> DataFrame:
        return cs.percent_change(cs.corpus_stats(texts, text, [by]), by, base)

    def generate(self, question: str, evidence: str, db_id: str) -> str:
        """One query by the direct generator, corrected by what its analysis says."""
        schema = columns_of(self.spark, self.folder, self.databases[db_id])
        session = open_database(self.spark, self.folder, self.databases[db_id])
        return gb.self_correct(session, gb.direct(question, evidence, schema), schema)[0]

    def evaluate(self, preds: dict[int, str], gold: dict[int, str], db_id: str, mode: str = "auto") -> DataFrame:
        """item_id, correct, same: execution accuracy and exact match of each prediction."""
        session = open_database(self.spark, self.folder, self.databases[db_id])
        rows = ms.execution_accuracy(list(preds.items()), gold, session, mode)
        rows = [(k, ok, ms.normalize_sql(preds[k]) == ms.normalize_sql(gold[k])) for k, ok in rows]
        return self.spark.createDataFrame(rows, "item_id long, correct boolean, same boolean")

    def compare(self, scores: DataFrame) -> dict[str, DataFrame]:
        """Gains of methods, gaps of languages, stability of ranks; scores: method, lang, measure, value."""
        return {"gain": ms.method_gain(scores), "gap": ms.language_gap(scores), "stability": ms.rank_stability(scores)}
