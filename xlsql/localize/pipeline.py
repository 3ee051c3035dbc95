"""The whole construction: name maps, text, SQL, verification, flags, repair."""

from __future__ import annotations

import itertools
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from xlsql.catalog.spec import DATABASES, columns_of, extract_all, open_database
from xlsql.localize import sql_tree
from xlsql.localize import text as lt
from xlsql.mapping import names as nm
from xlsql.mapping.lexicon import lexicon_table
from xlsql.providers.base import EchoProvider, InventedLocaleProvider, Provider
from xlsql.session import materialize, run_folder
from xlsql.verify import checks
from xlsql.verify.exec_equal import run_pairs


def localize_items_sql(items: DataFrame, names: dict[str, dict], schemas: dict[str, dict[str, list[str]]]) -> DataFrame:
    """Add sql_loc and problems. Distinct texts are rewritten once, in the workers; maps and schemas are metadata."""

    def run(frames):
        import pandas as pd

        for frame in frames:
            made = [sql_tree.localize_sql(s, names[d], schemas[d]) for d, s in zip(frame["db_id"], frame["sql"])]
            yield pd.DataFrame({"db_id": frame["db_id"], "sql": frame["sql"], "sql_loc": [m[0] for m in made], "problems": [",".join(m[1]) for m in made]})

    texts = items.select("db_id", "sql").distinct().mapInPandas(run, "db_id string, sql string, sql_loc string, problems string")
    return items.join(texts, ["db_id", "sql"])


def open_both(spark: SparkSession, sf_dir: str, db_id: str, names: dict) -> tuple[SparkSession, SparkSession]:
    """Sessions of a database under its own and under its localized names."""
    target = spark.newSession()
    target.conf.set("spark.sql.session.timeZone", "UTC")
    nm.publish_localized_views(target, sf_dir, DATABASES[db_id], names)
    return open_database(spark, sf_dir, DATABASES[db_id]), target


def verify_items(spark: SparkSession, sf_dir: str, items: DataFrame, names: dict[str, dict], batch: int = 2000) -> DataFrame:
    """Add verdict and rung of each item's pair of texts. Distinct pairs only; most end at the plan rung, without reading data.

    Pairs are driven from here, several at a time, in batches whose verdicts are written, so any number of them passes through.
    """
    sessions, path = {d: open_both(spark, sf_dir, d, n) for d, n in names.items()}, run_folder(spark, "verdicts")
    schema = "db_id string, sql string, sql_loc string, verdict string, rung string"
    spark.createDataFrame([], schema).write.parquet(path)
    pairs = items.select("db_id", "sql", "sql_loc").distinct().toLocalIterator()
    while held := list(itertools.islice(pairs, batch)):
        asked = [(sessions[r["db_id"]][0], r["sql"], sessions[r["db_id"]][1], r["sql_loc"]) for r in held]
        results = run_pairs(asked)
        spark.createDataFrame([(*r, x.verdict, x.rung) for r, x in zip(held, results)], schema).write.mode("append").parquet(path)
    return items.join(spark.read.schema(schema).parquet(path), ["db_id", "sql", "sql_loc"])


@dataclass
class Maps:
    """The name map in force: the relation, and what workers need of it for each database."""

    table: DataFrame
    names: dict[str, dict]
    schemas: dict[str, dict[str, list[str]]]

    @classmethod
    def of(cls, spark: SparkSession, sf_dir: str, table: DataFrame, databases: list[str]) -> Maps:
        return cls(table, {d: nm.as_dict(table, d) for d in databases}, {d: columns_of(spark, sf_dir, DATABASES[d]) for d in databases})

    @property
    def localized(self) -> dict[str, dict[str, list[str]]]:
        return {d: {n["table"][t]: [n["column"][c] for c in cs] for t, cs in self.schemas[d].items()} for d, n in self.names.items()}


def localize_once(spark: SparkSession, sf_dir: str, items: DataFrame, maps: Maps, provider: Provider, joint: bool = True) -> DataFrame:
    """Evidence, text, SQL and verdict of each item under the maps in force, written."""
    parts = [items.where(F.col("db_id") == d).withColumn("evidence_std", lt.standardize_evidence(F.col("evidence"), lt.span_map(maps.table, d))) for d in maps.names]
    text = lt.localize_text(reduce(DataFrame.unionByName, parts), provider, "question", "evidence_std", joint).withColumnRenamed("evidence_std_loc", "evidence_loc")
    # verdicts are batches of jobs: what they are asked for is made once
    made = materialize(localize_items_sql(text, maps.names, maps.schemas), "localized")
    return materialize(verify_items(spark, sf_dir, made, maps.names), "verified")


def check_items(spark: SparkSession, held: DataFrame, maps: Maps, provider: Provider) -> DataFrame:
    """Flags (item_id, reason, detail): results that differ, names outside the map, spans that the item's SQL does not use, lost constants and comparisons, stray back-ticks."""
    refs = checks.sql_references(held.select("item_id", "db_id", F.col("sql_loc").alias("sql")), maps.localized)
    texts = held.withColumn("b", F.concat_ws(" ", "question", "evidence_std")).withColumn("a", F.concat_ws(" ", "question_loc", "evidence_loc"))
    found = (
        held.where("verdict <> 'equal'").select("item_id", F.lit("exec").alias("reason"), F.col("rung").alias("detail")),
        held.where("problems <> ''").select("item_id", F.lit("sql_name").alias("reason"), F.col("problems").alias("detail")),
        checks.check_sql_identifiers(refs, maps.table),
        checks.check_evidence_identifiers(held, maps.table, "evidence_loc", refs),
        lt.check_constants(texts, "b", "a").withColumn("detail", F.lit("")),
        lt.check_comparatives(held, lt.cue_table(spark), lt.cue_table(spark, getattr(provider, "phrase", None))),
        held.select("item_id", lt.parse_flags(F.col("evidence_loc")).alias("reason"), F.lit("").alias("detail")).where("reason is not null"),
    )
    return reduce(DataFrame.unionByName, found)


def amend_maps(spark: SparkSession, sf_dir: str, maps: Maps, databases: list[str]) -> Maps:
    """Maps made one-to-one again in the given databases; the version of their rows grows, other databases keep theirs."""
    mine = maps.table.where(F.col("db_id").isin(databases))
    again = nm.resolve_collisions(mine.withColumn("candidate", F.col("localized")).drop("localized")).withColumn("version", F.col("version") + 1)
    table = materialize(maps.table.where(~F.col("db_id").isin(databases)).unionByName(again.select(*maps.table.columns)), "maps")
    return Maps.of(spark, sf_dir, table, list(maps.names))


def build_localized(spark: SparkSession, sf_dir: str, items: DataFrame, locale: str = "es", provider: Provider | None = None, name_map: DataFrame | None = None, max_rounds: int = 3, history: list | None = None) -> DataFrame:
    """The whole construction: localize, verify, flag, judge, correct what the judge sends back, and verify it again.

    A map that is not one-to-one is amended, and all items of its database, and of no other, are made anew; texts that lost constants or spans, or that
    the judge sends back, are localized part by part, and in the last round kept as they were. Returns item_id, db_id, split, question_loc, evidence_loc, sql_loc, verdict,
    rung, flags, score, decision (``keep``, or what the judge says of an item that still fails), rounds. ``history`` collects (round, items made, items flagged).
    """
    provider = provider or InventedLocaleProvider()
    used = sorted(r[0] for r in items.select("db_id").distinct().collect())
    table = name_map if name_map is not None else nm.build_name_map(extract_all(spark, sf_dir), lexicon_table(spark, locale))
    maps, todo, done = Maps.of(spark, sf_dir, materialize(table, "maps"), used), items, None
    for k in range(max_rounds + 1):
        answers = provider if k < max_rounds else EchoProvider()
        held = localize_once(spark, sf_dir, todo, maps, answers, joint=k == 0)
        judged = checks.judge_alignment(checks.collect_flags(check_items(spark, held, maps, answers)))
        out = held.join(judged.select("item_id", "reasons", "score", "decision"), "item_id", "left")
        out = out.select("item_id", "db_id", "split", "question_loc", "evidence_loc", "sql_loc", "verdict", "rung", F.coalesce("reasons", F.lit("")).alias("flags"), F.coalesce("score", F.lit(1.0)).alias("score"), F.coalesce("decision", F.lit("keep")).alias("decision"), F.lit(k).alias("rounds"))
        out = materialize(out if done is None else done.join(todo.select("item_id"), "item_id", "left_anti").unionByName(out), "round")
        # a judge keeps small faults, but lost constants or spans make another question
        lost = F.array_contains(F.split("flags", ","), "constant")
        done, back = out, out.where((F.col("rounds") == k) & ((F.col("flags") != "") & (F.col("decision") != "keep") | lost | (F.col("verdict") != "equal")))
        flagged = {r["db_id"]: r["n"] for r in back.groupBy("db_id").agg(F.count("*").alias("n")).collect()}
        if history is not None:
            history.append((k, held.count(), sum(flagged.values())))
        if not flagged or k == max_rounds:
            return done
        # a database is amended once at least two names share an image
        broken = nm.check_bijection(maps.table.where(F.col("db_id").isin(used)), extract_all(spark, sf_dir).where(F.col("db_id").isin(used)))
        amended = sorted(r[0] for r in broken.select("db_id").distinct().collect())
        if amended:
            maps = amend_maps(spark, sf_dir, maps, amended)
        todo = items.where(F.col("db_id").isin(amended)).unionByName(items.where(~F.col("db_id").isin(amended)).join(back.select("item_id"), "item_id", "left_semi"))
    return done


def seeded_map(spark: SparkSession, sf_dir: str, locale: str = "es") -> DataFrame:
    """The name map with one fault: two columns of ``commerce`` share an image."""
    table = nm.build_name_map(extract_all(spark, sf_dir), lexicon_table(spark, locale))
    shared = table.where("db_id = 'commerce' and source_name = 'c_acctbal'").select(F.col("localized").alias("taken"))
    hit = (F.col("db_id") == "commerce") & (F.col("source_name") == "c_custkey")
    return table.crossJoin(F.broadcast(shared)).withColumn("localized", F.when(hit, F.col("taken")).otherwise(F.col("localized"))).drop("taken")


def repair_demo(spark: SparkSession, sf_dir: str) -> DataFrame:
    """round, made, flagged: the construction over the core items, begun with a map in which two names share an image."""
    from xlsql.workloads.items import core_items

    history: list[tuple[int, int, int]] = []
    build_localized(spark, sf_dir, core_items(spark), name_map=seeded_map(spark, sf_dir), history=history)
    return spark.createDataFrame(history, "round int, made long, flagged long")
