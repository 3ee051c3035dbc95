"""Integrity checks, flags, the rubric judge, and the loop that corrects and verifies again."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from xlsql.functions.text import spans
from xlsql.localize.sql_tree import referenced_names

REASONS = ("exec", "sql_name", "evidence_name", "constant", "comparative", "backtick")
# The rubric's weights.
RUBRIC = {"exec": 0.4, "sql_name": 0.2, "evidence_name": 0.15, "constant": 0.15, "comparative": 0.05, "backtick": 0.05}
FLAG = "item_id long, reason string, detail string"


def sql_references(items: DataFrame, schemas: dict[str, dict[str, list[str]]], sql: str = "sql", key: str = "item_id") -> DataFrame:
    """key, db_id, kind, name: every table and column that each item's SQL refers to. Schemas are metadata, sent to every task."""

    def run(frames):
        import pandas as pd

        for frame in frames:
            rows = []
            for k, db, text in zip(frame[key], frame["db_id"], frame[sql]):
                for kind, names in referenced_names(text or "", schemas.get(db, {})).items():
                    rows += [(k, db, kind, n) for n in sorted(names)]
            yield pd.DataFrame(rows, columns=[key, "db_id", "kind", "name"])

    return items.select(key, "db_id", sql).mapInPandas(run, f"{key} long, db_id string, kind string, name string")


def check_sql_identifiers(references: DataFrame, name_map: DataFrame) -> DataFrame:
    """Flags of names in localized SQL that no identifier of the database maps to."""
    known = name_map.select("db_id", "kind", F.col("localized").alias("name")).distinct()
    return references.join(F.broadcast(known), ["db_id", "kind", "name"], "left_anti").select("item_id", F.lit("sql_name").alias("reason"), F.col("name").alias("detail"))


def check_evidence_identifiers(items: DataFrame, name_map: DataFrame, text: str = "evidence_loc", references: DataFrame | None = None) -> DataFrame:
    """Flags of back-ticked spans that are no localized identifier; with ``references`` also of those that the item's SQL does not use."""
    at = items.select("item_id", "db_id", F.explode(spans(F.col(text))).alias("span")).withColumn("name", F.element_at(F.split("span", r"\."), -1))
    known = name_map.select("db_id", F.col("localized").alias("name")).distinct()
    bad = at.join(F.broadcast(known), ["db_id", "name"], "left_anti")
    if references is not None:
        bad = bad.unionByName(at.join(references.select("item_id", "name").distinct(), ["item_id", "name"], "left_anti")).distinct()
    return bad.select("item_id", F.lit("evidence_name").alias("reason"), F.col("span").alias("detail"))


def collect_flags(*checks: DataFrame) -> DataFrame:
    """item_id, reasons, n: what each flagged item failed."""
    out = checks[0]
    for c in checks[1:]:
        out = out.unionByName(c)
    return out.groupBy("item_id").agg(F.array_join(F.array_sort(F.collect_set("reason")), ",").alias("reasons"), F.count("*").alias("n"))


def rubric_score(reasons: Column) -> Column:
    """1 less the weights of the reasons (comma-joined) of a flagged item."""
    lost = sum((F.when(F.array_contains(F.split(reasons, ","), r), w).otherwise(0.0) for r, w in RUBRIC.items()), F.lit(0.0))
    return F.round(1.0 - lost, 6)


def judge_alignment(flags: DataFrame, keep: float = 0.8) -> DataFrame:
    """Score and decision of each flagged item: keep, repair or drop."""
    scored = flags.withColumn("score", rubric_score(F.col("reasons")))
    return scored.withColumn("decision", F.when(F.col("score") >= keep, "keep").when(F.col("score") >= 0.4, "repair").otherwise("drop"))


def judge_with_provider(flagged: DataFrame, provider) -> DataFrame:
    """item_id, text: a provider's judgement of each flagged item; columns item_id, question_loc, sql_loc, reasons."""
    from xlsql.providers.base import complete

    asked = flagged.withColumn("prompt", F.concat_ws("\n", F.lit("# Judge"), "question_loc", "sql_loc", "reasons"))
    made = complete(asked.select(F.lit("judge").alias("task"), "prompt"), provider)
    key = F.md5(F.concat_ws("\x1f", F.lit("judge"), "prompt", F.lit("")))
    return asked.withColumn("key", key).join(made, "key", "left").select("item_id", "text")


def repair_loop(state: dict, verify: Callable[[dict], DataFrame], repair: Callable[[dict, DataFrame], dict], max_rounds: int = 5) -> tuple[dict, list[int]]:
    """Verify, correct what is flagged, verify again, until nothing is flagged or nothing changes.

    ``repair`` returns the amended state; it names the databases whose map it changed in ``state["amended"]``, so that only their items
    need to be made anew. Returns the state and the number of flagged items of each round.
    """
    history: list[int] = []
    for _ in range(max_rounds):
        flags = verify(state)
        history.append(flags.select("item_id").distinct().count())
        if not history[-1] or len(history) > 1 and history[-1] == history[-2]:
            break
        state = repair(state, flags)
    return state, history
