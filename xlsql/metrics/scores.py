"""Exact match, execution accuracy, valid efficiency, and the comparisons drawn from them."""

from __future__ import annotations

import time
import uuid
from collections.abc import Iterator, Sequence

import pandas as pd
from pyspark.errors import PySparkException
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from xlsql.localize.sql_tree import SHAPING, SOFT, tokenize

#: Times below this (milliseconds) are raised to it, so that no ratio divides by zero.
RESOLUTION = 0.001


def normalize_sql(sql: str | None, level: str = "canonical") -> str:
    """Normal form of a query.

    surface: comments and blanks squeezed, closing semicolons dropped. canonical: besides, keywords and unquoted names in lower case,
    needless quotes dropped, ``<>`` for ``!=``, ``=`` for ``==``, number forms, no optional AS, table aliases numbered.
    """
    if not sql:
        return ""
    tokens = [t for t in tokenize(sql) if t.kind != "blank"]
    while tokens and tokens[-1].text == ";":
        tokens.pop()
    if level == "surface":
        return " ".join(t.text for t in tokens)
    out = []
    for t in tokens:
        text = t.text
        if t.kind == "word":
            text = t.low
        elif t.kind == "quoted" and t.name.isidentifier() and t.name.lower() not in SHAPING:
            text = t.name.lower()
        elif t.kind == "text" and text[0] == '"':
            text = "'" + text[1:-1].replace("'", "''") + "'"
        elif t.kind == "number":
            text = text.rstrip("LDSYF").lstrip("0") or "0"
            if "." in text:
                text = text.rstrip("0").rstrip(".") or "0"
        out.append({"!=": "<>", "==": "="}.get(text, text))
    renamed: dict[str, str] = {}
    # FROM or JOIN, a table, perhaps AS, and a name that nothing shapes: an alias
    i = 0
    in_from = False
    while i < len(out):
        if out[i] in ("from", "join") or in_from and out[i] == ",":
            in_from = True
            k = i + 2
            if k < len(out) and out[k] == "as":
                del out[k]
            if k < len(out) and out[k].isidentifier() and out[k] not in SHAPING | SOFT and out[i + 1].isidentifier():
                renamed.setdefault(out[k], f"t{len(renamed) + 1}")
        elif out[i] in ("where", "group", "order", "having", "select"):
            in_from = False
        i += 1
    out = [t for i, t in enumerate(out) if not (t == "as" and i + 1 < len(out) and out[i + 1] != "(" and not _in_cast(out, i))]
    return " ".join(renamed.get(t, t) if i + 1 < len(out) and out[i + 1] == "." or i and out[i - 1] != "." else t for i, t in enumerate(out))


def _in_cast(out: list[str], i: int) -> bool:
    depth = 0
    while i > 0:
        i -= 1
        depth += {")": 1, "(": -1}.get(out[i], 0)
        if depth < 0:
            return i > 0 and out[i - 1] in ("cast", "try_cast")
    return False


def with_normal_form(df: DataFrame, sql: str, out: str, level: str = "canonical") -> DataFrame:
    def run(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for b in batches:
            yield b.map(lambda s: normalize_sql(s, level))

    return df.withColumn(out, F.pandas_udf(run, "string")(F.col(sql)))


def exact_match(preds: DataFrame, gold: DataFrame, by: Sequence[str], level: str = "canonical") -> DataFrame:
    """by, n, em over all gold items; missing predictions count as wrong. Normal forms are made once for each distinct text."""
    texts = preds.select("sql").unionByName(gold.select("sql")).distinct()
    forms = with_normal_form(texts, "sql", "form", level)
    p = preds.join(forms, "sql", "left").withColumnRenamed("form", "form_p").drop("sql")
    g = gold.select("item_id", "sql").join(forms, "sql").select("item_id", F.col("form").alias("form_g"))
    hit = F.coalesce((F.col("form_p") == F.col("form_g")) & (F.col("form_g") != ""), F.lit(False)).cast("double")
    return p.join(g, "item_id").groupBy(*by).agg(F.count("*").alias("n"), F.avg(hit).alias("em"))


def plan_match(session: SparkSession, predicted: str, gold: str) -> bool:
    """Exact match on plans: normal forms agree, or both texts analyse to the same plan."""
    if normalize_sql(predicted) == normalize_sql(gold):
        return True
    try:
        return session.sql(predicted).sameSemantics(session.sql(gold))
    except PySparkException:
        return False


def ves_reward(gold: Column, predicted: Column) -> Column:
    return F.sqrt(F.greatest(gold, F.lit(RESOLUTION)) / F.greatest(predicted, F.lit(RESOLUTION)))


def score(log: DataFrame, by: Sequence[str]) -> DataFrame:
    """by, n, ex, ves, ratio from rows (correct, time_gold, time_pred): wrong ones count zero; ratio is the mean reward of correct ones."""
    ok = F.coalesce(F.col("correct"), F.lit(False))
    reward = F.when(ok, ves_reward(F.col("time_gold"), F.col("time_pred")))
    return log.groupBy(*by).agg(F.count("*").alias("n"), F.round(F.avg(ok.cast("double")), 6).alias("ex"), F.round(F.avg(F.coalesce(reward, F.lit(0.0))), 6).alias("ves"), F.round(F.avg(reward), 6).alias("ratio"))


def trim_times(log: DataFrame, by: Sequence[str], time_column: str, sigmas: float = 3.0) -> DataFrame:
    """by, n, n_kept, mean of times within ``sigmas`` standard deviations of their group's mean. Two aggregations, no window."""
    s = log.groupBy(*by).agg(F.avg(time_column).alias("m"), F.stddev_pop(time_column).alias("d"), F.count("*").alias("n"))
    kept = log.join(s, list(by)).where(F.abs(F.col(time_column) - F.col("m")) <= sigmas * F.col("d") + 1e-12)
    return kept.groupBy(*by).agg(F.max("n").alias("n"), F.count("*").alias("n_kept"), F.round(F.avg(time_column), 6).alias("mean"))


def stage_totals(session: SparkSession, group: str) -> dict[str, float]:
    """cpu (milliseconds of executors) and bytes_read of all stages that a job group has run, from the application's own status store."""
    tracker, store = session.sparkContext.statusTracker(), session.sparkContext._jsc.sc().statusStore()
    out = {"cpu": 0.0, "bytes_read": 0.0}
    for job in tracker.getJobIdsForGroup(group):
        info = tracker.getJobInfo(job)
        for stage in info.stageIds if info else ():
            try:
                data = store.lastStageAttempt(stage)
            except Exception:  # a skipped stage has no attempt
                continue
            out["cpu"] += data.executorCpuTime() / 1e6
            out["bytes_read"] += data.inputBytes()
    return out


def measure(session: SparkSession, sql: str, reps: int = 5, warmup: int = 1, sigmas: float = 3.0, clock: str = "wall") -> float:
    """Cost of running a query into the empty sink: mean of repeats within ``sigmas`` deviations, after warm-up runs.

    ``clock``: wall (milliseconds), cpu (milliseconds of executors), or bytes_read as the scans report it, which does not vary with the machine.
    """
    costs, context = [], session.sparkContext
    for k in range(warmup + reps):
        group = f"measure-{uuid.uuid4().hex}"
        context.setJobGroup(group, sql[:80])
        began = time.perf_counter()
        session.sql(sql).write.format("noop").mode("overwrite").save()
        took = (time.perf_counter() - began) * 1000
        if k >= warmup:
            costs.append(took if clock == "wall" else stage_totals(session, group)[clock])
    context.setLocalProperty("spark.jobGroup.id", None)
    mean = sum(costs) / len(costs)
    spread = (sum((t - mean) ** 2 for t in costs) / len(costs)) ** 0.5
    kept = [t for t in costs if abs(t - mean) <= sigmas * spread + 1e-9]
    return sum(kept) / len(kept)


def execution_accuracy(preds: list[tuple], gold: dict[int, str], session: SparkSession, mode: str = "auto", cache=None) -> list[tuple]:
    """(..., item_id, correct) of predictions (..., item_id, sql). Distinct pairs of texts are compared once, several at a time, and each distinct plan runs once; invalid ones are wrong."""
    from xlsql.verify.exec_equal import run_pairs

    known: dict[tuple, bool] = {} if cache is None else cache
    new = list(dict.fromkeys((gold[r[-2]], r[-1]) for r in preds if r[-1] and (gold[r[-2]], r[-1]) not in known))
    results = run_pairs([(session, a, session, b) for a, b in new], mode, snapshots=("", ""))
    known.update(zip(new, (r.equal for r in results)))
    return [(*r[:-1], known.get((gold[r[-2]], r[-1]), False)) for r in preds]


def average_runs(scores: DataFrame, by: Sequence[str], measures: Sequence[str]) -> DataFrame:
    """by, runs, mean and spread of each measure over runs."""
    aggs = [a for m in measures for a in (F.round(F.avg(m), 6).alias(f"{m}_mean"), F.round(F.stddev_samp(m), 6).alias(f"{m}_sd"))]
    return scores.groupBy(*by).agg(F.count("*").alias("runs"), *aggs)


def contrast(scores: DataFrame, on: str, first: str, second: str, by: Sequence[str], value: str = "value") -> DataFrame:
    """by, first_value, second_value, gain (second − first), relative: of two levels of ``on``, by one small pivot."""
    wide = scores.groupBy(*by).pivot(on, [first, second]).agg(F.first(value))
    a, b = F.col(f"`{first}`"), F.col(f"`{second}`")
    return wide.select(*by, a.alias("first_value"), b.alias("second_value"), F.round(b - a, 4).alias("gain"), F.round(100 * (b - a) / a, 4).alias("relative"))


def method_gain(scores: DataFrame, first: str = "direct", second: str = "staged") -> DataFrame:
    return contrast(scores, "method", first, second, ["lang", "measure"])


def language_gap(scores: DataFrame, source: str = "source", target: str = "target") -> DataFrame:
    return contrast(scores, "lang", target, source, ["method", "measure"])


def rank_stability(scores: DataFrame) -> DataFrame:
    """measure, stable: whether methods rank alike in all languages."""
    r = scores.withColumn("rank", F.rank().over(Window.partitionBy("lang", "measure").orderBy(F.desc("value"))))
    ranks = r.groupBy("measure", "method").agg(F.countDistinct("rank").alias("d"))
    return ranks.groupBy("measure").agg((F.max("d") == 1).alias("stable"))


def scaling_trend(scores: DataFrame) -> DataFrame:
    """family, measure, monotone: whether each larger model of a family scores higher. Columns family, size_order, measure, value."""
    w = Window.partitionBy("family", "measure").orderBy("size_order")
    step = scores.withColumn("step", F.col("value") - F.lag("value").over(w))
    return step.groupBy("family", "measure").agg(F.coalesce(F.min("step") > 0, F.lit(True)).alias("monotone"), F.round(F.max("value") - F.min("value"), 4).alias("spread"))


def cross_family(scores: DataFrame, better: str, worse: str) -> DataFrame:
    """measure, better_model, worse_model, holds: every pair across two families."""
    a = scores.where(F.col("family") == better).select("measure", F.col("model").alias("better_model"), F.col("value").alias("x"))
    b = scores.where(F.col("family") == worse).select("measure", F.col("model").alias("worse_model"), F.col("value").alias("y"))
    return a.join(b, "measure").select("measure", "better_model", "worse_model", (F.col("x") > F.col("y")).alias("holds"))
