"""Evaluation logs as they arrive: windows, sessions, late rows, repeats, state and upserts."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from xlsql.session import run_folder


def event_stream(spark: SparkSession, path: str, files: int = 4) -> DataFrame:
    """Stream of a Parquet folder or file of events; ``ts`` becomes a zoned timestamp, as watermarks need."""
    batch = spark.read.parquet(path)
    folder = path if not path.rstrip("/").rsplit("/", 1)[-1].count(".") else path
    return spark.readStream.schema(batch.schema).option("maxFilesPerTrigger", files).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def staged_files(df: DataFrame, parts: int, order: str) -> str:
    """Write a table as files in order of a column into the shared folder, to be read as a stream."""
    path = run_folder(df.sparkSession, "stream")
    df.repartitionByRange(parts, order).sortWithinPartitions(order).write.parquet(path)
    return path


def drain(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run a stream over what is there into the shared folder and return the rows: all (append, update) or those of the last batch (complete).

    In update and complete mode every batch overwrites a folder of its own, so a batch that runs twice counts once; nothing comes to the driver.
    """
    spark = stream.sparkSession
    mark, out = run_folder(spark, f"{name}-offsets"), run_folder(spark, f"{name}-sink")
    if mode == "append":
        stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", mark).outputMode("append").trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(out)
    spark.createDataFrame([], stream.schema).write.parquet(f"{out}/batch=-1")

    def keep(rows: DataFrame, batch: int) -> None:
        rows.write.mode("overwrite").parquet(f"{out}/batch={batch}")

    stream.writeStream.foreachBatch(keep).option("checkpointLocation", mark).outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    held = spark.read.option("basePath", out).parquet(out)
    if mode == "complete":
        held = held.where(F.col("batch") == held.agg(F.max("batch")).first()[0])
    return held.select(*stream.columns)


def tumbling(events: DataFrame, size: str = "1 day", late: str = "1 hour") -> DataFrame:
    """window_start, event_type, n, total for each window of a type."""
    e = events.withWatermark("ts", late).groupBy(F.window("ts", size), "event_type")
    return e.agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total")).select(F.col("window.start").alias("window_start"), "event_type", "n", "total")


def sliding(events: DataFrame, size: str = "2 days", slide: str = "1 day", late: str = "1 hour") -> DataFrame:
    e = events.withWatermark("ts", late).groupBy(F.window("ts", size, slide))
    return e.agg(F.count("*").alias("n")).select(F.col("window.start").alias("window_start"), "n")


def sessions(events: DataFrame, gap: str = "10 minutes", late: str = "1 hour") -> DataFrame:
    """user_id, session_start, session_end, n."""
    e = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id")
    return e.agg(F.count("*").alias("n")).select("user_id", F.col("session_window.start").alias("session_start"), F.col("session_window.end").alias("session_end"), "n")


def distinct_events(events: DataFrame, keys: list[str], late: str = "1 hour") -> DataFrame:
    """Rows without repeats of ``keys`` inside the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(keys)


def running_means(events: DataFrame, key: str = "event_type", value: str = "value") -> DataFrame:
    """key, n, mean, m2: count, mean and squared deviations of each key, kept in state over micro-batches (update mode)."""

    def step(k: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, mean, m2 = state.get if state.exists else (0, 0.0, 0.0)
        for frame in frames:
            for x in frame[value].dropna():
                n += 1
                d = x - mean
                mean += d / n
                m2 += d * (x - mean)
        state.update((n, mean, m2))
        yield pd.DataFrame({key: [k[0]], "n": [n], "mean": [mean], "m2": [m2]})

    return events.select(key, value).groupBy(key).applyInPandasWithState(step, f"{key} string, n long, mean double, m2 double", "n long, mean double, m2 double", "update", GroupStateTimeout.NoTimeout)


def latest(updates: DataFrame, key: str, by: str) -> DataFrame:
    """Last row of each key of an update stream's output."""
    rest = [c for c in updates.columns if c != key]
    return updates.groupBy(key).agg(F.max_by(F.struct(*rest), by).alias("x")).select(key, "x.*")


def upsert(stream: DataFrame, apply: Callable[[DataFrame, int], None], trigger_once: bool = True) -> None:
    """Hand every micro-batch to ``apply`` (foreachBatch), which merges it into a table."""
    writer = stream.writeStream.foreachBatch(apply).option("checkpointLocation", run_folder(stream.sparkSession, "offsets"))
    (writer.trigger(availableNow=True) if trigger_once else writer).start().awaitTermination()


def with_gold(log: DataFrame, items: DataFrame) -> DataFrame:
    """A stream of predictions joined to the static table of gold queries; how is for the planner to say, from the table's size."""
    return log.join(items.select("item_id", F.col("sql").alias("gold_sql")), "item_id", "left")


def join_log(predictions: DataFrame, executions: DataFrame, within: str = "1 hour") -> DataFrame:
    """Predictions with the execution record of their item that arrives within a bound; both sides are watermarked."""
    p, e = predictions.withWatermark("ts", within).alias("p"), executions.withWatermark("ts", within).alias("e")
    return p.join(e, F.expr(f"p.item_id = e.item_id AND e.ts BETWEEN p.ts AND p.ts + INTERVAL {within}"))
