"""Relational operators that evaluation needs beside the built-in ones: as-of and range joins, top rows of groups, salted joins."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, key: str, left_time: str, right_time: str, values: list[str]) -> DataFrame:
    """Each left row with ``values`` of the last right row of its key at or before its time (null if none).

    One union, one sort within keys and a running last value: no pair of rows is formed. Ties of time go to the right row that
    is last by its values; rows with a null key or time match nothing.
    """
    packed = F.struct(F.col(right_time).alias("_at"), *[F.col(v).alias(v) for v in values])
    lcols = left.columns
    a = left.select(F.col(key).alias("_k"), F.col(left_time).alias("_t"), F.lit(1).alias("_side"), F.struct(*lcols).alias("_row"), F.lit(None).alias("_v"))
    b = right.where(F.col(right_time).isNotNull()).select(F.col(key).alias("_k"), F.col(right_time).alias("_t"), F.lit(0).alias("_side"), F.lit(None).alias("_row"), packed.alias("_v"))
    both = a.select("_k", "_t", "_side", "_row", F.lit(None).cast(b.schema["_v"].dataType).alias("_v")).unionByName(b.select("_k", "_t", "_side", F.lit(None).cast(a.schema["_row"].dataType).alias("_row"), "_v"))
    w = Window.partitionBy("_k").orderBy("_t", "_side", "_v").rowsBetween(Window.unboundedPreceding, 0)
    filled = both.withColumn("_last", F.last("_v", ignorenulls=True).over(w)).where("_side = 1")
    found = F.when(F.col("_k").isNotNull() & F.col("_t").isNotNull(), F.col("_last"))
    return filled.select("_row.*", *[found[v].alias(v) for v in values])


def range_join(points: DataFrame, ranges: DataFrame, point: str, low: str, high: str, width: float) -> DataFrame:
    """Pairs with low <= point < high, through buckets of ``width``: an equi-join with a residual instead of a nested loop."""
    p = points.withColumn("_b", F.floor(F.col(point) / width))
    r = ranges.withColumn("_b", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))))
    return p.join(r, "_b").where((F.col(low) <= F.col(point)) & (F.col(point) < F.col(high))).drop("_b")


def top_per_group(df: DataFrame, by: list[str], order: list[Column], k: int) -> DataFrame:
    """First k rows of each group; ranks are cut in each task before the shuffle."""
    return df.withColumn("_nth", F.row_number().over(Window.partitionBy(*by).orderBy(*order))).where(F.col("_nth") <= k).drop("_nth")


def salted_join(big: DataFrame, small: DataFrame, on: list[str], salts: int = 16, how: str = "inner") -> DataFrame:
    """Equi-join whose hot keys are dealt over ``salts`` tasks; ``small`` is copied that often.

    ``how`` keeps or drops rows of ``big`` only (inner, left, left_semi, left_anti): copies of unmatched rows of ``small`` must not come out.
    """
    if how not in ("inner", "left", "left_semi", "left_anti"):
        raise ValueError(f"salted joins cannot be {how}: the small side is copied")
    b = big.withColumn("_salt", F.pmod(F.xxhash64(*[c for c in big.columns]), F.lit(salts)).cast("int"))
    s = small.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return b.join(s, [*on, "_salt"], how).drop("_salt")


def distinct_count_salted(df: DataFrame, by: list[str], value: str) -> DataFrame:
    """Distinct values of each group in two aggregations, so that a hot group's values are spread over tasks."""
    return df.groupBy(*by, value).agg(F.count("*").alias("_n")).groupBy(*by).agg(F.count(value).alias("n_distinct"))


def in_neighbourhood(df: DataFrame, key: str, order: str, column: str, back: int = 1, out: str = "previous") -> DataFrame:
    return df.withColumn(out, F.lag(column, back).over(Window.partitionBy(key).orderBy(order)))
