"""Grouped aggregates in pandas: reference forms of measures that the library computes with built-in expressions."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import functions as F


@F.pandas_udf("double")
def wilson_low(verdict: pd.Series) -> float:
    """Lower end of the 95 % Wilson interval of a 0/1 column."""
    n, z = len(verdict), 1.96
    p = verdict.mean()
    return float(((p + z * z / (2 * n)) - z * (p * (1 - p) / n + z * z / (4 * n * n)) ** 0.5) / (1 + z * z / n))


@F.pandas_udf("double")
def kappa(a: pd.Series, b: pd.Series) -> float:
    """Cohen's kappa of two 0/1 columns."""
    raw, x, y = (a == b).mean(), a.mean(), b.mean()
    chance = x * y + (1 - x) * (1 - y)
    return float((raw - chance) / (1 - chance))
