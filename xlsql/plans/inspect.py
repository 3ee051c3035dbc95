"""What a physical plan does: exchanges, joins, Python, pushed filters."""

from __future__ import annotations

import contextlib
import io
import re
from collections import Counter

from pyspark.sql import DataFrame


def plan_text(df: DataFrame) -> str:
    out = io.StringIO()
    with contextlib.redirect_stdout(out):
        df.explain("formatted")
    return out.getvalue()


def operators(df: DataFrame) -> Counter:
    """Number of nodes of each kind in the physical plan."""
    tree = plan_text(df).split("\n\n\n")[0]
    return Counter(m.group(1) for m in re.finditer(r"[-+*: ]*(?:\* )?([A-Z]\w+)(?: \w+)? \(\d+\)", tree))


def pushed_filters(df: DataFrame) -> list[str]:
    return re.findall(r"PushedFilters: \[([^\]]*)\]", plan_text(df))


def read_columns(df: DataFrame) -> list[str]:
    return re.findall(r"ReadSchema: struct<([^>]*)>", plan_text(df))
