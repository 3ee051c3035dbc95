"""Functions callable from plain SQL: a table function of tokens, and temporary scalar functions."""

from __future__ import annotations

import regex
from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

PATTERN = r"[\p{L}\p{N}]+|[^\s\p{L}\p{N}]"


class ExplodeTokens:
    """A row for each word or punctuation mark of a text; none for null."""

    def eval(self, text: str):
        for m in regex.finditer(PATTERN, text or ""):
            yield (m.group(),)


class ExplodeIdentifiers:
    """A row (ord, name) for each name in a query that is neither a shaping word, a literal nor a function."""

    def eval(self, sql: str):
        from xlsql.localize.sql_tree import SHAPING, tokenize

        code = [t for t in tokenize(sql or "") if t.kind != "blank"]
        n = 0
        for i, t in enumerate(code):
            if t.name is not None and t.low not in SHAPING and not (i + 1 < len(code) and code[i + 1].text == "("):
                yield (n, t.name)
                n += 1


def register(spark: SparkSession) -> None:
    spark.udtf.register("explode_tokens", udtf(ExplodeTokens, returnType="token string"))
    spark.udtf.register("explode_identifiers", udtf(ExplodeIdentifiers, returnType="ord int, name string"))
    for sql in (
        "CREATE OR REPLACE TEMPORARY FUNCTION ascii_snake(s STRING) RETURNS STRING RETURN trim('_' FROM regexp_replace(lower(s), '[^a-z0-9]+', '_'))",
        "CREATE OR REPLACE TEMPORARY FUNCTION clt_n(z DOUBLE, e DOUBLE, p DOUBLE, n BIGINT) RETURNS BIGINT "
        "RETURN ceil(round(ceil(round(z * z * p * (1 - p) / (e * e), 9)) / (1 + (ceil(round(z * z * p * (1 - p) / (e * e), 9)) - 1) / n), 9))",
        "CREATE OR REPLACE TEMPORARY FUNCTION ves_reward(tg DOUBLE, tp DOUBLE) RETURNS DOUBLE RETURN sqrt(greatest(tg, 0.001D) / greatest(tp, 0.001D))",
    ):
        spark.sql(sql)
