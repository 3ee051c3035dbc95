"""Evidence and questions: names replaced in back-ticks, constants frozen, text localized together, and the checks on it."""

from __future__ import annotations

import re
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from xlsql.functions.text import backticks_balanced, constants_preserved, spans
from xlsql.providers.base import Provider, complete

# Cues of comparison, and fixed forms of instructions, as pairs of pattern and replacement.
CUES = {
    "highest": ("highest", "most", "maximum", "largest", "top"),
    "lowest": ("lowest", "least", "minimum", "smallest", "bottom"),
    "more": ("more than", "greater than", "above", "over"),
    "less": ("less than", "fewer than", "below", "under"),
}
STYLE = ((r"^List\b", "Please list"), (r"^Show\b", "Please list"), (r"^How many\b", "What number of"), (r"\s+\?$", "?"))
SEPARATOR = " ⟦∥⟧ "


def span_map(name_map: DataFrame, db_id: str | None = None) -> Column:
    """Literal map of the images of one database's names, keyed by kind and name; metadata, as many entries as identifiers."""
    rows = (name_map if db_id is None else name_map.where(F.col("db_id") == db_id)).select("kind", "source_name", "localized").distinct().collect()
    return F.create_map(*[F.lit(x) for r in rows for x in (f"{r['kind']} {r['source_name']}", r["localized"])])


def standardize_span(span: Column, names: Column) -> Column:
    """Image of a span: a name, or table.column part by part; case differences are tolerated; what has no image stays.

    The last part is a column if there is one of that name, else a table; parts before it are tables first.
    """
    at = lambda kind, p: F.coalesce(F.element_at(names, F.concat(F.lit(kind + " "), p)), F.element_at(names, F.concat(F.lit(kind + " "), F.lower(F.trim(p)))))
    parts = F.split(span, r"\.")
    image = lambda p, i: F.when(i == F.size(parts) - 1, F.coalesce(at("column", p), at("table", p), p)).otherwise(F.coalesce(at("table", p), at("column", p), p))
    return F.array_join(F.transform(parts, image), ".")


def standardize_evidence(text: Column, names: Column) -> Column:
    """Every closed back-ticked span replaced by its image, all else untouched."""
    pieces = F.split(text, "`", -1)
    closed = F.when(F.size(pieces) % 2 == 0, F.size(pieces) - 1).otherwise(F.size(pieces))
    return F.array_join(F.transform(pieces, lambda p, i: F.when((i % 2 == 1) & (i < closed), standardize_span(p, names)).otherwise(p)), "`")


def evidence_spans(items: DataFrame, names: DataFrame, text: str = "evidence", key: str = "item_id") -> DataFrame:
    """key, ord, span, localized, ok: every span of every item and its image, if it has one."""
    at = items.select(key, "db_id", F.posexplode(spans(F.col(text))).alias("ord", "span"))
    last = F.element_at(F.split("span", r"\."), -1)
    known = names.select("db_id", F.col("source_name"), "localized").distinct()
    return at.withColumn("source_name", last).join(F.broadcast(known), ["db_id", "source_name"], "left").select(key, "ord", "span", "localized", F.col("localized").isNotNull().alias("ok"))


def parse_flags(text: Column) -> Column:
    """``backtick`` where a text's back-ticks are unbalanced."""
    return F.when(~backticks_balanced(text), F.lit("backtick"))


def localize_text(items: DataFrame, provider: Provider, question: str = "question", evidence: str = "evidence", joint: bool = True) -> DataFrame:
    """Add question_loc, evidence_loc. With ``joint`` both go through one call, in one context, and are taken apart again.

    Prompts are distinct texts; a failed answer leaves nulls, which the checks flag.
    """
    pair = F.concat(F.col(question), F.lit(SEPARATOR), F.col(evidence))
    if joint:
        asked = items.withColumn("prompt", pair)
        made = complete(asked.select(F.lit("text").alias("task"), "prompt"), provider)
        out = asked.withColumn("key", F.md5(F.concat_ws("\x1f", F.lit("text"), "prompt", F.lit("")))).join(made, "key", "left")
        parts = F.split("text", r"\s*⟦∥⟧\s*")
        return out.withColumn("question_loc", F.get(parts, 0)).withColumn("evidence_loc", F.get(parts, 1)).drop("key", "text", "ok", "error", "prompt")
    out = items
    for c in (question, evidence):
        made = complete(out.select(F.lit("text").alias("task"), F.col(c).alias("prompt")), provider).select("key", F.col("text").alias(f"{c}_loc"))
        out = out.withColumn("key", F.md5(F.concat_ws("\x1f", F.lit("text"), F.col(c), F.lit("")))).join(made, "key", "left").drop("key")
    return out


def cue_table(spark: SparkSession, phrase=None) -> DataFrame:
    """cue, word: the cues of comparison, or what a locale's ``phrase`` makes of them."""
    return spark.createDataFrame([(k, (phrase(w) if phrase else w).lower()) for k, ws in CUES.items() for w in ws], "cue string, word string")


def comparative_cues(items: DataFrame, cues: DataFrame, text: str = "question", key: str = "item_id") -> DataFrame:
    """key, cue: the kinds of comparison that each text makes."""
    held = items.select(key, F.concat(F.lit(" "), F.lower(F.regexp_replace(text, r"[^\p{L}\p{N}]+", " ")), F.lit(" ")).alias("t"))
    return held.join(F.broadcast(cues), F.col("t").contains(F.concat(F.lit(" "), F.col("word"), F.lit(" ")))).select(key, "cue").distinct()


def comparatives_preserved(before: DataFrame, after: DataFrame, cues_before: DataFrame, cues_after: DataFrame, key: str = "item_id", text: str = "question") -> DataFrame:
    """key, preserved: whether both texts make the same comparisons."""
    own = lambda d, c, n: comparative_cues(d, c, text, key).groupBy(key).agg(F.array_join(F.array_sort(F.collect_set("cue")), ",").alias(n))
    both = before.select(key).join(own(before, cues_before, "x"), key, "left").join(own(after, cues_after, "y"), key, "left")
    return both.select(key, F.col("x").eqNullSafe(F.col("y")).alias("preserved"))


def check_comparatives(items: DataFrame, cues_before: DataFrame, cues_after: DataFrame, before: str = "question", after: str = "question_loc", key: str = "item_id") -> DataFrame:
    """Flags of items whose two texts do not make the same comparisons."""
    a, b = items.select(key, F.col(before).alias("question")), items.select(key, F.col(after).alias("question"))
    return comparatives_preserved(a, b, cues_before, cues_after, key).where("not preserved").select(key, F.lit("comparative").alias("reason"), F.lit("").alias("detail"))


def apply_style_rules(text: Column, rules=STYLE) -> Column:
    return reduce(lambda c, r: F.regexp_replace(c, *r), rules, text)


def check_constants(items: DataFrame, before: str = "question", after: str = "question_loc", key: str = "item_id") -> DataFrame:
    """Items whose numbers, quoted values or back-ticked spans are not the same before and after."""
    return items.where(~F.coalesce(constants_preserved(F.col(before), F.col(after)), F.lit(False))).select(key, F.lit("constant").alias("reason"))


def translate_prompt(template: str, translate) -> str:
    """A prompt template in another language: headings, placeholders ({name}) and fenced examples stay, prose lines are translated."""
    out, fenced = [], False
    for line in template.split("\n"):
        fenced ^= line.startswith("```")
        keep = fenced or line.startswith(("#", "```")) or not line.strip()
        pieces = [line] if keep else re.split(r"(\{\w+\})", line)
        out.append(line if keep else "".join(p if p.startswith("{") or not p.strip() else translate(p) for p in pieces))
    done = "\n".join(out)
    if sorted(re.findall(r"\{\w+\}", done)) != sorted(re.findall(r"\{\w+\}", template)):
        raise ValueError("placeholders changed")
    return done
