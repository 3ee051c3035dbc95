"""Generators of SQL: direct, staged, trained stand-ins of two families, and bounds. Model calls go through a provider."""

from __future__ import annotations

import hashlib
import re
from collections import Counter
from collections.abc import Sequence
from dataclasses import asdict, dataclass

from pyspark.errors import AnalysisException, PySparkException
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from xlsql.functions.text import subwords

# Cues of each class of query, in order of precedence.
INTENTS = (
    ("top_k", ("top", "highest", "lowest", "most", "least")),
    ("set_operation", ("but no", "but not")),
    ("anti", ("have no", "without")),
    ("group", ("each", "per", "every")),
    ("nested", ("above the average", "below the average")),
    ("filter_count", ("how many", "number of", "count")),
    ("lookup", ("show", "list", "find", "give")),
)
STOP = ("the", "of", "and", "with", "have", "has", "are", "there", "is", "in", "to", "a", "an", "each", "many", "how", "list", "show", "more", "than", "no", "number", "up", "were", "made", "from", "which", "what", "but", "one", "come")


# What the cues of questions become in the invented locale, and the form that the generators know.
LOCALE_CUES = {"source": (), "target": (("kac", "how many"), ("moreden", "more than"), ("moredan", "more than"), ("numberun", "number of"), ("upa", "up to"))}


def canonical_question(question: str, locale: str = "source", coverage: float = 1.0) -> str:
    """A question with its locale's cues in the form that the generators know; ``coverage`` is the share of the cue table that they were given."""
    known = LOCALE_CUES[locale]
    for cue, plain in known[: round(coverage * len(known))]:
        question = re.sub(rf"(?<!\w){cue}(?!\w)", plain, question)
    return question


@dataclass(frozen=True)
class ExperimentConfig:
    """What must be equal for a comparison to be controlled; its hash goes with every prediction."""

    model: str
    temperature: float = 0.0
    evidence: bool = True
    descriptions: bool = True
    coverage: float = 1.0
    seed: int = 42

    @property
    def hash(self) -> str:
        return hashlib.md5(repr(sorted(asdict(self).items())).encode()).hexdigest()[:12]


def assert_controlled(preds: DataFrame) -> DataFrame:
    """method, lang, configs: cells whose predictions come from more than one configuration (none when controlled)."""
    cells = preds.groupBy("method", "lang").agg(F.countDistinct("config_hash").alias("configs")).where("configs > 1")
    whole = preds.agg(F.countDistinct("config_hash").alias("configs")).where("configs > 1").select(F.lit("*").alias("method"), F.lit("*").alias("lang"), "configs")
    return cells.unionByName(whole)


def schema_text(meta: DataFrame, descriptions: bool = True) -> DataFrame:
    """db_id, schema_text: tables with their columns. A database's metadata is a bounded group."""
    note = F.when(F.lit(descriptions) & F.col("description").isNotNull(), F.concat(F.lit(" -- "), "description")).otherwise(F.lit(""))
    col = F.concat(F.lit("  "), "column_name", F.lit(" "), "data_type", note)
    t = meta.where("column_name is not null").groupBy("db_id", "table_name").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("ordinal", col.alias("c")))), lambda x: x["c"]), "\n").alias("cols"))
    one = F.concat(F.lit("table "), "table_name", F.lit("\n"), "cols")
    return t.groupBy("db_id").agg(F.array_join(F.array_sort(F.collect_list(one)), "\n").alias("schema_text"))


def render_prompt(items: DataFrame, schemas: DataFrame, evidence: bool = True) -> DataFrame:
    """Add ``prompt``: schema, question and, if wanted, evidence."""
    note = F.concat(F.lit("\n# Hint\n"), "evidence") if evidence else F.lit("")
    return items.join(F.broadcast(schemas), "db_id").withColumn("prompt", F.concat(F.lit("# Schema\n"), "schema_text", F.lit("\n# Question\n"), "question", note, F.lit("\n# SQL\n")))


def has_cue(text: Column, cue: str) -> Column:
    return F.concat(F.lit(" "), F.trim(F.regexp_replace(F.lower(text), r"[^a-z0-9\-]+", " ")), F.lit(" ")).contains(f" {cue} ")


def intent_of(question: Column) -> Column:
    """First class of ``INTENTS`` one of whose cues the question has; lookup otherwise."""
    out = None
    for name, cues in INTENTS:
        hit = F.greatest(*[has_cue(question, c) for c in cues]) if len(cues) > 1 else has_cue(question, cues[0])
        out = F.when(hit, name) if out is None else out.when(hit, name)
    return out.otherwise("lookup")


def link_schema(items: DataFrame, meta: DataFrame, top: int = 3, evidence: bool = True) -> DataFrame:
    """item_id, table_name, column_name, score, nth: columns whose sub-words or description share most tokens with the question.

    Tokens meet columns by an equi-join; a back-ticked name in the evidence counts five times.
    """
    tok = lambda c: F.array_distinct(F.filter(F.split(F.lower(F.regexp_replace(c, r"[^\p{L}\p{N}_]+", " ")), " "), lambda w: (w != "") & ~w.isin(*STOP)))
    q = items.select("item_id", "db_id", F.explode(tok(F.col("question"))).alias("w"), F.lit(1).alias("weight"))
    if evidence:
        q = q.unionByName(items.select("item_id", "db_id", F.explode(F.regexp_extract_all(F.lower("evidence"), F.lit("`([^`]+)`"), F.lit(1))).alias("w"), F.lit(5).alias("weight")))
    singular = lambda c: F.regexp_replace(c, "(?<=...)s$", "")
    words = F.array_distinct(F.concat(F.array(F.lower("column_name")), subwords(F.col("column_name")), subwords(F.col("table_name")), F.coalesce(tok(F.col("description")), F.array().cast("array<string>"))))
    m = meta.where("column_name is not null").select("db_id", "table_name", "column_name", "ordinal", F.explode(words).alias("w")).withColumn("w", singular("w")).distinct()
    s = q.withColumn("w", singular("w")).join(F.broadcast(m), ["db_id", "w"]).groupBy("item_id", "table_name", "column_name", "ordinal").agg(F.sum("weight").alias("score"))
    order = Window.partitionBy("item_id").orderBy(F.desc("score"), "table_name", "ordinal")
    return s.withColumn("nth", F.row_number().over(order)).where(F.col("nth") <= top).select("item_id", "table_name", "column_name", "score", "nth")


# ---------------------------------------------------------------------------------------------------------- offline generators


def _constants(text: str) -> list[str]:
    return re.findall(r"\d+(?:\.\d+)?", text)


def _template(intent: str, table: str, columns: Sequence[str], question: str, evidence: str) -> str:
    first, nums = columns[0] if columns else "*", _constants(question)
    conditions = [f"{c} = '{v}'" for c, v in re.findall(r"`(\w+)` = '([^']*)'", evidence)] + [f"{c} = {v}" for c, v in re.findall(r"`(\w+)` = (\d+)", evidence)]
    for cue, op in (("more than", ">"), ("above", ">"), ("less than", "<"), ("below", "<"), ("up to", "<=")):
        m = re.search(cue + r" (\d+(?:\.\d+)?)", question)
        if m and first != "*":
            conditions.append(f"{first} {op} {m.group(1)}")
            break
    where = f" WHERE {' AND '.join(conditions)}" if conditions else ""
    if intent == "filter_count":
        return f"SELECT count(*) FROM {table}{where}"
    if intent == "group":
        return f"SELECT {first}, count(*) AS n FROM {table}{where} GROUP BY {first}"
    if intent == "top_k":
        return f"SELECT {', '.join(dict.fromkeys([*columns[1:2], first]))} FROM {table}{where} ORDER BY {first} {'ASC' if 'lowest' in question else 'DESC'} LIMIT {nums[0] if nums else 1}"
    if intent == "nested":
        return f"SELECT count(*) FROM {table} WHERE {first} > (SELECT avg({first}) FROM {table})"
    return f"SELECT {', '.join(columns) or '*'} FROM {table}{where}"


def direct(question: str, evidence: str, schema: dict[str, list[str]], run: int = 0) -> str:
    """One pass: the table whose names overlap the question most, all its columns, filters from the evidence. ``run`` only breaks ties between tables."""
    words = set(re.findall(r"[a-z]+", question.lower()))
    stem = lambda w: w[:-1] if w.endswith("s") else w
    words = {stem(w) for w in words}
    lot = lambda t: hashlib.md5(f"{run} {question} {t}".encode()).hexdigest()
    table = max(sorted(schema), key=lambda t: (stem(t) in words, sum(stem(p) in words for c in schema[t] for p in c.split("_")), lot(t)))
    named = [c for c in re.findall(r"`(\w+)`", evidence) if c in schema[table]]
    intent = "filter_count" if question.lower().startswith("how many") else "lookup"
    return _template(intent, table, named, question, evidence)


def staged(question: str, evidence: str, schema: dict[str, list[str]], links: Sequence[tuple[str, str]], intent: str, stages: Sequence[str] = ("link", "intent"), run: int = 0) -> str:
    """Linked columns choose the table and the order of columns; the class of the query chooses its form."""
    if "link" not in stages or not links:
        return direct(question, evidence, schema, run)
    named = [c for c in re.findall(r"`(\w+)`", evidence)]
    tables = Counter(t for t, _ in links)
    own = [t for t, cols in schema.items() if any(c in cols for c in named)]
    table = next((t for t, _ in links if t in own), tables.most_common(1)[0][0])
    columns = [c for c in named if c in schema[table]] or [c for t, c in links if t == table][:2]
    return _template(intent if "intent" in stages else "lookup", table, columns, question, evidence)


def nearest(name: str, names: Sequence[str]) -> str:
    """The known name with the least edit distance, ties to the first."""

    def distance(a: str, b: str) -> int:
        row = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            before, row[0] = row[0], i
            for j, y in enumerate(b, 1):
                before, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, before + (x != y))
        return row[-1]

    return min(names, key=lambda n: (distance(name, n), n))


def nearest_value(session: SparkSession, table: str, column: str, value: str) -> str | None:
    """The column's value nearest to one that it does not have, among its most frequent 200; None if it has the value or is no text."""
    kind = dict(session.table(table).dtypes).get(column)
    if kind != "string" or not session.table(table).where(F.col(column) == value).isEmpty():
        return None
    known = [r[0] for r in session.table(table).where(F.col(column).isNotNull()).groupBy(column).count().orderBy(F.desc("count"), column).limit(200).collect()]
    return nearest(value, known) if known else None


def result_fault(session: SparkSession, sql: str, question: str = "") -> str | None:
    """What execution says of a valid query: ``empty`` if it gives no row, ``shape`` if a question of how many in all gets more than one row or a column."""
    rows = session.sql(sql).limit(2).collect()
    if not rows:
        return "empty"
    if question.lower().startswith("how many") and " each " not in question.lower() and (len(rows) > 1 or len(rows[0]) > 1):
        return "shape"
    return None


def self_correct(session: SparkSession, sql: str, schema: dict[str, list[str]], rounds: int = 2, question: str = "", execute: bool = False, trace: list | None = None) -> tuple[str, int, bool]:
    """Revise a query by feedback. (query, rounds used, valid).

    Analysis: unknown columns and tables become the nearest known names. With ``execute``, results: where none comes back, a text literal that its column
    does not have becomes the nearest value of the column; where a count is asked for and rows come back, they are counted. ``trace``
    collects (round, fault, query) of each revision.
    """
    note = lambda k, fault: trace.append((k, fault, sql)) if trace is not None else None
    for k in range(rounds + 1):
        try:
            session.sql(sql).schema  # noqa: B018
            fault = result_fault(session, sql, question) if execute and k < rounds else None
            if fault is None:
                return sql, k, True
            note(k, fault)
            if fault == "shape":
                sql = f"SELECT count(*) FROM ({sql})"
                continue
            tables = [t for t in schema if re.search(rf"\b{re.escape(t)}\b", sql)]
            found = [(c, v, near) for c, v in re.findall(r"(\w+) = '([^']*)'", sql) for t in tables if c in schema[t] and (near := nearest_value(session, t, c, v)) is not None]
            if not found:
                return sql, k, True
            c, v, near = found[0]
            sql = sql.replace(f"{c} = '{v}'", f"{c} = '{near}'")
        except AnalysisException as e:
            if k == rounds:
                return sql, k, False
            note(k, "analysis")
            said = str(e)
            m = re.search(r"(?:with name|view) `?([\w`.]+?)`? cannot", said)
            wrong = m.group(1).strip("`").split("`.`")[-1].split(".")[-1] if m else None
            if not wrong or wrong not in sql:
                return sql, k, False
            known = sorted(schema) if "TABLE_OR_VIEW" in said else sorted({c for cols in schema.values() for c in cols})
            sql = re.sub(rf"\b{re.escape(wrong)}\b", nearest(wrong, known), sql)
        except PySparkException:
            return sql, k, False
    return sql, rounds, False


# ---------------------------------------------------------------------------------------------------------------- trained


SIZES = {"S": 2**8, "M": 2**10, "L": 2**12, "0.5": 2**8, "1.5": 2**10, "3": 2**12}


def features(items: DataFrame, size: str, family: str) -> DataFrame:
    """Hashed features of questions: character trigrams (multilingual family); words besides (code family)."""
    from pyspark.ml.feature import HashingTF

    q = F.lower("question")
    grams = F.transform(F.sequence(F.lit(1), F.greatest(F.lit(1), F.length(q) - 2)), lambda i: F.substring(q, i, F.lit(3)))
    terms = grams if family == "multilingual" else F.concat(grams, F.split(q, " "), F.regexp_extract_all("evidence", F.lit("`([^`]+)`"), F.lit(1)))
    return HashingTF(numFeatures=SIZES[size], inputCol="terms", outputCol="features").transform(items.withColumn("terms", terms))


def fit_template_model(train: DataFrame, family: str, size: str, seed: int = 42):
    """Multinomial logistic regression from features to the query's class; iterations aggregate over a tree."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import StringIndexer

    index = StringIndexer(inputCol="intent", outputCol="label", handleInvalid="keep", stringOrderType="alphabetAsc").fit(train)
    model = LogisticRegression(maxIter={"S": 5, "M": 10, "L": 20, "0.5": 5, "1.5": 10, "3": 20}[size], regParam=0.01).fit(index.transform(features(train, size, family)))
    return index.labels, model


def predict_intents(items: DataFrame, fitted, family: str, size: str) -> DataFrame:
    """item_id, intent, predicted. Without a fitted model (an untuned one) every item gets the most general class."""
    if fitted is None:
        return items.select("item_id", "intent", F.lit("lookup").alias("predicted"))
    labels, model = fitted
    names = F.array(*[F.lit(x) for x in [*labels, "lookup"]])
    return model.transform(features(items, size, family)).select("item_id", "intent", F.get(names, F.col("prediction").cast("int")).alias("predicted"))


def oracle_generator(gold: dict[int, str]) -> dict[int, str]:
    """Upper bound: gold itself."""
    return dict(gold)


def constant_generator(gold: dict[int, str], sql: str = "SELECT 1") -> dict[int, str]:
    """Lower bound: one query for every item."""
    return dict.fromkeys(gold, sql)


SWAPPED = {"max": "min", "min": "max", "sum": "count", "avg": "max", "desc": "asc", "asc": "desc"}


def mutate_sql(sql: str, kind: str) -> str | None:
    """A query with one change: literal (a number grows by one), aggregate, direction, limit, distinct; None if there is nothing to change."""
    from xlsql.localize.sql_tree import tokenize

    tokens = tokenize(sql)
    code = [t for t in tokens if t.kind != "blank"]
    for i, t in enumerate(code):
        before = code[i - 1].low if i else ""
        if kind == "literal" and t.kind == "number" and before != "limit" or kind == "limit" and t.kind == "number" and before == "limit":
            t.new = str(int(float(t.text)) + 1)
        elif kind == "aggregate" and t.low in ("max", "min", "sum", "avg") and i + 1 < len(code) and code[i + 1].text == "(":
            t.new = SWAPPED[t.low]
        elif kind == "direction" and t.low in ("asc", "desc"):
            t.new = SWAPPED[t.low]
        elif kind == "distinct" and t.low == "distinct":
            t.new = ""
        else:
            continue
        return "".join(x.new if x.new is not None else x.text for x in tokens)
    return None
