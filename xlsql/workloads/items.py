"""Items: questions, evidence and gold SQL from templates over the given tables, and seeded faults."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

ITEM = "item_id long, db_id string, split string, intent string, question string, evidence string, sql string"

# One item for each intent, in SQL that both engines run. Answers are compared by position.
CORE = (
    (1, "commerce", "lookup", "Show the name and balance of the customers with key up to 10", "key is `c_custkey`, balance is `c_acctbal`",
     "SELECT c_name, c_acctbal FROM customer WHERE c_custkey <= 10"),
    (2, "commerce", "filtered_count", "How many orders have status F and priority 1-URGENT ?", "status is `o_orderstatus` = 'F', urgent is `o_orderpriority` = '1-URGENT'",
     "SELECT count(*) FROM orders WHERE o_orderstatus = 'F' AND o_orderpriority = '1-URGENT'"),
    (3, "commerce", "group_aggregate", "List the number of customers and the highest balance of each segment", "segment is `c_mktsegment`, balance is `c_acctbal`",
     "SELECT c_mktsegment, count(*) AS n, max(c_acctbal) AS top FROM customer GROUP BY c_mktsegment"),
    (4, "commerce", "top_k", "List the top 10 orders with the highest total price", "total price is `o_totalprice`",
     "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10"),
    (5, "commerce", "multi_join", "How many orders come from each region ?", "region is `r_name`",
     "SELECT r_name, count(*) AS n FROM region JOIN nation ON n_regionkey = r_regionkey JOIN customer ON c_nationkey = n_nationkey JOIN orders ON o_custkey = c_custkey GROUP BY r_name"),
    (6, "commerce", "scalar_subquery", "How many customers have a balance above the average ?", "balance is `c_acctbal`",
     "SELECT count(*) FROM customer WHERE c_acctbal > (SELECT avg(c_acctbal) FROM customer)"),
    (7, "commerce", "exists", "How many customers have an order of more than 200000 ?", "price of an order is `o_totalprice`",
     "SELECT count(*) FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 200000)"),
    (8, "commerce", "anti", "How many customers have no orders ?", "an order's customer is `o_custkey`",
     "SELECT count(*) FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)"),
    (9, "commerce", "set_operation", "Which nations have customers but no suppliers ?", "nation is `c_nationkey` and `s_nationkey`",
     "SELECT c_nationkey FROM customer EXCEPT SELECT s_nationkey FROM supplier"),
    (10, "commerce", "window", "List the three customers with the highest balance of each segment", "segment is `c_mktsegment`, balance is `c_acctbal`",
     "SELECT c_mktsegment, c_custkey, rk FROM (SELECT c_mktsegment, c_custkey, row_number() OVER (PARTITION BY c_mktsegment ORDER BY c_acctbal DESC, c_custkey) AS rk FROM customer) t WHERE rk <= 3"),
    (11, "commerce", "dates", "How many orders were made in 1996 ?", "date is `o_orderdate`",
     "SELECT count(*) FROM orders WHERE year(o_orderdate) = 1996"),
    (12, "commerce", "cte", "List the customers with the lowest number of orders above 20", "customer is `o_custkey`",
     "WITH t AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey) SELECT o_custkey, n FROM t WHERE n > 20 ORDER BY n, o_custkey"),
    (13, "activity", "group_aggregate", "How many events of each type are there ?", "type is `event_type`", "SELECT event_type, count(*) AS n FROM events GROUP BY event_type"),
    (14, "activity", "filtered_count", "How many events have a value of more than 50 ?", "value is `value`", "SELECT count(*) FROM events WHERE value > 50"),
    (15, "activity", "top_k", "List the top 5 users with the most events", "user is `user_id`", "SELECT user_id, count(*) AS n FROM events GROUP BY user_id ORDER BY n DESC, user_id LIMIT 5"),
    (16, "corpus", "group_aggregate", "How many documents of each language are toxic ?", "toxic is `toxic` = 1, language is `lang`",
     "SELECT d.lang, count(*) AS n FROM documents d JOIN labels l ON d.doc_id = l.doc_id WHERE l.toxic = 1 GROUP BY d.lang"),
    (17, "corpus", "using", "How many documents from each source have the highest quality ?", "source is `source`, quality is `quality`",
     "SELECT source, count(*) AS n FROM documents JOIN labels USING (doc_id) WHERE quality = 1 GROUP BY source"),
    (18, "corpus", "literal", "How many turns of the role user are there ?", "role is `role` = 'user'", "SELECT count(*) FROM conversations WHERE role = 'user'"),
    (19, "vectors", "array", "Show the first component of the vectors with key below 5", "vector is `embedding`", "SELECT vec_id, embedding[0] AS x FROM embeddings WHERE vec_id < 5"),
    (20, "vectors", "group_aggregate", "How many vectors of each label are there ?", "label is `label`", "SELECT label, count(*) AS n FROM embeddings GROUP BY label"),
)

# Queries on which plain substitution goes wrong, since names also stand in literals, aliases or longer names.
ADVERSARIAL = (
    (101, "commerce", "SELECT count(*) AS name FROM customer WHERE c_name <> 'c_name'"),
    (102, "commerce", "SELECT c_acctbal AS orders FROM customer WHERE c_custkey = 1"),
    (103, "commerce", "WITH orders AS (SELECT n_name FROM nation) SELECT count(*) FROM orders"),
    (104, "corpus", "SELECT text AS pages FROM benchmark WHERE text <> 'the text' AND item_id < 3"),
    (105, "corpus", "SELECT source AS lang, count(*) AS n FROM documents GROUP BY source ORDER BY lang"),
    (106, "activity", "SELECT event_type AS value, count(*) AS events FROM events GROUP BY event_type"),
    (107, "commerce", "SELECT `c_name` FROM customer /* c_name */ WHERE c_name LIKE '%part%'"),
    (108, "corpus", "SELECT l.label_text FROM (SELECT quality AS label_text FROM labels) l"),
)

#: Mutations of gold queries: kind, item, changed query.
MUTANTS = (
    ("literal", 1, "SELECT c_name, c_acctbal FROM customer WHERE c_custkey <= 11"),
    ("column", 4, "SELECT o_custkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10"),
    ("aggregate", 3, "SELECT c_mktsegment, count(*) AS n, min(c_acctbal) AS top FROM customer GROUP BY c_mktsegment"),
    ("direction", 4, "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice, o_orderkey LIMIT 10"),
    ("limit", 4, "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 9"),
    ("distinct", 9, "SELECT c_nationkey FROM customer"),
    ("join", 8, "SELECT count(*) FROM customer"),
    ("same", 6, "SELECT count(*) FROM customer WHERE (SELECT avg(c_acctbal) FROM customer) < c_acctbal"),
    ("same", 5, "SELECT r_name, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name"),
    ("invalid", 2, "SELECT count(*) FROM orders WHERE no_such_column = 1"),
)


@dataclass(frozen=True)
class Item:
    item_id: int
    db_id: str
    intent: str
    question: str
    evidence: str
    sql: str


ITEMS = tuple(Item(*x) for x in CORE)
BY_ID = {i.item_id: i for i in ITEMS}


# Columns of the tables of ``commerce``, for what must be known without reading them.
COLUMNS = {
    "commerce": {
        "region": ("r_regionkey", "r_name"), "nation": ("n_nationkey", "n_name", "n_regionkey"), "customer": ("c_custkey", "c_name", "c_nationkey", "c_acctbal", "c_mktsegment"),
        "supplier": ("s_suppkey", "s_name", "s_nationkey", "s_acctbal"), "part": ("p_partkey", "p_name", "p_brand", "p_type", "p_size", "p_retailprice"),
        "orders": ("o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice", "o_orderdate", "o_orderpriority"),
        "lineitem": ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"),
    },
}


def width_of(sql: str) -> int:
    """Columns of a generated or gold query's result, from its select list; a star over ``commerce`` counts the table's columns."""
    body = sql[sql.rindex(") SELECT ") + 2 :] if sql.startswith("WITH ") else sql
    listed, depth, n = body[len("SELECT ") :], 0, 1
    for i, c in enumerate(listed):
        depth += (c == "(") - (c == ")")
        if depth == 0 and listed.startswith(" FROM ", i):
            shown = listed[:i]
            return len(COLUMNS["commerce"][listed[i + 6 :].split()[0]]) if shown == "*" else n
        n += c == "," and depth == 0
    return n


def split_of(item_id: int) -> str:
    return "dev" if item_id % 7 == 0 else "train"


def core_items(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(i.item_id, i.db_id, split_of(i.item_id), i.intent, i.question, i.evidence, i.sql) for i in ITEMS], ITEM)


# Forms of generated items; what stands in braces is drawn from the data or by rule.
TEMPLATES = (
    ("commerce", "lookup", "Show the name of the customer with key {KEY}", "key is `c_custkey`", "SELECT c_name FROM customer WHERE c_custkey = {KEY}"),
    ("commerce", "filtered_count", "How many orders have the status {STATUS} ?", "status is `o_orderstatus` = '{STATUS}'", "SELECT count(*) FROM orders WHERE o_orderstatus = '{STATUS}'"),
    ("commerce", "top_k", "List the top {K} orders with the highest total price", "total price is `o_totalprice`", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT {K}"),
    ("commerce", "group_aggregate", "How many customers with a key below {KEY} are there in each segment ?", "segment is `c_mktsegment`, key is `c_custkey`", "SELECT c_mktsegment, count(*) AS n FROM customer WHERE c_custkey < {KEY} GROUP BY c_mktsegment"),
    ("commerce", "multi_join", "How many customers with a key below {KEY} come from each nation ?", "nation is `n_name`, key is `c_custkey`",
     "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey WHERE c_custkey < {KEY} GROUP BY n_name"),
    ("activity", "filtered_count", "How many events have a value of more than {VALUE} ?", "value is `value`", "SELECT count(*) FROM events WHERE value > {VALUE}"),
    ("activity", "group_aggregate", "How many events of each type have a value of more than {VALUE} ?", "type is `event_type`, value is `value`", "SELECT event_type, count(*) AS n FROM events WHERE value > {VALUE} GROUP BY event_type"),
    ("activity", "top_k", "List the top {K} users with the most events", "user is `user_id`", "SELECT user_id, count(*) AS n FROM events GROUP BY user_id ORDER BY n DESC, user_id LIMIT {K}"),
    ("corpus", "filtered_count", "How many documents are in the language {LANG} ?", "language is `lang` = '{LANG}'", "SELECT count(*) FROM documents WHERE lang = '{LANG}'"),
    ("corpus", "group_aggregate", "How many documents in the language {LANG} are there of each source ?", "source is `source`, language is `lang` = '{LANG}'", "SELECT source, count(*) AS n FROM documents WHERE lang = '{LANG}' GROUP BY source"),
    ("corpus", "lookup", "Show the text of the benchmark item with key {K}", "text is `text`, key is `item_id`", "SELECT text FROM benchmark WHERE item_id = {K}"),
    ("vectors", "filtered_count", "How many vectors have the label {K} ?", "label is `label` = {K}", "SELECT count(*) FROM embeddings WHERE label = {K}"),
    ("vectors", "group_aggregate", "How many vectors with a key below {KEY} are there of each label ?", "label is `label`, key is `vec_id`", "SELECT label, count(*) AS n FROM embeddings WHERE vec_id < {KEY} GROUP BY label"),
)


def make_items(spark: SparkSession, sf_dir: str, n: int = 300, seed: int = 42) -> DataFrame:
    """``n`` items over all databases whose constants are drawn by plain arithmetic, keys within those of the data.

    Made by one projection over a range, so the number of items is free.
    """
    from xlsql.session import load_table

    customers = load_table(spark, sf_dir, "customer").select(F.max("c_custkey").alias("top"))
    ids = spark.range(n).withColumn("r", F.floor((F.col("id") * 1103515245 + seed * 12345) % 2147483648 / 1024)).crossJoin(F.broadcast(customers))
    draw = lambda xs: F.get(F.array(*[F.lit(x) for x in xs]), (F.col("r") % len(xs)).cast("int"))
    drawn = {"KEY": (F.col("r") % F.col("top") + 1).cast("string"), "K": (F.col("r") % 9 + 1).cast("string"), "STATUS": draw("FOP"), "VALUE": (F.col("r") % 90 + 5).cast("string"), "LANG": draw(("en", "de", "fr", "es"))}
    kind = (F.col("id") % len(TEMPLATES)).cast("int")

    def text(place: int):
        out = F.get(F.array(*[F.lit(t[place]) for t in TEMPLATES]), kind)
        for name, c in drawn.items():
            out = F.replace(out, F.lit("{" + name + "}"), c)
        return out

    return ids.select(
        (F.col("id") + 1000).alias("item_id"), text(0).alias("db_id"), F.when(F.col("id") % 7 == 0, "dev").otherwise("train").alias("split"),
        text(1).alias("intent"), text(2).alias("question"), text(3).alias("evidence"), text(4).alias("sql"),
    )


# Faults put into localized items, and the check that finds each.
FAULTS = (
    (1, "sql_name", "renglon_fantasma"), (2, "evidence_name", "clave_fantasma"), (3, "constant", "17"), (4, "comparative", "lowest"), (5, "backtick", "`"), (6, "exec", "different"), (6, "sql_name", "otra_fantasma"),
)


def seeded_flags(spark: SparkSession) -> DataFrame:
    """item_id, reason, detail of the seeded faults."""
    return spark.createDataFrame(list(FAULTS), "item_id long, reason string, detail string")
