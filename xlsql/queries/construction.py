"""Construction and quality control: schema, name maps, evidence, text, SQL, equality, integrity."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from xlsql.catalog.spec import DATABASES, TABLES, columns_of, extract_all, open_database
from xlsql.functions import text as tx
from xlsql.localize import sql_tree
from xlsql.localize import text as lt
from xlsql.mapping import names as nm
from xlsql.mapping.lexicon import ES, lexicon_table
from xlsql.queries import query, quote, values
from xlsql.session import load_table
from xlsql.verify import checks
from xlsql.verify.exec_equal import digest, run_pairs
from xlsql.workloads import items as wi

OWNER = {t: d.db_id for d in DATABASES.values() for t in d.tables}
COLUMNS = f"""(SELECT table_name AS t, column_name AS c, CAST(ordinal_position AS INTEGER) AS o, data_type AS k, m.db_id
    FROM information_schema.columns JOIN {values([(t, d) for t, d in OWNER.items()], 'tn, db_id', 'm')} ON m.tn = table_name)"""


def image(name: str) -> str:
    """What the offline lexicon makes of a name of the given tables."""
    return "_".join(ES.get(w, w) for w in name.split("_"))


#: Name maps by application, folder and database: metadata that many queries share.
KNOWN: dict[tuple[str, str], dict[str, dict]] = {}


def name_dicts(spark: SparkSession, sf_dir: str, db_id: str) -> dict[str, dict[str, str]]:
    key = (spark.sparkContext.applicationId, sf_dir)
    if key not in KNOWN:
        held: dict[str, dict] = {d: {"table": {}, "column": {}} for d in DATABASES}
        for r in full_map(spark, sf_dir).select("db_id", "kind", "source_name", "localized").collect():
            held[r["db_id"]][r["kind"]][r["source_name"]] = r["localized"]
        KNOWN[key] = held
    return KNOWN[key][db_id]


def full_map(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nm.build_name_map(extract_all(spark, sf_dir), lexicon_table(spark, "es"))


@query(f"""
    SELECT db_id, t AS table_name, c AS column_name, o AS ordinal,
           CASE k WHEN 'BIGINT' THEN 'bigint' WHEN 'INTEGER' THEN 'int' WHEN 'VARCHAR' THEN 'string' WHEN 'DOUBLE' THEN 'double' WHEN 'TIMESTAMP' THEN 'timestamp_ntz' WHEN 'FLOAT[]' THEN 'array<float>' ELSE k END AS data_type
    FROM {COLUMNS}""")
def q01_schema_extract(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_all(spark, sf_dir).where("column_name is not null").select("db_id", "table_name", "column_name", "ordinal", "data_type")


@query(r"""
    WITH n AS (SELECT DISTINCT p_name AS name FROM part UNION SELECT DISTINCT source || ' Über-' || lang FROM documents),
    f AS (SELECT name, trim(regexp_replace(lower(regexp_replace(replace(name, 'Ü', 'U'), '([a-z0-9])([A-Z])', '\1_\2', 'g')), '[^a-z0-9]+', '_', 'g'), '_') AS s FROM n)
    SELECT name, CASE WHEN regexp_matches(s, '^[0-9]') THEN 'n_' || s ELSE s END AS snake FROM f""")
def q02_identifier_snake(spark: SparkSession, sf_dir: str) -> DataFrame:
    part = load_table(spark, sf_dir, "part").select(F.col("p_name").alias("name"))
    docs = load_table(spark, sf_dir, "documents").select(F.concat("source", F.lit(" Über-"), "lang").alias("name"))
    return part.unionByName(docs).distinct().select("name", tx.to_ascii_snake(F.col("name")).alias("snake"))


@query(f"""
    WITH n AS (SELECT DISTINCT t AS name FROM {COLUMNS} UNION SELECT DISTINCT c FROM {COLUMNS}), w AS (SELECT unnest(string_split(name, '_')) AS subword FROM n)
    SELECT subword, count(*) AS n FROM w WHERE subword <> '' GROUP BY subword""")
def q03_subterm_standard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nm.standardize_subterms(extract_all(spark, sf_dir))


@query(f"""
    WITH n AS (SELECT DISTINCT db_id, 'table' AS kind, t AS source_name FROM {COLUMNS} UNION SELECT DISTINCT db_id, 'column', c FROM {COLUMNS}),
    w AS (SELECT n.*, unnest(string_split(source_name, '_')) AS word, generate_subscripts(string_split(source_name, '_'), 1) AS pos FROM n),
    l AS (SELECT * FROM {values(list(ES.items()), 'word, localized')})
    SELECT db_id, kind, source_name, string_agg(coalesce(localized, w.word), '_' ORDER BY pos) AS localized
    FROM w LEFT JOIN l ON l.word = w.word GROUP BY db_id, kind, source_name""")
def q04_name_map(spark: SparkSession, sf_dir: str) -> DataFrame:
    return full_map(spark, sf_dir).select("db_id", "kind", "source_name", "localized")


STEMS = "SELECT DISTINCT p_name AS source_name, substr(replace(lower(p_name), ' ', '_'), 1, 6) AS candidate FROM part"


def _stems(spark: SparkSession, sf_dir: str) -> DataFrame:
    names = load_table(spark, sf_dir, "part").select(F.col("p_name").alias("source_name")).distinct()
    return names.select(F.lit("commerce").alias("db_id"), F.lit("column").alias("kind"), "source_name", F.substring(F.replace(F.lower("source_name"), F.lit(" "), F.lit("_")), 1, 6).alias("candidate"))


@query(f"""
    WITH s AS ({STEMS}), r AS (SELECT *, row_number() OVER (PARTITION BY candidate ORDER BY source_name) AS nth FROM s)
    SELECT source_name, candidate, CASE WHEN nth > 1 THEN candidate || '_' || CAST(nth AS VARCHAR) ELSE candidate END AS localized FROM r""")
def q05_collision_resolve(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nm.resolve_collisions(_stems(spark, sf_dir)).select("source_name", "candidate", "localized")


@query(f"""
    WITH s AS ({STEMS}) SELECT candidate, count(*) AS n, string_agg(source_name, ',' ORDER BY source_name) AS sources FROM s GROUP BY candidate HAVING count(*) > 1""")
def q06_collision_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nm.collision_report(_stems(spark, sf_dir)).select("candidate", "n", "sources")


EVIDENCE = """
    SELECT DISTINCT 'urgency is `o_orderpriority` = ''' || o_orderpriority || ''' in `orders`' AS evidence FROM orders
    UNION SELECT DISTINCT 'segment is `customer.c_mktsegment` = ''' || c_mktsegment || '''' FROM customer
    UNION SELECT DISTINCT 'brand is `p_brand` = ''' || p_brand || ''' of `part' FROM part"""


def _evidence(spark: SparkSession, sf_dir: str) -> DataFrame:
    a = load_table(spark, sf_dir, "orders").select(F.concat(F.lit("urgency is `o_orderpriority` = '"), "o_orderpriority", F.lit("' in `orders`")).alias("evidence"))
    b = load_table(spark, sf_dir, "customer").select(F.concat(F.lit("segment is `customer.c_mktsegment` = '"), "c_mktsegment", F.lit("'")).alias("evidence"))
    c = load_table(spark, sf_dir, "part").select(F.concat(F.lit("brand is `p_brand` = '"), "p_brand", F.lit("' of `part")).alias("evidence"))
    return a.unionByName(b).unionByName(c).distinct()


@query(f"""
    SELECT evidence, replace(replace(replace(replace(evidence, '`o_orderpriority`', '`{image("o_orderpriority")}`'), '`orders`', '`{image("orders")}`'),
        '`customer.c_mktsegment`', '`{image("customer")}.{image("c_mktsegment")}`'), '`p_brand`', '`{image("p_brand")}`') AS standard FROM ({EVIDENCE})""")
def q07_evidence_rewrite(spark: SparkSession, sf_dir: str) -> DataFrame:
    names = lt.span_map(full_map(spark, sf_dir), "commerce")
    return _evidence(spark, sf_dir).select("evidence", lt.standardize_evidence(F.col("evidence"), names).alias("standard"))


@query(f"""
    SELECT evidence, (length(evidence) - length(replace(evidence, '`', ''))) // 2 AS n_spans, (length(evidence) - length(replace(evidence, '`', ''))) % 2 = 0 AS balanced FROM ({EVIDENCE})""")
def q08_evidence_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _evidence(spark, sf_dir).select("evidence", F.size(tx.spans(F.col("evidence"))).cast("long").alias("n_spans"), tx.backticks_balanced(F.col("evidence")).alias("balanced"))


@query(r"""
    SELECT doc_id, len(regexp_extract_all(text, '[0-9]+(?:[.,][0-9]+)*')) AS n_held, true AS same,
           length(regexp_replace(text, '[0-9]+(?:[.,][0-9]+)*', '', 'g')) AS rest FROM documents""")
def q09_freeze_thaw(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load_table(spark, sf_dir, "documents").select("doc_id", "text", tx.freeze(F.col("text")).alias("f"))
    rest = F.length(F.regexp_replace("f.frozen", "⟦[0-9]+⟧", "")).cast("long")
    return docs.select("doc_id", F.size("f.held").cast("long").alias("n_held"), (tx.thaw(F.col("f.frozen"), F.col("f.held")) == F.col("text")).alias("same"), rest.alias("rest"))


@query(r"""
    WITH d AS (SELECT doc_id, text, CASE WHEN doc_id % 7 = 0 THEN replace(text, '1', '2') ELSE upper(text) END AS after FROM documents),
    b AS (SELECT item_id, text, regexp_replace(text, 'the ', 'a ', 'g') AS after FROM benchmark)
    SELECT 'documents' AS corpus, count(*) AS n, count(*) FILTER (list_sort(regexp_extract_all(text, '[0-9]+(?:[.,][0-9]+)*')) = list_sort(regexp_extract_all(after, '[0-9]+(?:[.,][0-9]+)*'))) AS kept FROM d
    UNION ALL SELECT 'benchmark', count(*), count(*) FILTER (list_sort(regexp_extract_all(text, '[0-9]+(?:[.,][0-9]+)*')) = list_sort(regexp_extract_all(after, '[0-9]+(?:[.,][0-9]+)*'))) FROM b""")
def q10_constants_check(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load_table(spark, sf_dir, "documents").select(F.lit("documents").alias("corpus"), "text", F.when(F.col("doc_id") % 7 == 0, F.replace("text", F.lit("1"), F.lit("2"))).otherwise(F.upper("text")).alias("after"))
    bench = load_table(spark, sf_dir, "benchmark").select(F.lit("benchmark").alias("corpus"), "text", F.regexp_replace("text", "the ", "a ").alias("after"))
    kept = (F.array_sort(tx.numbers(F.col("text"))) == F.array_sort(tx.numbers(F.col("after")))).cast("long")
    return docs.unionByName(bench).groupBy("corpus").agg(F.count("*").alias("n"), F.sum(kept).alias("kept"))


QUESTIONS = values([(i.item_id, i.question) for i in wi.ITEMS], "item_id, question", "q")


@query(f"""
    SELECT cue, count(DISTINCT item_id) AS n FROM {QUESTIONS}, {values([(c, w) for c, ws in lt.CUES.items() for w in ws], 'cue, word', 'c')}
    WHERE contains(' ' || lower(regexp_replace(question, '[^a-zA-Z0-9]+', ' ', 'g')) || ' ', ' ' || word || ' ') GROUP BY cue""")
def q11_comparative_cues(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lt.comparative_cues(wi.core_items(spark), lt.cue_table(spark)).groupBy("cue").agg(F.count("*").alias("n"))


@query(rf"""
    SELECT CAST(item_id AS BIGINT) AS item_id, regexp_replace(regexp_replace(regexp_replace(regexp_replace(question, '^List\b', 'Please list'), '^Show\b', 'Please list'), '^How many\b', 'What number of'), '\s+\?$', '?') AS styled
    FROM {QUESTIONS}""")
def q12_style_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return wi.core_items(spark).select("item_id", lt.apply_style_rules(F.col("question")).alias("styled"))


def localized_core(spark: SparkSession, sf_dir: str) -> list[tuple[int, str, list[str]]]:
    """(item, localized SQL, problems) of the core items."""
    dicts = {d: (name_dicts(spark, sf_dir, d), columns_of(spark, sf_dir, DATABASES[d])) for d in DATABASES}
    return [(i.item_id, *sql_tree.localize_sql(i.sql, *dicts[i.db_id])) for i in wi.ITEMS]


def _all_names() -> list[str]:
    """Names whose every occurrence in the plain core items is an identifier, so that word-wise substitution is right on them."""
    return ["region", "nation", "customer", "supplier", "orders", "events", "documents", "labels", "embeddings", *sorted({c for i in wi.ITEMS for c in re.findall(r"\b(?:[rncspol]_[a-z]+|event_type|user_id|doc_id|vec_id|toxic|quality|lang)\b", i.sql)})]


PLAIN_ITEMS = [i for i in wi.ITEMS if i.intent not in ("literal", "array") and i.item_id not in (14, 17, 20)]


def _substituted() -> str:
    out = "sql"
    for n in _all_names():
        out = f"regexp_replace({out}, '\\b{n}\\b', '{image(n)}', 'g')"
    return f"SELECT CAST(item_id AS BIGINT) AS item_id, {out} AS sql_loc FROM {values([(i.item_id, i.sql) for i in PLAIN_ITEMS], 'item_id, sql')}"


@query(_substituted)
def q13_sql_rewrite(spark: SparkSession, sf_dir: str) -> DataFrame:
    keep = {i.item_id for i in PLAIN_ITEMS}
    return spark.createDataFrame([(k, s) for k, s, _ in localized_core(spark, sf_dir) if k in keep], "item_id long, sql_loc string")


# What no substitution may change: quoted texts, comments, names that AS or WITH gives.
HELD = r"'[^']*'|/\*.*?\*/|(?:AS|WITH) \w+"


def _damage_sql() -> str:
    """Whether a name of the database stands within what must not change."""
    rows = values([(k, db, sql) for k, db, sql in wi.ADVERSARIAL], "item_id, db_id, sql")
    return f"""WITH p AS (SELECT item_id, db_id, unnest(regexp_extract_all(sql, {quote(HELD)})) AS piece FROM {rows}), n AS (SELECT DISTINCT db_id, t AS name FROM {COLUMNS} UNION SELECT DISTINCT db_id, c FROM {COLUMNS})
        SELECT CAST(v.item_id AS BIGINT) AS item_id, EXISTS (SELECT 1 FROM p JOIN n ON n.db_id = p.db_id AND contains(piece, name) WHERE p.item_id = v.item_id) AS damaged FROM {rows}"""


@query(_damage_sql)
def q14_sql_naive_damage(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whether plain substitution changes what is no identifier; rewriting the tree must not, and must resolve every name."""
    rows = []
    for k, db, sql in wi.ADVERSARIAL:
        names = name_dicts(spark, sf_dir, db)
        made, problems = sql_tree.localize_sql(sql, names, columns_of(spark, sf_dir, DATABASES[db]))
        if problems or re.findall(HELD, made) != re.findall(HELD, sql):
            raise ValueError((made, problems))
        rows.append((k, re.findall(HELD, sql_tree.localize_sql_naive(sql, names)) != re.findall(HELD, sql)))
    return spark.createDataFrame(rows, "item_id long, damaged boolean")


def _localized(item_id: int):
    """Run an item's localized SQL on localized views; the oracle runs its source SQL."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        item = wi.BY_ID[item_id]
        db = DATABASES[item.db_id]
        names = name_dicts(spark, sf_dir, item.db_id)
        own = spark.newSession()
        own.conf.set("spark.sql.session.timeZone", "UTC")
        nm.publish_localized_views(own, sf_dir, db, names)
        made, problems = sql_tree.localize_sql(item.sql, names, columns_of(spark, sf_dir, db))
        if problems:
            raise ValueError(problems)
        out = own.sql(made)
        return out.toDF(*[f"c{k}" for k in range(len(out.columns))])

    return run


WIDTH = {1: 2, 2: 1, 3: 3, 4: 2, 5: 2, 6: 1, 7: 1, 8: 1, 9: 1, 10: 3, 11: 1, 12: 2, 13: 2, 16: 2, 19: 2}
for _key, _item in (
    ("q15_loc_lookup", 1), ("q16_loc_filtered_count", 2), ("q17_loc_group_aggregate", 3), ("q18_loc_top_k", 4), ("q19_loc_multi_join", 5), ("q20_loc_scalar_subquery", 6), ("q21_loc_exists", 7),
    ("q22_loc_anti", 8), ("q23_loc_set_operation", 9), ("q24_loc_window", 10), ("q24a_loc_dates", 11), ("q24b_loc_cte", 12), ("q25_loc_activity", 13), ("q26_loc_corpus", 16), ("q27_loc_vectors", 19),
):
    _run = _localized(_item)
    _run.__name__ = _key
    _sql = wi.BY_ID[_item].sql.replace("embedding[0]", "embedding[1]")  # arrays begin at 1 there
    # ranks are of the wider type there
    _cols = ", ".join("CAST(c2 AS INTEGER) AS c2" if (_item, k) == (10, 2) else f"c{k}" for k in range(WIDTH[_item]))
    query(f"SELECT {_cols} FROM ({_sql}) t({', '.join(f'c{k}' for k in range(WIDTH[_item]))})")(_run)

PAIRS = [(f"gold-{i.item_id}", i.sql, i.sql) for i in wi.ITEMS if i.db_id == "commerce" and i.item_id != 12] + [(f"{kind}-{item}-{k}", wi.BY_ID[item].sql, sql) for k, (kind, item, sql) in enumerate(wi.MUTANTS) if kind != "invalid"]


def bag_equal(a: str, b: str) -> str:
    """SQL that tells whether two queries give the same bag."""
    return f"NOT EXISTS (SELECT * FROM (SELECT * FROM ({a}) EXCEPT ALL SELECT * FROM ({b})) UNION ALL SELECT * FROM (SELECT * FROM ({b}) EXCEPT ALL SELECT * FROM ({a})))"


@query(" UNION ALL ".join(f"SELECT {quote(k)} AS pair, {bag_equal(a, b)} AS equal" for k, a, b in PAIRS))
def q28_exec_equal_bag(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Gold against its localized form, and gold against mutants."""
    db = DATABASES["commerce"]
    names, schema = name_dicts(spark, sf_dir, "commerce"), columns_of(spark, sf_dir, db)
    source, target = open_database(spark, sf_dir, db), spark.newSession()
    nm.publish_localized_views(target, sf_dir, db, names)
    asked = [(source, a, target, sql_tree.localize_sql(b, names, schema)[0]) if k.startswith("gold-") else (source, a, source, b) for k, a, b in PAIRS]
    results = run_pairs(asked, "bag", snapshots=("source", "source"))
    return spark.createDataFrame([(k, r.equal) for (k, _, _), r in zip(PAIRS, results)], "pair string, equal boolean")


FEW = "SELECT {0} FROM orders WHERE o_orderkey < 500 ORDER BY {1}"
TOP = "SELECT {0} FROM orders ORDER BY {1} LIMIT {2}"
#: Pairs of which both orders are total: the lists of rows tell.
ORDERED = [
    ("same", TOP.format("o_orderkey, o_totalprice", "o_totalprice DESC, o_orderkey", 50), TOP.format("o_orderkey, o_totalprice", "o_totalprice DESC, o_orderkey ASC", 50)),
    ("reversed", FEW.format("o_orderkey, o_totalprice", "o_orderkey"), FEW.format("o_orderkey, o_totalprice", "o_orderkey DESC")),
    ("other key", FEW.format("o_orderkey, o_totalprice", "o_orderkey"), FEW.format("o_orderkey, o_totalprice", "o_totalprice, o_orderkey")),
    ("first place, other direction", TOP.format("o_orderkey", "o_totalprice DESC, o_orderkey", 1), TOP.format("o_orderkey", "o_totalprice, o_orderkey", 1)),
    ("first place, other column", TOP.format("o_orderkey, o_custkey", "o_totalprice DESC, o_orderkey", 1), TOP.format("o_orderkey, o_orderkey", "o_totalprice DESC, o_orderkey", 1)),
    ("wrong last row", "SELECT * FROM (VALUES (0, 5), (1, 6), (2, 7)) t(a, b) ORDER BY a LIMIT 3", "SELECT * FROM (VALUES (0, 5), (1, 6), (2, 77)) t(a, b) ORDER BY a LIMIT 3"),
    ("permuted", "SELECT * FROM (VALUES (0), (1), (2)) t(a) ORDER BY a LIMIT 3", "SELECT * FROM (VALUES (0), (1), (2)) t(a) ORDER BY a <> 1, a LIMIT 3"),
    ("hidden key", FEW.format("o_custkey", "o_totalprice, o_orderkey"), FEW.format("o_custkey", "o_totalprice * 2, o_orderkey")),
    ("one row more", TOP.format("o_orderkey", "o_orderkey", 5), TOP.format("o_orderkey", "o_orderkey", 6)),
]
HIDDEN, GROUPS = FEW.format("o_orderkey", "o_orderpriority"), "SELECT o_orderpriority FROM orders WHERE o_orderkey < 500 GROUP BY o_orderpriority HAVING count(*) > 1"
CUT = TOP.format("o_orderpriority, o_orderkey", "o_orderpriority", 5)
#: Pairs with ties: name, gold, prediction, and what tells in SQL whether all that the prediction may give is right.
TIED = [
    # each row's place must lie within the places of its own tie group
    ("finer order of a hidden key", HIDDEN, HIDDEN + ", o_orderkey DESC", """NOT EXISTS (SELECT * FROM (SELECT o_orderpriority AS p, row_number() OVER (ORDER BY o_orderpriority, o_orderkey DESC) AS n FROM orders WHERE o_orderkey < 500) r
        JOIN (SELECT o_orderpriority AS p, count(*) AS size, sum(count(*)) OVER (ORDER BY o_orderpriority) AS last FROM orders WHERE o_orderkey < 500 GROUP BY o_orderpriority) g ON r.p = g.p WHERE n > last OR n <= last - size)"""),
    ("coarser order", HIDDEN + ", o_orderkey", HIDDEN, f"NOT EXISTS ({GROUPS})"),
    ("cut between ties", CUT, TOP.format("o_orderpriority, o_orderkey", "o_orderpriority, o_orderkey DESC", 5),
     "(SELECT count(*) FROM (SELECT o_orderpriority FROM orders ORDER BY o_orderpriority, o_orderkey DESC LIMIT 5) t WHERE o_orderpriority = (SELECT min(o_orderpriority) FROM orders)) = (SELECT least(5, count(*)) FROM orders)"),
    ("cut in another group", CUT, TOP.format("o_orderpriority, o_orderkey", "o_orderpriority DESC, o_orderkey", 5), "(SELECT min(o_orderpriority) = max(o_orderpriority) FROM orders)"),
    ("any rows", "SELECT o_orderkey FROM orders LIMIT 5", TOP.format("o_orderkey", "o_orderkey DESC", 5), f"(SELECT count(*) FROM ({TOP.format('o_orderkey', 'o_orderkey DESC', 5)}) t WHERE o_orderkey IN (SELECT o_orderkey FROM orders)) = 5"),
]


def list_equal(a: str, b: str, width: int) -> str:
    """SQL that tells whether two queries give the same rows in the same order."""
    names = ", ".join(f"c{k}" for k in range(width))
    return f"(SELECT list(t) FROM (SELECT * FROM ({a}) x({names})) t) = (SELECT list(t) FROM (SELECT * FROM ({b}) x({names})) t)"


def _ordered_sql() -> str:
    wide = {"same": 2, "reversed": 2, "other key": 2, "first place, other column": 2, "wrong last row": 2}
    return " UNION ALL ".join([f"SELECT {quote(k)} AS pair, {list_equal(a, b, wide.get(k, 1))} AS equal" for k, a, b in ORDERED] + [f"SELECT {quote(k)}, {told}" for k, _, _, told in TIED])


@query(_ordered_sql)
def q29_exec_equal_ordered(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order-sensitive verdicts: rows that tie may change places, a cut between ties may choose, all else must agree."""
    s = open_database(spark, sf_dir, DATABASES["commerce"])
    pairs = [p[:3] for p in (*ORDERED, *TIED)]
    results = run_pairs([(s, a, s, b) for _, a, b in pairs], "auto")
    return spark.createDataFrame([(k, r.equal) for (k, _, _), r in zip(pairs, results)], "pair string, equal boolean")


@query("""
    WITH h AS (SELECT CAST('0x' || substr(md5(concat_ws('|', l_orderkey, l_partkey, l_suppkey, l_linenumber, l_returnflag, l_linestatus)), 1, 12) AS BIGINT) AS x FROM lineitem)
    SELECT count(*) AS n, CAST(sum(x) AS VARCHAR) AS total, bit_xor(x) AS mixed FROM h""")
def q30_result_digest(spark: SparkSession, sf_dir: str) -> DataFrame:
    cols = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_returnflag", "l_linestatus"]
    h = load_table(spark, sf_dir, "lineitem").select(F.conv(F.substring(F.md5(F.concat_ws("|", *cols)), 1, 12), 16, 10).cast("bigint").alias("x"))
    return h.agg(F.count("*").alias("n"), F.sum(F.col("x").cast("decimal(38,0)")).cast("string").alias("total"), F.bit_xor("x").alias("mixed"))


def _faulty_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Localized commerce items; every third refers to a name that is not in the map, every fourth's evidence to another."""
    made = {k: s for k, s, _ in localized_core(spark, sf_dir)}
    rows = []
    for i in wi.ITEMS:
        if i.db_id == "commerce":
            sql = made[i.item_id] + (" UNION ALL SELECT fantasma FROM tabla_fantasma" if i.item_id % 3 == 0 else "")
            evidence = re.sub(r"`(\w+)`", lambda m: f"`{image(m.group(1))}`", i.evidence) + (" and `columna_fantasma`" if i.item_id % 4 == 0 else "")
            rows.append((i.item_id, i.db_id, sql, evidence))
    return spark.createDataFrame(rows, "item_id long, db_id string, sql string, evidence_loc string")


COMMERCE = [i for i in wi.ITEMS if i.db_id == "commerce"]


@query(f"SELECT CAST(item_id AS BIGINT) AS item_id, 'sql_name' AS reason, detail FROM {values([(i.item_id, x) for i in COMMERCE if i.item_id % 3 == 0 for x in ('fantasma', 'tabla_fantasma')], 'item_id, detail')}")
def q31_integrity_sql(spark: SparkSession, sf_dir: str) -> DataFrame:
    names = name_dicts(spark, sf_dir, "commerce")
    cols = columns_of(spark, sf_dir, DATABASES["commerce"])
    # the localized schema, and the phantom table whose use the check must find
    schema = {names["table"][t]: [names["column"][c] for c in cs] for t, cs in cols.items()} | {"tabla_fantasma": ["fantasma"]}
    refs = checks.sql_references(_faulty_items(spark, sf_dir), {"commerce": schema})
    return checks.check_sql_identifiers(refs, full_map(spark, sf_dir))


@query(f"""
    WITH e AS (SELECT * FROM {values([(i.item_id, re.sub(r"`(\w+)`", lambda m: f"`{image(m.group(1))}`", i.evidence) + (" and `columna_fantasma`" if i.item_id % 4 == 0 else "")) for i in COMMERCE], 'item_id, evidence')}),
    s AS (SELECT item_id, unnest(regexp_extract_all(evidence, '`([^`]*)`', 1)) AS detail FROM e)
    SELECT CAST(item_id AS BIGINT) AS item_id, 'evidence_name' AS reason, detail FROM s
    WHERE detail NOT IN (SELECT * FROM {values([(image(n),) for n in sorted({m for i in COMMERCE for m in re.findall(r"`(\w+)`", i.evidence)})], 'x')})""")
def q32_integrity_evidence(spark: SparkSession, sf_dir: str) -> DataFrame:
    return checks.check_evidence_identifiers(_faulty_items(spark, sf_dir), full_map(spark, sf_dir))


FLAGGED = values(wi.FAULTS, "item_id, reason, detail")


def _found_flags_sql() -> str:
    """The faults as SQL finds them: names that stand in no list of the map's images."""
    rows = [(i.item_id, i.item_id % 3 == 0, re.sub(r"`(\w+)`", lambda m: f"`{image(m.group(1))}`", i.evidence) + (" and `columna_fantasma`" if i.item_id % 4 == 0 else "")) for i in COMMERCE]
    known = values([(image(n),) for n in sorted({m for i in COMMERCE for m in re.findall(r"`(\w+)`", i.evidence)})], "x")
    return f"""WITH e AS (SELECT item_id, broken, unnest(regexp_extract_all(evidence, '`([^`]*)`', 1)) AS span FROM {values(rows, 'item_id, broken, evidence')}),
        f AS (SELECT item_id, 'evidence_name' AS reason FROM e WHERE span NOT IN (SELECT x FROM {known}) UNION ALL SELECT item_id, 'sql_name' FROM (SELECT item_id, unnest(['fantasma', 'tabla_fantasma']) AS name FROM {values(rows, 'item_id, broken, evidence')} WHERE broken))
        SELECT reason, count(*) AS n, count(DISTINCT item_id) AS items FROM f GROUP BY ROLLUP (reason)"""


@query(_found_flags_sql)
def q33_flags_by_reason(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The outcome report: flags that the checks raise on localized items with seeded faults, by reason and in all."""
    found = q31_integrity_sql(spark, sf_dir).unionByName(q32_integrity_evidence(spark, sf_dir))
    return found.rollup("reason").agg(F.count("*").alias("n"), F.countDistinct("item_id").alias("items"))


@query(f"""
    WITH f AS (SELECT item_id, string_agg(DISTINCT reason, ',' ORDER BY reason) AS reasons, round(1.0 - sum(DISTINCT w), 6) AS score
        FROM {FLAGGED} JOIN {values(list(checks.RUBRIC.items()), 'r, w', 'rubric')} ON r = reason GROUP BY item_id)
    SELECT CAST(item_id AS BIGINT) AS item_id, reasons, CAST(score AS DOUBLE) AS score, CASE WHEN score >= 0.8 THEN 'keep' WHEN score >= 0.4 THEN 'repair' ELSE 'drop' END AS decision FROM f""")
def q34_judge_rubric(spark: SparkSession, sf_dir: str) -> DataFrame:
    return checks.judge_alignment(checks.collect_flags(wi.seeded_flags(spark))).select("item_id", "reasons", "score", "decision")


def _source_rows_sql() -> str:
    """Rows that each core item's source SQL gives."""
    rows = [f"SELECT CAST({i.item_id} AS BIGINT) AS item_id, '{i.db_id}' AS db_id, (SELECT count(*) FROM ({i.sql.replace('embedding[0]', 'embedding[1]')}) t) AS n_rows, 'equal' AS verdict, 'keep' AS decision" for i in wi.ITEMS]
    return " UNION ALL ".join(rows)


@query(_source_rows_sql)
def q34a_localize_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The construction over the core items; n_rows is what the localized SQL gives on localized views, the oracle's what the source SQL gives."""
    from xlsql.localize.pipeline import build_localized

    made, views, rows = build_localized(spark, sf_dir, wi.core_items(spark)).collect(), {}, []
    for r in made:
        if r["db_id"] not in views:
            views[r["db_id"]] = spark.newSession()
            nm.publish_localized_views(views[r["db_id"]], sf_dir, DATABASES[r["db_id"]], name_dicts(spark, sf_dir, r["db_id"]))
        rows.append((r["item_id"], r["db_id"], views[r["db_id"]].sql(r["sql_loc"]).count(), r["verdict"], r["decision"]))
    return spark.createDataFrame(rows, "item_id long, db_id string, n_rows long, verdict string, decision string")


def _repair_sql() -> str:
    """Items whose result changes where one column is read in place of another; after the amendment none, and only their database is made anew."""
    differs = [f"SELECT CAST(NOT {bag_equal(i.sql, i.sql.replace('c_acctbal', 'c_custkey'))} AS INTEGER) AS x" for i in COMMERCE]
    return f"SELECT 0 AS round, CAST({len(wi.ITEMS)} AS BIGINT) AS made, CAST(sum(x) AS BIGINT) AS flagged FROM ({' UNION ALL '.join(differs)}) UNION ALL SELECT 1, CAST({len(COMMERCE)} AS BIGINT), CAST(0 AS BIGINT)"


@query(_repair_sql)
def q34b_repair_loop(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rounds of correction after two names of one database got one image: round, items made, items that still fail."""
    from xlsql.localize.pipeline import repair_demo

    return repair_demo(spark, sf_dir)


MANY = 325


def _many_sql() -> str:
    kinds = values([(k, t[0], t[1]) for k, t in enumerate(wi.TEMPLATES)], "kind, db_id, intent")
    return f"SELECT db_id, intent, count(*) AS n, count(*) AS n_equal, count(*) AS n_kept FROM range({MANY}) r(id) JOIN {kinds} ON id % {len(wi.TEMPLATES)} = kind GROUP BY db_id, intent"


@query(_many_sql)
def q34c_localize_many(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The construction over made items of all databases: items, pairs whose execution agrees, items that the judge keeps."""
    from xlsql.localize.pipeline import build_localized

    items = wi.make_items(spark, sf_dir, MANY)
    made = build_localized(spark, sf_dir, items).join(items.select("item_id", "intent"), "item_id")
    return made.groupBy("db_id", "intent").agg(F.count("*").alias("n"), F.count_if(F.col("verdict") == "equal").alias("n_equal"), F.count_if(F.col("decision") == "keep").alias("n_kept"))


def _digest_both(spark: SparkSession, sf_dir: str) -> DataFrame:
    db = DATABASES["commerce"]
    names = name_dicts(spark, sf_dir, "commerce")
    own = spark.newSession()
    nm.publish_localized_views(own, sf_dir, db, names)
    rows = []
    for t in db.tables:
        a, b = tuple(digest(load_table(spark, sf_dir, t)).first()), tuple(digest(own.table(names["table"][t])).first())
        rows.append((t, a == b, int(a[0])))
    return spark.createDataFrame(rows, "table_name string, same boolean, n long")


@query(" UNION ALL ".join(f"SELECT '{t}' AS table_name, true AS same, count(*) AS n FROM {t}" for t in DATABASES["commerce"].tables))
def q30a_view_digests(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Digests of each table and of its localized view."""
    return _digest_both(spark, sf_dir)


assert set(OWNER) == set(TABLES)
