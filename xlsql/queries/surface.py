"""The operators, functions and streams that gold SQL and evaluation logs need."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from xlsql.catalog.spec import DATABASES
from xlsql.functions.text import tokens
from xlsql.operators import relational as rel
from xlsql.queries import query, values
from xlsql.queries.construction import image, name_dicts
from xlsql.session import load_table
from xlsql.stats import corpus as cs
from xlsql.stats import sampling as sm
from xlsql.streaming import scores as st


def T(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return load_table(spark, sf_dir, name)


@query("""
    SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS net, CASE WHEN l_quantity >= 40 THEN 'large' WHEN l_quantity >= 20 THEN 'medium' ELSE 'small' END AS size, try_cast(l_returnflag AS BIGINT) AS flag
    FROM lineitem WHERE l_shipdate < TIMESTAMP '1997-06-01' AND l_returnflag IN ('R', 'A') AND l_quantity BETWEEN 5 AND 45""")
def q68_scan_filter_project(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = T(spark, sf_dir, "lineitem").where((F.col("l_shipdate") < F.lit("1997-06-01").cast("timestamp_ntz")) & F.col("l_returnflag").isin("R", "A") & F.col("l_quantity").between(5, 45))
    size = F.when(F.col("l_quantity") >= 40, "large").when(F.col("l_quantity") >= 20, "medium").otherwise("small")
    return df.select("l_orderkey", "l_linenumber", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"), size.alias("size"), F.col("l_returnflag").try_cast("bigint").alias("flag"))


@query(" UNION ALL ".join(f"SELECT '{k}' AS kind, count(*) AS n, count(c_custkey) AS n_left, count(o_orderkey) AS n_right FROM customer {j} JOIN orders ON o_custkey = c_custkey AND o_totalprice > 300000" for k, j in (("inner", "INNER"), ("left", "LEFT"), ("full", "FULL"))))
def q69_join_inner_left_full(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = T(spark, sf_dir, "customer").select("c_custkey")
    o = T(spark, sf_dir, "orders").select("o_custkey", "o_orderkey", "o_totalprice")
    out = None
    for kind in ("inner", "left", "full"):
        part = c.join(o, (F.col("o_custkey") == F.col("c_custkey")) & (F.col("o_totalprice") > 300000), kind).agg(F.lit(kind).alias("kind"), F.count("*").alias("n"), F.count("c_custkey").alias("n_left"), F.count("o_orderkey").alias("n_right"))
        out = part if out is None else out.unionByName(part)
    return out


@query("""SELECT 'member' AS side, lang, count(*) AS n FROM documents WHERE doc_id IN (SELECT doc_id FROM labels) GROUP BY lang
    UNION ALL SELECT 'other', lang, count(*) FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels) GROUP BY lang""")
def q70_join_semi_anti(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = T(spark, sf_dir, "documents").select("doc_id", "lang"), T(spark, sf_dir, "labels").select("doc_id")
    part = lambda how, side: docs.join(labels, "doc_id", how).groupBy("lang").agg(F.count("*").alias("n")).select(F.lit(side).alias("side"), "lang", "n")
    return part("left_semi", "member").unionByName(part("left_anti", "other"))


COLUMN_NAMES = sorted({"c_name", "c_acctbal", "o_totalprice", "l_tax", "p_size", "missing_name"})


@query(f"SELECT a.name, b.localized FROM {values([(c,) for c in COLUMN_NAMES], 'name', 'a')} LEFT JOIN {values([(c, image(c)) for c in COLUMN_NAMES if c != 'missing_name'], 'name, localized', 'b')} ON a.name = b.name")
def q71_join_broadcast_map(spark: SparkSession, sf_dir: str) -> DataFrame:
    names = name_dicts(spark, sf_dir, "commerce")["column"]
    m = spark.createDataFrame(list(names.items()), "name string, localized string")
    return spark.createDataFrame([(c,) for c in COLUMN_NAMES], "name string").join(F.broadcast(m), "name", "left")


BANDS = [(k, 50000.0 * k, 50000.0 * (k + 1)) for k in range(10)]


@query(f"SELECT band, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders JOIN {values(BANDS, 'band, low, high', 'b')} ON low <= o_totalprice AND o_totalprice < high GROUP BY band")
def q72_join_theta_range(spark: SparkSession, sf_dir: str) -> DataFrame:
    bands = spark.createDataFrame(BANDS, "band int, low double, high double")
    joined = rel.range_join(T(spark, sf_dir, "orders").select("o_totalprice"), bands, "o_totalprice", "low", "high", 25000.0)
    return joined.groupBy("band").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


@query("""
    WITH c AS (SELECT event_id, user_id, ts FROM events WHERE event_type = 'purchase'), v AS (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type <> 'purchase' GROUP BY user_id, ts)
    SELECT c.event_id, v.event_id AS before_id FROM c ASOF LEFT JOIN v ON c.user_id = v.user_id AND c.ts >= v.ts""")
def q73_join_asof(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last other event of the user at or before each purchase."""
    e = T(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type")
    others = e.where("event_type <> 'purchase'").select("user_id", "ts", F.col("event_id").alias("before_id"))
    return rel.asof_join(e.where("event_type = 'purchase'").select("event_id", "user_id", "ts"), others, "user_id", "ts", "ts", ["before_id"]).select("event_id", "before_id")


@query("SELECT a.conv_id, a.turn, a.role AS asked, b.role AS answered, length(b.text) - length(a.text) AS longer FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1")
def q74_join_self(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = T(spark, sf_dir, "conversations")
    b = c.select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("role").alias("answered"), F.length("text").alias("_b"))
    joined = c.select("conv_id", "turn", F.col("role").alias("asked"), F.length("text").alias("_a")).join(b, ["conv_id", "turn"])
    return joined.select("conv_id", "turn", "asked", "answered", (F.col("_b") - F.col("_a")).cast("long").alias("longer"))


@query("""SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS total, round(avg(l_extendedprice), 4) AS mean, min(l_discount) AS least, max(l_tax) AS most, round(stddev_samp(l_quantity), 6) AS spread,
    count(*) FILTER (l_quantity > 25) AS many, bool_and(l_quantity > 0) AS positive FROM lineitem GROUP BY l_returnflag, l_linestatus""")
def q75_agg_two_phase(spark: SparkSession, sf_dir: str) -> DataFrame:
    q = F.col("l_quantity")
    return T(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(
        F.count("*").alias("n"), F.round(F.sum(q), 2).alias("total"), F.round(F.avg("l_extendedprice"), 4).alias("mean"), F.min("l_discount").alias("least"), F.max("l_tax").alias("most"),
        F.round(F.stddev_samp(q), 6).alias("spread"), F.count_if(q > 25).alias("many"), F.bool_and(q > 0).alias("positive"),
    )


@query("SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers, count(DISTINCT l_orderkey) AS orders FROM lineitem GROUP BY l_returnflag")
def q76_agg_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("suppliers"), F.countDistinct("l_orderkey").alias("orders"))


@query("SELECT l_returnflag, count(DISTINCT l_partkey) AS exact, true AS distinct_ok, true AS median_ok FROM lineitem GROUP BY l_returnflag")
def q77_agg_approx(spark: SparkSession, sf_dir: str) -> DataFrame:
    a = T(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(
        F.countDistinct("l_partkey").alias("exact"), F.approx_count_distinct("l_partkey", 0.02).alias("sketch"), F.percentile_approx("l_extendedprice", 0.5, 10000).alias("p"), F.median("l_extendedprice").alias("m")
    )
    return a.select("l_returnflag", "exact", (F.abs(F.col("sketch") - F.col("exact")) <= 0.1 * F.col("exact")).alias("distinct_ok"), (F.abs(F.col("p") - F.col("m")) <= 0.01 * F.col("m")).alias("median_ok"))


@query("""SELECT lang, source, CAST(grouping(lang) * 2 + grouping(source) AS BIGINT) AS level, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents GROUP BY CUBE (lang, source)
    UNION ALL SELECT lang, NULL, 9, count(*), CAST(sum(n_chars) AS BIGINT) FROM documents GROUP BY ROLLUP (lang)""")
def q78_agg_cube_rollup_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = T(spark, sf_dir, "documents").select("lang", "source", "n_chars")
    a = d.cube("lang", "source").agg(F.grouping_id().alias("level"), F.count("*").alias("n"), F.sum("n_chars").alias("chars"))
    b = d.rollup("lang").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars")).select("lang", F.lit(None).cast("string").alias("source"), F.lit(9).cast("long").alias("level"), "n", "chars")
    return a.select("lang", "source", "level", "n", "chars").unionByName(b)


LANGS = ("de", "en", "es", "fr")


@query("WITH p AS (SELECT source, " + ", ".join(f"CAST(count(*) FILTER (lang = '{x}') AS BIGINT) AS {x}" for x in LANGS) + " FROM documents GROUP BY source) UNPIVOT p ON de, en, es, fr INTO NAME lang VALUE n")
def q79_pivot_unpivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    wide = T(spark, sf_dir, "documents").groupBy("source").pivot("lang", list(LANGS)).agg(F.count(F.lit(1))).fillna(0)
    return wide.unpivot(["source"], list(LANGS), "lang", "n")


@query("""SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER (PARTITION BY o_orderstatus ORDER BY o_orderpriority) AS rk, dense_rank() OVER (PARTITION BY o_orderstatus ORDER BY o_orderpriority) AS dr, ntile(4) OVER w AS quarter,
    lag(o_orderkey) OVER w AS before, lead(o_orderkey, 2) OVER w AS after, round(avg(o_totalprice) OVER (PARTITION BY o_orderstatus ORDER BY o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS near,
    count(*) OVER (PARTITION BY o_orderstatus ORDER BY o_orderkey RANGE BETWEEN 100 PRECEDING AND 100 FOLLOWING) AS around FROM orders WINDOW w AS (PARTITION BY o_orderstatus ORDER BY o_orderkey)""")
def q80_window_rank_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    w, p = Window.partitionBy("o_orderstatus").orderBy("o_orderkey"), Window.partitionBy("o_orderstatus").orderBy("o_orderpriority")
    return T(spark, sf_dir, "orders").select(
        "o_orderkey", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(p).cast("long").alias("rk"), F.dense_rank().over(p).cast("long").alias("dr"), F.ntile(4).over(w).cast("long").alias("quarter"),
        F.lag("o_orderkey").over(w).alias("before"), F.lead("o_orderkey", 2).over(w).alias("after"), F.round(F.avg("o_totalprice").over(w.rowsBetween(-2, 0)), 4).alias("near"), F.count("*").over(w.rangeBetween(-100, 100)).alias("around"),
    )


@query("SELECT c_mktsegment, c_custkey, c_acctbal FROM (SELECT *, row_number() OVER (PARTITION BY c_mktsegment ORDER BY c_acctbal DESC, c_custkey) AS k FROM customer) WHERE k <= 5")
def q81_topk_per_group(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rel.top_per_group(T(spark, sf_dir, "customer").select("c_mktsegment", "c_custkey", "c_acctbal"), ["c_mktsegment"], [F.desc("c_acctbal"), F.asc("c_custkey")], 5)


@query(" UNION ALL ".join(f"SELECT '{k}' AS op, count(*) AS n, CAST(sum(x) AS BIGINT) AS s FROM (SELECT c_nationkey AS x FROM customer {k} SELECT s_nationkey FROM supplier)" for k in ("UNION", "UNION ALL", "INTERSECT", "INTERSECT ALL", "EXCEPT", "EXCEPT ALL")))
def q82_set_ops(spark: SparkSession, sf_dir: str) -> DataFrame:
    a = T(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("x"))
    b = T(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("x"))
    made = {"UNION": a.union(b).distinct(), "UNION ALL": a.union(b), "INTERSECT": a.intersect(b), "INTERSECT ALL": a.intersectAll(b), "EXCEPT": a.subtract(b), "EXCEPT ALL": a.exceptAll(b)}
    out = None
    for k, df in made.items():
        part = df.agg(F.lit(k).alias("op"), F.count("*").alias("n"), F.sum("x").cast("long").alias("s"))
        out = part if out is None else out.unionByName(part)
    return out


SUBQUERIES = """
    WITH RECURSIVE steps(k) AS (SELECT 1 UNION ALL SELECT k + 1 FROM steps WHERE k < 8), big AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey HAVING count(*) > 5)
    SELECT 'scalar' AS kind, count(*) AS n FROM customer WHERE c_acctbal > (SELECT avg(c_acctbal) FROM customer)
    UNION ALL SELECT 'in', count(*) FROM customer WHERE c_custkey IN (SELECT o_custkey FROM big)
    UNION ALL SELECT 'exists', count(*) FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > c.c_acctbal * 20)
    UNION ALL SELECT 'correlated', count(*) FROM orders o WHERE o_totalprice > (SELECT avg(i.o_totalprice) FROM orders i WHERE i.o_custkey = o.o_custkey)
    UNION ALL SELECT 'recursive', count(*) FROM steps"""


@query(SUBQUERIES)
def q83_subqueries_cte(spark: SparkSession, sf_dir: str) -> DataFrame:
    own = spark.newSession()
    for t in ("customer", "orders"):
        T(own, sf_dir, t).createOrReplaceTempView(t)
    return own.sql(SUBQUERIES)


@query(r"""SELECT event_id, CAST(props->>'$.k' AS BIGINT) AS k, upper(event_type) AS up, len(string_split(event_type, '_')) AS parts, event_type LIKE '%c%' AS has_c, md5(event_type) AS digest,
    list_sort(list_distinct([user_id % 3, user_id % 5, 1])) AS xs, list_contains([1, 2], user_id % 3) AS held, lpad(CAST(user_id AS VARCHAR), 6, '0') AS padded, levenshtein(event_type, 'purchase') AS far FROM events""")
def q84_scalar_strings_arrays_maps_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    u = F.col("user_id")
    m = F.create_map(F.lit("k"), F.get_json_object("props", "$.k").cast("long"))
    return T(spark, sf_dir, "events").select(
        "event_id", F.element_at(m, "k").alias("k"), F.upper("event_type").alias("up"), F.size(F.split("event_type", "_")).cast("long").alias("parts"), F.col("event_type").like("%c%").alias("has_c"), F.md5("event_type").alias("digest"),
        F.array_sort(F.array_distinct(F.array(u % 3, u % 5, F.lit(1).cast("long")))).alias("xs"), F.array_contains(F.array(F.lit(1).cast("long"), F.lit(2).cast("long")), u % 3).alias("held"),
        F.lpad(u.cast("string"), 6, "0").alias("padded"), F.levenshtein("event_type", F.lit("purchase")).cast("long").alias("far"),
    )


@query("""SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, CAST(date_trunc('month', o_orderdate) AS DATE) AS month_start, strftime(o_orderdate, '%Y-%m') AS label, date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS days,
    CAST(o_orderdate + INTERVAL 30 DAY AS DATE) AS due, round(sqrt(o_totalprice), 4) AS root, CAST(ceil(o_totalprice / 1000) AS BIGINT) AS thousands, greatest(o_totalprice, 100000.0) AS at_least, round(ln(o_totalprice), 6) AS log FROM orders""")
def q85_scalar_dates_math(spark: SparkSession, sf_dir: str) -> DataFrame:
    d, p = F.col("o_orderdate"), F.col("o_totalprice")
    return T(spark, sf_dir, "orders").select(
        "o_orderkey", F.year(d).cast("long").alias("y"), F.month(d).cast("long").alias("m"), F.date_trunc("month", d).cast("date").alias("month_start"), F.date_format(d, "yyyy-MM").alias("label"), F.datediff(d, F.lit("1992-01-01").cast("date")).cast("long").alias("days"),
        F.date_add(d.cast("date"), 30).alias("due"), F.round(F.sqrt(p), 4).alias("root"), F.ceil(p / 1000).cast("long").alias("thousands"), F.greatest(p, F.lit(100000.0)).alias("at_least"), F.round(F.log(p), 6).alias("log"),
    )


def _event_files(spark: SparkSession, sf_dir: str, files: int = 4) -> str:
    """Events as files in order of time, closed by a row far in the future that lets the last windows out."""
    e = T(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type", "value")
    last = e.agg((F.max("ts") + F.expr("INTERVAL 30 DAYS")).alias("ts")).select(F.lit(-1).cast("long").alias("event_id"), "ts", F.lit(-1).cast("long").alias("user_id"), F.lit("end").alias("event_type"), F.lit(0.0).alias("value"))
    return st.staged_files(e.unionByName(last), files, "ts")


@query("SELECT time_bucket(INTERVAL 1 DAY, ts) AS window_start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2")
def q86_stream_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = st.drain(st.tumbling(st.event_stream(spark, _event_files(spark, sf_dir))), "tumbling")
    return out.where("event_type <> 'end'").withColumn("window_start", F.col("window_start").cast("timestamp_ntz"))


@query("""WITH w AS (SELECT date_trunc('day', ts) + to_days(CAST(k AS INTEGER)) AS window_start FROM events, (VALUES (0), (-1)) v(k)) SELECT CAST(window_start AS TIMESTAMP) AS window_start, count(*) AS n FROM w GROUP BY window_start""")
def q87_stream_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    stream = st.event_stream(spark, _event_files(spark, sf_dir))
    out = st.drain(st.sliding(stream.where("event_id >= 0 or ts is not null")), "sliding")
    last = T(spark, sf_dir, "events").agg(F.max("ts").alias("last"))
    return out.crossJoin(last).where(F.col("window_start").cast("timestamp_ntz") <= F.col("last")).select(F.col("window_start").cast("timestamp_ntz").alias("window_start"), "n")


@query("""
    WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 10 MINUTE THEN 0 ELSE 1 END AS new FROM events), s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g)
    SELECT user_id, min(ts) AS session_start, max(ts) + INTERVAL 10 MINUTE AS session_end, count(*) AS n FROM s GROUP BY user_id, k""")
def q88_stream_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = st.drain(st.sessions(st.event_stream(spark, _event_files(spark, sf_dir))), "sessions").where("user_id >= 0")
    return out.select("user_id", F.col("session_start").cast("timestamp_ntz").alias("session_start"), F.col("session_end").cast("timestamp_ntz").alias("session_end"), "n")


@query("SELECT event_type, count(*) AS n, CAST(sum(event_id) AS BIGINT) AS ids FROM events GROUP BY event_type")
def q89_stream_dedup_late(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every tenth event comes twice, and old ones come again at the end: repeats and late rows are dropped."""
    from xlsql.session import run_folder

    e = T(spark, sf_dir, "events").select("event_id", "ts", "event_type")
    path = run_folder(spark, "stream")
    e.unionByName(e.where("event_id % 10 = 0")).repartitionByRange(4, "ts").sortWithinPartitions("ts").write.parquet(path)
    first = e.agg(F.min("ts").alias("first"))
    late = e.crossJoin(first).where(F.col("ts") < F.col("first") + F.expr("INTERVAL 1 DAY")).select((F.col("event_id") + 10_000_000).alias("event_id"), "ts", "event_type")
    late.coalesce(1).write.mode("append").parquet(path)
    # the first four files make one batch; the late file, written after them, the next
    stream = st.event_stream(spark, path, 4)
    out = st.drain(st.distinct_events(stream, ["event_id"]), "dedup")
    return out.where("event_id < 10000000").groupBy("event_type").agg(F.count("*").alias("n"), F.sum("event_id").alias("ids"))


@query("SELECT event_type, count(*) AS n, round(avg(value), 4) AS mean, round(var_pop(value), 4) AS variance FROM events GROUP BY event_type")
def q90_stream_state_means(spark: SparkSession, sf_dir: str) -> DataFrame:
    stream = st.event_stream(spark, _event_files(spark, sf_dir), 1).where("event_id >= 0")
    out = st.latest(st.drain(st.running_means(stream), "means", "update"), "event_type", "n")
    return out.select("event_type", "n", F.round("mean", 4).alias("mean"), F.round(F.col("m2") / F.col("n"), 4).alias("variance"))


@query(r"SELECT page_id, len(regexp_extract_all(regexp_replace(html, '<[^>]*>', ' ', 'g'), '[\p{L}\p{N}]+|[^\s\p{L}\p{N}]')) AS n_tokens FROM pages")
def q91_html_text_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T(spark, sf_dir, "pages").select("page_id", F.size(tokens(F.regexp_replace("html", "<[^>]*>", " "))).cast("long").alias("n_tokens"))


@query("SELECT vec_id AS vec_ident, round(CAST(embedding[1] AS DOUBLE), 6) AS first, len(embedding) AS size, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x)), 4) AS norm2 FROM embeddings")
def q92_vector_access(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Array access under localized names."""
    names = name_dicts(spark, sf_dir, "vectors")
    v = T(spark, sf_dir, "embeddings").withColumnsRenamed(names["column"])
    e = F.col(names["column"]["embedding"])
    norm = F.aggregate(e, F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double"))
    return v.select(F.col(names["column"]["vec_id"]).alias("vec_ident"), F.round(e[0].cast("double"), 6).alias("first"), F.size(e).cast("long").alias("size"), F.round(norm, 4).alias("norm2"))


@query(r"SELECT item_id, unnest(regexp_extract_all(text, '[\p{L}\p{N}]+|[^\s\p{L}\p{N}]')) AS token FROM benchmark")
def q93_udtf_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A table function callable from SQL by a lateral join."""
    from xlsql.functions.udtf import register

    own = spark.newSession()
    register(own)
    T(own, sf_dir, "benchmark").createOrReplaceTempView("benchmark")
    return own.sql("SELECT item_id, t.token FROM benchmark, LATERAL explode_tokens(text) t")


@query("""
    SELECT replace(lower(trim(p_name)), ' ', '_') AS snake, CAST(ceil(round(1068 / (1 + 1067 / CAST(p_partkey + 500 AS DOUBLE)), 9)) AS BIGINT) AS n, round(sqrt(greatest(p_retailprice, 0.001::DOUBLE) / greatest(CAST(p_size AS DOUBLE), 0.001::DOUBLE)), 6) AS reward
    FROM part WHERE regexp_matches(p_name, '^[a-z ]+$') AND NOT contains(p_name, '  ')""")
def q94_sql_function_surface(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The SQL functions over a table's rows."""
    from xlsql.functions.udtf import register

    own = spark.newSession()
    register(own)
    T(own, sf_dir, "part").createOrReplaceTempView("part")
    return own.sql("SELECT ascii_snake(p_name) AS snake, clt_n(1.96, 0.03, 0.5, p_partkey + 500) AS n, round(ves_reward(p_retailprice, CAST(p_size AS DOUBLE)), 6) AS reward FROM part WHERE p_name RLIKE '^[a-z ]+$' AND NOT contains(p_name, '  ')")


@query("""SELECT source, count(DISTINCT lang) AS n_distinct FROM documents GROUP BY source""")
def q95_salted_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rel.distinct_count_salted(T(spark, sf_dir, "documents").select("source", "lang"), ["source"], "lang")


@query("SELECT n_name, count(*) AS n FROM customer JOIN nation ON n_nationkey = c_nationkey GROUP BY n_name")
def q96_salted_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = T(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k"), "c_custkey")
    n = T(spark, sf_dir, "nation").select(F.col("n_nationkey").alias("k"), "n_name")
    return rel.salted_join(c, n, ["k"]).groupBy("n_name").agg(F.count("*").alias("n"))


@query("""
    SELECT lang, count(DISTINCT t) AS vocab, true AS close FROM (SELECT lang, unnest(regexp_extract_all(lower(text), '[\\p{L}\\p{N}]+|[^\\s\\p{L}\\p{N}]')) AS t FROM documents) GROUP BY lang""")
def q97_vocab_sketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exact vocabulary, and whether the sketch lies within its error of it."""
    docs = T(spark, sf_dir, "documents").select("lang", "text")
    both = cs.vocabulary(docs, "text", ["lang"]).join(cs.vocabulary(docs, "text", ["lang"], exact=False).withColumnRenamed("vocab", "sketch"), "lang")
    return both.select("lang", "vocab", (F.abs(F.col("sketch") - F.col("vocab")) <= 0.05 * F.col("vocab")).alias("close"))


PAGED = """
    SELECT 'page' AS part, CAST(o_orderkey AS VARCHAR(20)) AS k, CAST(o_custkey AS BIGINT) AS n FROM (SELECT o_orderkey, o_custkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 20) p
    UNION ALL SELECT 'lateral', c_mktsegment, t.n FROM (SELECT DISTINCT c_mktsegment FROM customer) s, LATERAL (SELECT count(*) AS n FROM customer c WHERE c.c_mktsegment = s.c_mktsegment AND c_acctbal > 0) t
    UNION ALL SELECT 'sets', coalesce(c_mktsegment, CAST(c_nationkey AS VARCHAR(20)), 'all'), count(*) FROM customer GROUP BY GROUPING SETS ((c_mktsegment), (c_nationkey), ())
    UNION ALL SELECT 'cross', r.r_name, count(*) FROM region r CROSS JOIN nation n WHERE r.r_regionkey < n.n_nationkey GROUP BY r.r_name
    UNION ALL SELECT 'mode', max_by(c_name, c_acctbal), bit_xor(c_custkey) FROM customer"""


@query(PAGED)
def q98_paging_lateral_sets_cross(spark: SparkSession, sf_dir: str) -> DataFrame:
    own = spark.newSession()
    for t in ("customer", "orders", "region", "nation"):
        T(own, sf_dir, t).createOrReplaceTempView(t)
    return own.sql(PAGED)


@query("SELECT CAST(item_id AS BIGINT) AS item_id, name FROM " + values([(1, n) for n in ("a", "t", "b")] + [(2, n) for n in ("x", "c d", "u", "x")], "item_id, name"))
def q99_udtf_identifiers(spark: SparkSession, sf_dir: str) -> DataFrame:
    from xlsql.functions.udtf import register

    own = spark.newSession()
    register(own)
    own.createDataFrame([(1, "SELECT count(a) FROM t WHERE b = 'text' -- c"), (2, "SELECT x.`c d` FROM u AS x")], "item_id long, sql string").createOrReplaceTempView("texts")
    return own.sql("SELECT item_id, t.name FROM texts, LATERAL explode_identifiers(sql) t")


JOINED = "SELECT count(*) AS n, CAST(sum(o_orderkey) AS BIGINT) AS s FROM orders JOIN customer ON o_custkey = c_custkey WHERE c_mktsegment = 'BUILDING'"


@query(" UNION ALL ".join(JOINED.replace("SELECT", f"SELECT '{h}' AS hint,", 1) for h in ("broadcast", "merge", "shuffle_hash")))
def q100_join_strategies(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same join by each strategy, each hinted; customers are few here, elsewhere the planner chooses by size."""
    o, c = T(spark, sf_dir, "orders").select("o_orderkey", "o_custkey"), T(spark, sf_dir, "customer").where("c_mktsegment = 'BUILDING'").select("c_custkey")
    out = None
    for h in ("broadcast", "merge", "shuffle_hash"):
        side = c.hint(h)
        part = o.join(side, o["o_custkey"] == side["c_custkey"]).agg(F.lit(h).alias("hint"), F.count("*").alias("n"), F.sum("o_orderkey").alias("s"))
        out = part if out is None else out.unionByName(part)
    return out


assert sm.Z and DATABASES
