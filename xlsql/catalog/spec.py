"""Databases: named sets of tables, their foreign keys, and the sessions that hold them as views."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from xlsql.session import load_table

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


@dataclass(frozen=True)
class DatabaseSpec:
    """One database: its tables, foreign keys (child table, column, parent table, column), descriptions of identifiers."""

    db_id: str
    tables: tuple[str, ...]
    keys: tuple[tuple[str, str, str, str], ...] = ()
    descriptions: dict[str, str] = field(default_factory=dict, hash=False)


DATABASES = {
    d.db_id: d
    for d in (
        DatabaseSpec(
            "commerce", ("region", "nation", "customer", "supplier", "part", "orders", "lineitem"),
            (("nation", "n_regionkey", "region", "r_regionkey"), ("customer", "c_nationkey", "nation", "n_nationkey"), ("supplier", "s_nationkey", "nation", "n_nationkey"),
             ("orders", "o_custkey", "customer", "c_custkey"), ("lineitem", "l_orderkey", "orders", "o_orderkey"), ("lineitem", "l_partkey", "part", "p_partkey"), ("lineitem", "l_suppkey", "supplier", "s_suppkey")),
            {"c_acctbal": "balance of the customer's account", "o_totalprice": "price of the whole order", "c_mktsegment": "market segment"},
        ),
        DatabaseSpec("activity", ("events",)),
        DatabaseSpec("corpus", ("documents", "labels", "benchmark", "pages", "conversations"), (("labels", "doc_id", "documents", "doc_id"),)),
        DatabaseSpec("vectors", ("embeddings",)),
    )
}

META = "db_id string, table_name string, column_name string, ordinal int, data_type string, is_key boolean, ref_table string, ref_column string, description string"


def schema_rows(spark: SparkSession, sf_dir: str, db: DatabaseSpec) -> list[tuple]:
    """Rows of ``META`` of one database, from the files' footers: one for each table (ordinal 0) and each column."""
    rows = []
    refs = {(t, c): (p, k) for t, c, p, k in db.keys}
    targets = {(p, k) for _, _, p, k in db.keys}
    for table in db.tables:
        rows.append((db.db_id, table, None, 0, None, False, None, None, db.descriptions.get(table)))
        for i, f in enumerate(load_table(spark, sf_dir, table).schema.fields, 1):
            ref = refs.get((table, f.name), (None, None))
            rows.append((db.db_id, table, f.name, i, f.dataType.simpleString(), (table, f.name) in targets, *ref, db.descriptions.get(f.name)))
    return rows


def extract_schema(spark: SparkSession, sf_dir: str, db: DatabaseSpec) -> DataFrame:
    """Schema metadata of a database."""
    return spark.createDataFrame(schema_rows(spark, sf_dir, db), META).coalesce(1)


def extract_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Metadata of all databases; as many rows as there are identifiers, so one task holds them."""
    return spark.createDataFrame([r for db in DATABASES.values() for r in schema_rows(spark, sf_dir, db)], META).coalesce(1)


def extract_catalog(session: SparkSession, db_id: str, tables: tuple[str, ...]) -> DataFrame:
    """Metadata of tables and views that a session's catalog knows."""
    rows = []
    for t in tables:
        rows.append((db_id, t, None, 0, None, False, None, None, session.catalog.getTable(t).description))
        rows += [(db_id, t, c.name, i, c.dataType, False, None, None, c.description) for i, c in enumerate(session.catalog.listColumns(t), 1)]
    return session.createDataFrame(rows, META).coalesce(1)


def extract_sqlite(spark: SparkSession, path: str, db_id: str) -> DataFrame:
    """Metadata of a database file: declared columns, primary keys and foreign keys."""
    from xlsql.sources.files import affinity, schema_of_file

    rows, at = [], {}
    for table, column, declared, is_key, ref_table, ref_column in schema_of_file(path):
        if table not in at:
            rows.append((db_id, table, None, 0, None, False, None, None, None))
        at[table] = at.get(table, 0) + 1
        rows.append((db_id, table, column, at[table], affinity(declared), is_key, ref_table, ref_column, None))
    return spark.createDataFrame(rows, META).coalesce(1)


def with_descriptions(meta: DataFrame, described: DataFrame) -> DataFrame:
    """Descriptions (db_id, table_name, column_name, description), as read from JSON or CSV files, put into metadata; known ones stay where none is given."""
    d = described.select("db_id", "table_name", "column_name", F.col("description").alias("_told"))
    same = F.col("m.db_id").eqNullSafe(F.col("d.db_id")) & F.col("m.table_name").eqNullSafe(F.col("d.table_name")) & F.col("m.column_name").eqNullSafe(F.col("d.column_name"))
    joined = meta.alias("m").join(d.alias("d"), same, "left")
    return joined.select(*[F.col(f"m.{c}") for c in meta.columns if c != "description"], F.coalesce("_told", F.col("m.description")).alias("description"))


def columns_of(spark: SparkSession, sf_dir: str, db: DatabaseSpec) -> dict[str, list[str]]:
    """Columns of each table, from the footers."""
    return {t: load_table(spark, sf_dir, t).columns for t in db.tables}


def open_database(spark: SparkSession, sf_dir: str, db: DatabaseSpec, prefix: str = "") -> SparkSession:
    """A session of its own in which the database's tables are views; other databases' names are not visible in it."""
    own = spark.newSession()
    own.conf.set("spark.sql.session.timeZone", "UTC")
    for t in db.tables:
        load_table(own, sf_dir, t).createOrReplaceTempView(prefix + t)
    return own
