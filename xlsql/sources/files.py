"""Sources and sinks: database files, item files, description files, and releases of splits."""

from __future__ import annotations

import sqlite3
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader
from pyspark.sql.types import StructType

# Declared types of database files and what they become.
AFFINITY = (("INT", "bigint"), ("CHAR", "string"), ("CLOB", "string"), ("TEXT", "string"), ("REAL", "double"), ("FLOA", "double"), ("DOUB", "double"), ("BLOB", "binary"))


def affinity(declared: str) -> str:
    return next((t for k, t in AFFINITY if k in (declared or "").upper()), "double" if declared else "string")


class SqliteSource(DataSource):
    """``spark.read.format("sqlite_file")`` with options path, table, partitions: rows of a table of a database file.

    Files are opened read-only, and split by ranges of row ids.
    """

    @classmethod
    def name(cls) -> str:
        return "sqlite_file"

    def schema(self) -> str:
        with sqlite3.connect(f"file:{self.options['path']}?mode=ro", uri=True) as db:
            cols = db.execute(f"PRAGMA table_info(\"{self.options['table']}\")").fetchall()
        return ", ".join(f"`{c[1]}` {affinity(c[2])}" for c in cols)

    def reader(self, schema: StructType) -> DataSourceReader:
        return SqliteReader(schema, self.options)


class RowRange(InputPartition):
    def __init__(self, low: int | None, high: int | None):
        self.low, self.high = low, high


class SqliteReader(DataSourceReader):
    def __init__(self, schema: StructType, options: dict):
        self.schema_, self.options = schema, dict(options)

    def partitions(self) -> list[InputPartition]:
        with sqlite3.connect(f"file:{self.options['path']}?mode=ro", uri=True) as db:
            try:
                low, high = db.execute(f"SELECT min(rowid), max(rowid) FROM \"{self.options['table']}\"").fetchone()
            except sqlite3.OperationalError:
                # a table without row ids is read by one task
                return [RowRange(None, None)]
        if low is None:
            return [RowRange(0, 0)]
        n = max(1, int(self.options.get("partitions", 4)))
        step = -(-(high - low + 1) // n)
        return [RowRange(a, min(a + step, high + 1)) for a in range(low, high + 1, step)]

    def read(self, partition: RowRange) -> Iterator[tuple]:
        kinds = [f.dataType.typeName() for f in self.schema_.fields]
        names = ", ".join(f'"{f.name}"' for f in self.schema_.fields)
        where, bounds = ("", ()) if partition.low is None else (" WHERE rowid >= ? AND rowid < ?", (partition.low, partition.high))
        db = sqlite3.connect(f"file:{self.options['path']}?mode=ro", uri=True)
        db.text_factory = lambda b: b.decode("utf-8", "replace")
        try:
            for row in db.execute(f"SELECT {names} FROM \"{self.options['table']}\"{where}", bounds):
                yield tuple(cell_of(v, k) for k, v in zip(kinds, row))
        finally:
            db.close()


def cell_of(value, kind: str):
    """A cell as its column's declared type; what cannot be read as that, as files of this kind may hold in any column, is null."""
    if value is None:
        return None
    try:
        if kind == "long":
            n = int(value)
            return n if -(1 << 63) <= n < 1 << 63 and (not isinstance(value, float) or n == value) else None
        if kind == "double":
            return float(value)
        if kind == "binary":
            return value if isinstance(value, bytes) else str(value).encode()
        return value.decode("utf-8", "replace") if isinstance(value, bytes) else str(value)
    except (ValueError, OverflowError, TypeError):
        return None


def dirty_cells(path: str, table: str) -> dict[str, int]:
    """Cells of each column that reading as the declared type makes null."""
    with sqlite3.connect(f"file:{path}?mode=ro", uri=True) as db:
        db.text_factory = lambda b: b.decode("utf-8", "replace")
        cols = [(c[1], {"bigint": "long"}.get(affinity(c[2]), affinity(c[2]))) for c in db.execute(f'PRAGMA table_info("{table}")').fetchall()]
        out = dict.fromkeys((c for c, _ in cols), 0)
        for row in db.execute(f'SELECT {", ".join(f"{chr(34)}{c}{chr(34)}" for c, _ in cols)} FROM "{table}"'):
            for v, (c, k) in zip(row, cols):
                out[c] += v is not None and cell_of(v, k) is None
    return out


class ItemStreamSource(DataSource):
    """``spark.readStream.format("item_lines")`` with option path: items as they are appended to a file of JSON lines."""

    @classmethod
    def name(cls) -> str:
        return "item_lines"

    def schema(self) -> str:
        return "line string"

    def simpleStreamReader(self, schema: StructType) -> SimpleDataSourceStreamReader:
        return ItemLines(self.options["path"], int(self.options.get("most", 1000)))


class ItemLines(SimpleDataSourceStreamReader):
    """Offsets are bytes; a line counts once it is ended."""

    def __init__(self, path: str, most: int):
        self.path, self.most = path, most

    def initialOffset(self) -> dict:
        return {"at": 0}

    def read(self, start: dict) -> tuple[Iterator[tuple], dict]:
        rows, at = [], start["at"]
        with open(self.path, "rb") as f:
            f.seek(at)
            for line in f:
                if not line.endswith(b"\n") or len(rows) >= self.most:
                    break
                at += len(line)
                rows.append((line.decode().rstrip("\n"),))
        return iter(rows), {"at": at}

    def readBetweenOffsets(self, start: dict, end: dict) -> Iterator[tuple]:
        with open(self.path, "rb") as f:
            f.seek(start["at"])
            return iter([(x.decode(),) for x in f.read(end["at"] - start["at"]).split(b"\n")[:-1]])


def register(spark: SparkSession) -> None:
    spark.dataSource.register(SqliteSource)
    spark.dataSource.register(ItemStreamSource)


def read_jdbc(spark: SparkSession, url: str, table: str, column: str, low: int, high: int, partitions: int, **properties) -> DataFrame:
    """A table of a database server, read in ranges of a numeric column (needs the server's driver on the class path)."""
    return spark.read.jdbc(url, table, column=column, lowerBound=low, upperBound=high, numPartitions=partitions, properties=properties)


def file_sizes(spark: SparkSession, path: str) -> DataFrame:
    """path, bytes of each file of a table, from the scan's metadata column."""
    meta = spark.read.parquet(path).select("_metadata.file_path", "_metadata.file_size")
    return meta.groupBy(F.col("file_path").alias("path")).agg(F.max("file_size").alias("bytes"))


def schema_of_file(path: str) -> list[tuple]:
    """(table, column, declared type, is key, referenced table, referenced column) of a database file."""
    out = []
    with sqlite3.connect(f"file:{path}?mode=ro", uri=True) as db:
        for (table,) in db.execute("SELECT name FROM sqlite_master WHERE type = 'table' ORDER BY name").fetchall():
            refs = {r[3]: (r[2], r[4]) for r in db.execute(f'PRAGMA foreign_key_list("{table}")')}
            for c in db.execute(f'PRAGMA table_info("{table}")').fetchall():
                out.append((table, c[1], c[2], bool(c[5]), *refs.get(c[1], (None, None))))
    return out


def read_items(spark: SparkSession, path: str, kind: str = "json") -> DataFrame:
    """Items from a JSON array, JSON lines or CSV, with a fixed schema."""
    from xlsql.workloads.items import ITEM

    if kind == "json":
        return spark.read.schema(ITEM).json(path, multiLine=True)
    return spark.read.schema(ITEM).json(path) if kind == "jsonl" else spark.read.schema(ITEM).csv(path, header=True)


def read_descriptions(spark: SparkSession, path: str) -> DataFrame:
    """Description files of a database, tolerant of bytes that are no UTF-8."""
    return spark.read.option("encoding", "ISO-8859-1").option("header", True).csv(path)


def release(items: DataFrame, path: str, kind: str = "parquet") -> None:
    """Items by split and locale."""
    writer = items.write.mode("overwrite").partitionBy("split", "locale")
    writer.parquet(path) if kind == "parquet" else writer.json(path)


def append_scores(scores: DataFrame, path: str) -> None:
    scores.write.mode("append").partitionBy("method", "lang").parquet(path)


def export_sqlite(df: DataFrame, path: str, table: str, most_rows: int = 1_000_000) -> int:
    """One table into a database file on the driver, which holds small releases only; refuses more than ``most_rows``."""
    rows = df.limit(most_rows + 1).collect()
    if len(rows) > most_rows:
        raise ValueError("too many rows for a file on the driver")
    kinds = {"long": "INTEGER", "integer": "INTEGER", "double": "REAL", "string": "TEXT"}
    with sqlite3.connect(path) as db:
        db.execute(f'CREATE TABLE "{table}" ({", ".join(f"{chr(34)}{f.name}{chr(34)} {kinds.get(f.dataType.typeName(), chr(84) + "EXT")}" for f in df.schema.fields)})')
        db.executemany(f'INSERT INTO "{table}" VALUES ({", ".join("?" * len(df.columns))})', [tuple(r) for r in rows])
    return len(rows)
