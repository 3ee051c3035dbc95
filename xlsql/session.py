"""Session helpers shared by the whole library: shared folder, written intermediate tables, batch bounds."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: ``spark.checkpoint.dir``. Where that is unset a local session takes a temporary one; on a cluster this raises."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    context = spark.sparkContext._jsc.sc()
    if found is None and context.getCheckpointDir().isDefined():
        found = context.getCheckpointDir().get()
    if found is None:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        found = "file://" + tempfile.mkdtemp(prefix="xlsql-shared-")
    if not context.getCheckpointDir().isDefined():
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


#: Folders made in the shared folder by this process.
FOLDERS: list[str] = []


def run_folder(spark: SparkSession, name: str) -> str:
    """A fresh path inside the shared folder; nothing is created yet."""
    FOLDERS.append(f"{shared_dir(spark)}/xlsql-{name}-{uuid.uuid4().hex[:12]}")
    return FOLDERS[-1]


def remove_run_folders(spark: SparkSession) -> int:
    """Delete what this process has written into the shared folder, once the results that read it are no longer needed."""
    jvm, n = spark.sparkContext._jvm, 0
    while FOLDERS:
        path = jvm.org.apache.hadoop.fs.Path(FOLDERS.pop())
        n += path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
    return n


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` as Parquet into the shared folder and read it back.

    Cuts the lineage like ``checkpoint()`` but columnar and compressed; it survives lost executors because the files
    lie in the folder that the cluster shares. The files are left for the caller of the result, which is lazy.
    """
    path = run_folder(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def bound_batches(spark: SparkSession, rows: int = 1000, size: str = "2m") -> None:
    """Bound Arrow batches by rows and bytes, so very long texts cannot fill a Python worker (runtime settings).

    A batch's words or tokens take many times its bytes as Python objects, hence the small size.
    """
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", rows)
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", size)


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given Parquet tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
