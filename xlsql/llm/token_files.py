"""Token counts from flat token files without an index: a scan for end-of-document identifiers."""

from __future__ import annotations

import base64
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import tiktoken
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from xlsql.session import bound_batches, materialize, run_folder

#: Tokens of one block of the scan.
BLOCK = 1 << 20
#: Documents of one file; files of a task follow one another.
FILE_TOKENS = 1 << 25


def default_ranks() -> str:
    """Path of the public byte-level rank file; every caller may name another."""
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken")


def load_ranks(blob: bytes) -> dict[bytes, int]:
    return {base64.b64decode(a): int(b) for a, b in map(bytes.split, blob.splitlines())}


def _writer(folder: str, ranks: bytes, pattern: str, separator: int) -> Callable[[Iterator[pd.DataFrame]], Iterator[pd.DataFrame]]:
    """Token files of a task. Names are new for each attempt, and only files that a finished task returns are read."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        coder = tiktoken.Encoding("flat", pat_str=pattern, mergeable_ranks=load_ranks(ranks), special_tokens={})
        store, at = fs.FileSystem.from_uri(folder)
        out, path, ordinal, tokens = None, None, 0, 0
        for batch in batches:
            paths, ordinals = [], []
            for text in batch["text"]:
                if out is None:
                    store.create_dir(at, recursive=True)
                    path = f"{at}/{uuid.uuid4().hex}.u16"
                    out, ordinal, tokens = store.open_output_stream(path, compression=None), 0, 0
                ids = np.array([*coder.encode_ordinary(text or ""), separator], "<u2")
                out.write(ids.tobytes())
                paths.append(path)
                ordinals.append(ordinal)
                ordinal, tokens = ordinal + 1, tokens + len(ids)
                if tokens >= FILE_TOKENS:
                    out.close()
                    out = None
            yield pd.DataFrame({"path": paths, "ordinal": np.array(ordinals, "i8"), "doc_id": batch["doc_id"]})
        if out is not None:
            out.close()

    return run


def write_token_files(docs: DataFrame, folder: str, doc_id: str = "doc_id", text: str = "text", ranks: str | bytes | None = None, pattern: str | None = None, separator: int = 50256) -> DataFrame:
    """Write the tokens of all texts as flat little-endian 16-bit files, each document ended by ``separator``.

    Returns path, ordinal (the document's place in its file), doc_id. A null text is empty. Identifiers must fit 16 bits.
    """
    bound_batches(docs.sparkSession)
    if pattern is None:
        import public_tokenizers

        pattern = public_tokenizers.PATTERN
    blob = ranks if isinstance(ranks, bytes) else open(ranks or default_ranks(), "rb").read()
    if max(load_ranks(blob).values()) >= separator or separator > 0xFFFF:
        raise ValueError("the separator must be free and fit 16 bits")
    # ids as text, for a batch with a null would turn whole numbers into doubles
    rows = docs.select(F.col(doc_id).cast("string").alias("doc_id"), F.col(text).alias("text"))
    places = rows.mapInPandas(_writer(folder, blob, pattern, separator), "path string, ordinal long, doc_id string")
    return places.withColumn("doc_id", F.col("doc_id").cast(docs.schema[doc_id].dataType))


def _scan(folder: str, separator: int, block: int) -> Callable[[Iterator[pd.DataFrame]], Iterator[pd.DataFrame]]:
    """What each block tells: its separators' places; of it only differences of neighbours and both ends are kept."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        store, _ = fs.FileSystem.from_uri(folder)
        for batch in batches:
            for path, k in zip(batch["path"], batch["block"]):
                with store.open_input_file(path) as f:
                    f.seek(int(k) * block * 2)
                    data = np.frombuffer(f.read(block * 2), "<u2")
                ends = np.flatnonzero(data == separator)
                tail = len(data) - (int(ends[-1]) + 1 if len(ends) else 0)
                yield pd.DataFrame({"path": [path], "block": [int(k)], "ends": [len(ends)], "tail": [tail], "lengths": [np.diff(ends, prepend=-1) - 1]})

    return run


def count_tokens(spark: SparkSession, files: DataFrame, folder: str, separator: int = 50256, block: int = BLOCK) -> DataFrame:
    """Tokens of every document of flat token files (column path), found by scanning for ``separator``.

    Blocks are scanned independently, each in one vectorised comparison. A prefix scan over the blocks of a file then gives the
    number of separators before each block, which numbers its documents, and the tokens that the last document of earlier blocks has
    left open, which the block's first document takes up. Returns path, ordinal, n_tokens (the separator not counted). Tokens after
    a file's last separator are a last document if there are any; an empty file has none. Bytes short of a whole token are an error of
    the file and raise.
    """

    def sizes(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        store, _ = fs.FileSystem.from_uri(folder)
        for batch in batches:
            paths = list(batch["path"])
            size = [i.size for i in store.get_file_info(paths)] if paths else []
            if any(s % 2 for s in size):
                raise ValueError("a token file ends within a token")
            yield pd.DataFrame({"path": paths, "bytes": size})

    known = files.select("path").distinct().mapInPandas(sizes, "path string, bytes long").where("bytes > 0")
    blocks = known.select("path", F.explode(F.sequence(F.lit(0), F.ceil(F.col("bytes") / (2 * block)) - 1)).alias("block"))
    scanned = materialize(blocks.repartition("path", "block").mapInPandas(_scan(folder, separator, block), "path string, block long, ends long, tail long, lengths array<long>"), "scan")
    order = Window.partitionBy("path").orderBy("block")
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    # blocks since and with the last separator: all their tails are open; a block without one is open as a whole
    runs = scanned.select("path", "block", "ends", "tail", F.coalesce(F.sum("ends").over(before), F.lit(0)).alias("first"), F.coalesce(F.sum((F.col("ends") > 0).cast("int")).over(order), F.lit(0)).alias("run"))
    open_run = Window.partitionBy("path", "run").orderBy("block")
    runs = runs.withColumn("so_far", F.sum("tail").over(open_run.rowsBetween(Window.unboundedPreceding, 0)))
    runs = runs.withColumn("carry", F.coalesce(F.lag("so_far").over(order), F.lit(0))).withColumn("last", F.lead("block").over(order).isNull())
    at = scanned.select("path", "block", "lengths").join(runs, ["path", "block"])
    whole = at.select("path", "first", "carry", F.posexplode("lengths").alias("i", "length"))
    whole = whole.select("path", (F.col("first") + F.col("i")).alias("ordinal"), (F.col("length") + F.when(F.col("i") == 0, F.col("carry")).otherwise(0)).alias("n_tokens"))
    rest = runs.where("last and so_far > 0").select("path", (F.col("first") + F.col("ends")).alias("ordinal"), F.col("so_far").alias("n_tokens"))
    return whole.unionByName(rest)


def token_counts(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", block: int = BLOCK, **coder) -> DataFrame:
    """Tokenise all texts into flat files in the shared folder, scan the files, and return doc_id, n_tokens of every row.

    Null and empty texts have 0 tokens; repeated rows and null ids come back as they are; other columns are ignored.
    """
    spark = docs.sparkSession
    folder = run_folder(spark, "tokens")
    places = materialize(write_token_files(docs, folder, doc_id, text, **coder), "places")
    counts = count_tokens(spark, places, folder, coder.get("separator", 50256), block)
    return places.join(counts, ["path", "ordinal"]).select("doc_id", "n_tokens")
