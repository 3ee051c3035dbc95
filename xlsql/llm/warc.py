"""WARC archives: one gzip member for each record, revisits for repeated payloads, and a sequential reader."""

from __future__ import annotations

import base64
import hashlib
import uuid
import zlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import pandas as pd
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from xlsql.llm.graph import HOT_ROWS
from xlsql.session import bound_batches, materialize, run_folder

#: Payloads of fewer bytes are written again instead of being referred to.
LEAST_REVISIT = 1000
#: Pages that cannot revisit, or whose payload is hot, are dealt over this many keys.
SPREAD = 4096
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
CHUNK = 1 << 16


def _base32(digest: bytes) -> str:
    return "sha1:" + base64.b32encode(digest).decode()


def encode_record(kind: str, headers: dict[str, str], block: bytes) -> bytes:
    """One WARC/1.1 record as one gzip member."""
    head = {"WARC-Type": kind, **headers, "WARC-Block-Digest": _base32(hashlib.sha1(block).digest()), "Content-Length": str(len(block))}
    raw = b"WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in head.items()).encode() + b"\r\n" + block + b"\r\n\r\n"
    packer = zlib.compressobj(6, zlib.DEFLATED, 31)
    return packer.compress(raw) + packer.flush()


def _base16(said: str | None) -> str | None:
    return base64.b32decode(said.rpartition(":")[2]).hex() if said else None


@dataclass
class Record:
    """A record as read: headers with lower-case names, the block, and whether its digest agreed."""

    headers: dict[str, str]
    block: bytes
    offset: int
    digest_ok: bool


class WarcError(ValueError):
    """An archive that breaks the format: bad member, framing or length."""


def _members(stream) -> Iterator[tuple[int, bytes]]:
    """(offset, content) of each gzip member, inflated chunk by chunk; at most one record is held."""
    inflate, start, parts, at = zlib.decompressobj(31), 0, [], 0
    begun = False
    while chunk := stream.read(CHUNK):
        at += len(chunk)
        while chunk:
            begun = True
            try:
                parts.append(inflate.decompress(chunk))
            except zlib.error as e:
                raise WarcError(f"member at {start}: {e}") from e
            chunk = b""
            if inflate.eof:
                chunk = inflate.unused_data
                yield start, b"".join(parts)
                start, inflate, parts, begun = at - len(chunk), zlib.decompressobj(31), [], False
    if begun:
        raise WarcError(f"member at {start} is cut off")


def read_records(stream) -> Iterator[Record]:
    """Read an archive from first to last byte: inflate, frame by Content-Length, verify the block's digest."""
    for offset, raw in _members(stream):
        head, found, rest = raw.partition(b"\r\n\r\n")
        lines = head.decode("utf-8").split("\r\n")
        if not found or not lines[0].startswith("WARC/"):
            raise WarcError(f"no record header at {offset}")
        headers = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}
        length = int(headers.get("content-length", -1))
        if length < 0 or len(rest) != length + 4 or rest[length:] != b"\r\n\r\n":
            raise WarcError(f"record at {offset}: content length {length}, {len(rest) - 4} bytes there")
        block = rest[:length]
        said = headers.get("warc-block-digest")
        yield Record(headers, block, offset, said is None or said == _base32(hashlib.sha1(block).digest()))


def _writer(folder: str) -> Callable[[Iterator[pd.DataFrame]], Iterator[pd.DataFrame]]:
    """Write the records of a task as one archive. Its name is new for each attempt, so a task that runs twice leaves an archive
    that nobody reads, and only the path that the task returns counts."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        store, at = fs.FileSystem.from_uri(folder)
        out, n, path = None, 0, f"{at}/{uuid.uuid4().hex}.warc.gz"
        for batch in batches:
            for row in batch.itertuples(index=False):
                if out is None:
                    store.create_dir(at, recursive=True)
                    out = store.open_output_stream(path, compression=None)
                payload = (row.html or "").encode("utf-8", "surrogatepass")
                headers = {"WARC-Record-ID": f"<urn:uuid:{uuid.uuid4()}>", "WARC-Date": "1970-01-01T00:00:00Z", "X-Page-Id": row.page_id or "", "X-Payload-Length": str(len(payload)), "WARC-Payload-Digest": _base32(bytes.fromhex(row.digest)), "Content-Type": "text/html; charset=utf-8"}
                if isinstance(row.url, str) and row.url:
                    headers["WARC-Target-URI"] = row.url.replace("\r", "%0D").replace("\n", "%0A")
                if row.revisit:
                    headers |= {"WARC-Profile": REVISIT_PROFILE, "X-Refers-To-Page": row.first}
                out.write(encode_record("revisit" if row.revisit else "response", headers, b"" if row.revisit else payload))
                n += 1
        if out is not None:
            out.close()
            yield pd.DataFrame({"path": [path], "records": [n]})

    return run


def write_warc(pages: DataFrame, folder: str, page_id: str = "page_id", url: str = "url", html: str = "html", least: int = LEAST_REVISIT) -> DataFrame:
    """Write a record for each page into archives below ``folder``; returns path, records of every archive.

    Of pages with equal payloads of at least ``least`` bytes, that with the largest page_id is the response, the others
    revisit it. A null html is an empty payload, a null url leaves the target out; rows that repeat the largest page_id are
    responses too; a page without id revisits if another page of its payload has an id. The text crosses one shuffle in which pages of a hot
    payload, and pages too short to revisit, are spread, and is not sorted: the chosen records are what is hashed.
    """
    bound_batches(pages.sparkSession, 256, "2m")
    body = F.coalesce(F.col(html), F.lit(""))
    held = pages.select(F.col(page_id).cast("long").alias("page_id"), F.col(url).cast("string").alias("url"), body.alias("html"), F.sha1(body.cast("binary")).alias("digest"), F.octet_length(body).alias("bytes"))
    chosen = held.where(F.col("bytes") >= least).groupBy("digest").agg(F.max("page_id").alias("first"), F.count("*").alias("n")).where("n > 1 and first is not null")
    chosen = materialize(chosen, "chosen")
    hot = F.col("n") > max(HOT_ROWS, chosen.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0] // 1000)
    # at most a thousand payloads can be hot
    held = held.join(F.broadcast(chosen.where(hot).select("digest", F.col("first").alias("hot_first"))), "digest", "left")
    alone = (F.col("bytes") < least) | F.col("hot_first").isNotNull()
    held = held.withColumn("key", F.when(alone, F.concat(F.lit("-"), F.pmod(F.monotonically_increasing_id(), F.lit(SPREAD)).cast("string"))).otherwise(F.col("digest")))
    held = held.join(chosen.where(~hot).select(F.col("digest").alias("key"), F.col("first").alias("cold_first")).hint("shuffle_hash"), "key", "left").withColumn("first", F.coalesce("hot_first", "cold_first"))
    revisit = F.col("first").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("first"))
    # ids as text, for a batch with a null would turn whole numbers into doubles
    ids = [F.col(c).cast("string").alias(c) for c in ("page_id", "first")]
    return held.select(*ids, "url", "html", "digest", revisit.alias("revisit")).mapInPandas(_writer(folder), "path string, records long")


def _reader(folder: str) -> Callable[[Iterator[pd.DataFrame]], Iterator[pd.DataFrame]]:
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        store, _ = fs.FileSystem.from_uri(folder)
        for batch in batches:
            for path in batch["path"]:
                rows, held = [], 0
                with store.open_input_stream(path, compression=None) as stream:
                    for r in read_records(stream):
                        h = r.headers
                        rows.append((path, r.offset, h.get("warc-type"), h.get("x-page-id") or None, h.get("warc-target-uri"), _base16(h.get("warc-payload-digest")), int(h.get("x-payload-length", len(r.block))), h.get("x-refers-to-page"), r.block, r.digest_ok))
                        held += len(r.block)
                        if held > 1 << 20 or len(rows) >= 256:
                            yield pd.DataFrame(rows, columns=COLUMNS)
                            rows, held = [], 0
                if rows:
                    yield pd.DataFrame(rows, columns=COLUMNS)

    return run


COLUMNS = ["path", "position", "record_type", "page", "url", "digest", "payload_bytes", "refers", "block", "block_ok"]


def read_warc(archives: DataFrame, folder: str) -> DataFrame:
    """Records of the archives listed in ``archives`` (column path), each archive read in sequence by one task.

    Returns page_id, url, record_type, payload (null for revisits), payload_bytes, payload_digest (lower-case hex SHA-1), refers_to,
    path, position, digest_ok (block digest agrees, and for responses the payload digest and length). A damaged archive raises.
    """
    raw = archives.repartition(max(1, archives.count()), "path").mapInPandas(_reader(folder), "path string, position long, record_type string, page string, url string, digest string, payload_bytes long, refers string, block binary, block_ok boolean")
    plain = F.col("digest")
    response = F.col("record_type") == "response"
    return raw.select(
        F.col("page").cast("long").alias("page_id"), "url", "record_type", F.when(response, F.col("block")).alias("payload"), "payload_bytes", plain.alias("payload_digest"),
        F.col("refers").cast("long").alias("refers_to"), "path", "position",
        (F.col("block_ok") & (~response | ((F.sha1("block") == plain) & (F.octet_length("block") == F.col("payload_bytes"))))).alias("digest_ok"),
    )


def warc_round_trip(spark: SparkSession, pages: DataFrame) -> DataFrame:
    """Write all pages into archives in the shared folder, read them back, and return the records."""
    folder = run_folder(spark, "warc")
    return read_warc(materialize(write_warc(pages, folder), "archives"), folder)
