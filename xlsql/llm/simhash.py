"""Near duplicates by 64-bit fingerprints: pivot distance tables over Hamming space."""

from __future__ import annotations

import itertools
import re
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from xlsql.llm.columns import fresh
from xlsql.llm.graph import Forest, connected_components, join_groups
from xlsql.session import bound_batches, materialize

WORD = re.compile(rb"[^\x20\x09-\x0D]+")
SEED = 42
#: Reference fingerprints of the distance table, from a rule.
REFERENCES = tuple(xxhash.xxh64_intdigest(f"reference {i}", 7) for i in range(16))
#: A bucket of more members is compared in blocks by Python tasks, not by a join.
LIGHT = 48
BLOCK = 1024


def fingerprint(text: str | None, width: int = 3) -> int:
    """Unsigned fingerprint of a whole text; null and texts without a word give 0."""
    words = WORD.findall((text or "").encode("utf-8", "surrogatepass").lower())
    if not words:
        return 0
    shingles = [b" ".join(x) for x in zip(*(words[i:] for i in range(width)))] or [b" ".join(words)]
    digest, set_bits = xxhash.xxh64_intdigest, np.zeros(64, "int64")
    for start in range(0, len(shingles), 65536):
        h = np.fromiter((digest(x, SEED) for x in shingles[start : start + 65536]), "<u8")
        set_bits += np.unpackbits(h.view("u1").reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype="int64")
    return int(np.packbits(2 * set_bits > len(shingles), bitorder="little").view("<u8")[0])


def with_fingerprint(docs: DataFrame, text: str = "text", out: str = "fp", width: int = 3) -> DataFrame:
    """Add the fingerprint as a signed long with the same 64 bits."""
    bound_batches(docs.sparkSession)

    def run(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for batch in batches:
            yield pd.Series(np.array([fingerprint(t, width) for t in batch], "u8").astype("i8"))

    return docs.withColumn(out, F.pandas_udf(run, "long")(F.col(text)))


def bit_groups(distance: int, n: int = 0) -> list[int]:
    """Masks such that any two fingerprints within ``distance`` agree on all bits of one mask.

    The bits are cut into distance + k runs; at most ``distance`` of them differ, so k agree. k grows with the number ``n`` of distinct
    fingerprints, so that a mask has about as many values as there are fingerprints.
    """
    agree = next(k for k in range(2, 64) if k == 16 or 64 * k >= n.bit_length() * (distance + k))
    runs = distance + agree
    cuts = [round(64 * i / runs) for i in range(runs + 1)]
    whole = [(1 << cuts[i + 1]) - (1 << cuts[i]) for i in range(runs)]
    return [sum(some) for some in itertools.combinations(whole, agree)]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def _blocks(distance: int) -> Callable[[pd.DataFrame], pd.DataFrame]:
    """Spanning forest of the links between two blocks of one bucket, by table, then by the bits themselves."""

    def run(group: pd.DataFrame) -> pd.DataFrame:
        fp, own = group["fp"].to_numpy("i8").view("u8"), group["block"].to_numpy()
        table = np.stack([np.bitwise_count(fp ^ np.uint64(r)) for r in REFERENCES], 1).astype("i1")
        order = np.argsort(table[:, 0], kind="stable")
        fp, own, table, rep = fp[order], own[order], table[order], group["rep"].to_numpy("i8")[order]
        across, forest = group["lo"].iat[0] != group["hi"].iat[0], Forest(len(fp))
        ends = np.searchsorted(table[:, 0], table[:, 0] + distance, "right")
        for i in range(len(fp)):
            window = slice(i + 1, ends[i])
            near = np.flatnonzero(np.abs(table[window] - table[i]).max(1, initial=0) <= distance) + i + 1
            near = near[np.bitwise_count(fp[near] ^ fp[i]) <= distance]
            if across:
                near = near[own[near] != own[i]]
            if len(near):
                forest.star(i, near)
        child, root = forest.edges()
        return pd.DataFrame({"a": rep[child], "b": rep[root]})

    return run


def hamming_links(prints: DataFrame, distance: int = 3, n: int = 0) -> DataFrame:
    """Links (a, b) of representatives whose fingerprints differ in at most ``distance`` bits.

    ``prints``: fp (long, distinct), rep (long); ``n``: about how many. Every fingerprint has a row of distances to ``REFERENCES``; by the triangle
    inequality a pair is discarded where any two of these differ by more than ``distance``, and the bits verify the rest. Distances
    to any references lie near 32 for nearly all fingerprints, so intervals of them cannot deal the work out by themselves: fingerprints
    meet in buckets of equal runs of bits (``bit_groups``), and no linked pair shares no bucket. A bucket over ``LIGHT`` members is cut into
    hashed blocks that tasks compare two by two, in order of the first distance, each giving a spanning forest: what is kept of a dense
    bucket grows with its members, and connectivity is exact.
    """
    table = [F.bit_count(F.col("fp").bitwiseXOR(F.lit(_signed(r)))).cast("tinyint").alias(f"d{i}") for i, r in enumerate(REFERENCES)]
    masks = F.array(*[F.col("fp").bitwiseAND(F.lit(_signed(m))) for m in bit_groups(distance, n)])
    keys = prints.where("rep is not null").select("fp", "rep", F.posexplode(masks).alias("grp", "key"))
    counts = keys.groupBy("grp", "key").agg(F.count("*").alias("members")).where("members > 1")
    held = materialize(keys.join(counts, ["grp", "key"]), "buckets")
    light = held.where(F.col("members") <= LIGHT).select("grp", "key", "fp", "rep", *table)
    a, b = light.alias("a"), light.alias("b")
    widest = F.greatest(*[F.abs(F.col(f"a.d{i}") - F.col(f"b.d{i}")) for i in range(len(REFERENCES))])
    pairs = a.join(b, (F.col("a.grp") == F.col("b.grp")) & (F.col("a.key") == F.col("b.key")) & (F.col("a.fp") < F.col("b.fp")) & (widest <= distance))
    pairs = pairs.where(F.bit_count(F.col("a.fp").bitwiseXOR(F.col("b.fp"))) <= distance).select(F.col("a.rep").alias("a"), F.col("b.rep").alias("b"))
    n = F.ceil(F.col("members") / BLOCK).cast("int")
    heavy = held.where(F.col("members") > LIGHT).withColumn("block", F.pmod(F.xxhash64("fp"), n).cast("int"))
    heavy = heavy.withColumn("other", F.explode(F.sequence(F.lit(0), n - 1))).withColumn("lo", F.least("block", "other")).withColumn("hi", F.greatest("block", "other"))
    heavy = heavy.groupBy("grp", "key", "lo", "hi").applyInPandas(_blocks(distance), "a long, b long")
    return pairs.unionByName(heavy)


def simhash_groups(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", width: int = 3, distance: int = 3) -> DataFrame:
    """Fingerprint and group of every document.

    Returns doc_id, fingerprint (16 lower-case hex digits), component_id (least doc_id reachable through links of at
    most ``distance`` differing bits, itself included).
    Nulls and ties: a null or wordless text has fingerprint zero and links like any other; equal fingerprints are one
    node, so copies are never paired; repeated rows come back repeated; rows that share a doc_id are one document for
    the grouping; a null doc_id keeps a null component unless other documents share its fingerprint. Other columns are
    ignored, whatever their names; an empty table gives an empty result.
    """
    rows = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text"))
    rows = materialize(with_fingerprint(rows, "text", "fp", width).select("doc_id", "fp"), "prints")
    reps = materialize(rows.groupBy("fp").agg(F.min("doc_id").alias("rep"), F.count("*").alias("copies")), "reps")
    comps = connected_components(hamming_links(reps, distance, reps.count()))
    groups = materialize(reps.join(comps, reps["rep"] == comps["node"], "left").select("fp", F.coalesce("component", "rep").alias("component_id"), "copies"), "groups")
    return join_groups(rows, groups, ["fp"]).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def pair_report(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", width: int = 3, distance: int = 3) -> DataFrame:
    """One row: fingerprints, pairs that meet in light buckets, pairs that the table of distances lets through, pairs that are links. Figures for judging the table, not needed for the groups."""
    prints = with_fingerprint(docs.select(F.col(text).alias("text")), "text", "fp", width).select("fp").distinct()
    n = prints.count()
    masks = F.array(*[F.col("fp").bitwiseAND(F.lit(_signed(m))) for m in bit_groups(distance, n)])
    keys = prints.select("fp", F.posexplode(masks).alias("grp", "key"))
    counts = keys.groupBy("grp", "key").agg(F.count("*").alias("members")).where(f"members between 2 and {LIGHT}")
    held = keys.join(counts, ["grp", "key"])
    a, b = held.alias("a"), held.alias("b")
    pairs = a.join(b, (F.col("a.grp") == F.col("b.grp")) & (F.col("a.key") == F.col("b.key")) & (F.col("a.fp") < F.col("b.fp")))
    far = [F.abs(F.bit_count(F.col("a.fp").bitwiseXOR(F.lit(_signed(r)))) - F.bit_count(F.col("b.fp").bitwiseXOR(F.lit(_signed(r))))) for r in REFERENCES]
    near = F.bit_count(F.col("a.fp").bitwiseXOR(F.col("b.fp"))) <= distance
    return pairs.agg(F.lit(n).alias("fingerprints"), F.count("*").alias("met"), F.count_if(F.greatest(*far) <= distance).alias("passed"), F.count_if(near).alias("linked"))


def dedup_keep(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", **parameters) -> DataFrame:
    """Rows of ``docs`` that stand for their group: one row of each group stays, that of the least doc_id.

    Rows without a doc_id stay. All columns of ``docs`` come back unchanged. Of rows that share a kept doc_id that with the least hash of all
    its columns stays, whatever the partitions.
    """
    groups = simhash_groups(docs, doc_id, text, **parameters)
    kept_id, all_of, mark = fresh(docs, "kept", "all", "mark")
    kept = groups.where("doc_id = component_id").select(F.col("doc_id").alias(kept_id)).distinct()
    known = docs.where(F.col(doc_id).isNotNull()).join(kept, F.col(doc_id).cast("long") == F.col(kept_id), "left_semi")
    # maps cannot be hashed as they are
    plain = [F.to_json(f.name) if "map<" in f.dataType.simpleString() else F.col(f"`{f.name}`") for f in docs.schema.fields]
    whole = known.select(F.col(doc_id).alias(kept_id), F.xxhash64(*plain).alias(mark), F.struct("*").alias(all_of))
    one = whole.groupBy(kept_id).agg(F.min_by(all_of, mark).alias(all_of)).select(f"{all_of}.*")
    return one.unionByName(docs.where(F.col(doc_id).isNull()))
