"""Near duplicates of embeddings: exact metric range join over pivot cells."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from xlsql.llm.graph import Forest, connected_components, join_groups
from xlsql.session import bound_batches, materialize

#: Vectors that one task holds of a cell's own, and of its guests.
HOME_BLOCK, GUEST_BLOCK = 16_384, 32_768
#: There are always some cells, so that small tables take the same way; the table of pivots, which every task gets, is bounded, and larger cells are cut into blocks.
LEAST_PIVOTS, MOST_PIVOTS = 8, 4096
#: Numbers of nearest pivots that a bound is drawn from together.
TOGETHER = (2, 4, 8, 16)
#: Cosines this near the threshold are summed again without rounding loss.
CLOSE = 1e-12


def _unit(x: np.ndarray) -> np.ndarray:
    x = x / np.abs(x).max(1, keepdims=True)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def _exact_cosine(a: np.ndarray, b: np.ndarray) -> float:
    dot, aa, bb = (math.fsum(p * q) for p, q in ((a, b), (a, a), (b, b)))
    return dot / math.sqrt(aa) / math.sqrt(bb)


def distinct_directions(table: np.ndarray) -> np.ndarray:
    """Unit vectors without those that are another one up to rounding: of parallel pivots the first stays."""
    kept: list[int] = []
    for i in range(len(table)):
        if not kept or (table[kept] @ table[i]).max() < 1 - 1e-12:
            kept.append(i)
    return table[kept]


def guest_cells(unit: np.ndarray, table: np.ndarray, reach: float) -> tuple[np.ndarray, np.ndarray]:
    """Home cell of each unit vector, and whether each cell may hold a vector within chord ``reach`` of it.

    A vector y of cell q is nearer to pivot q than to any other pivot p. So for any weights w >= 0 the difference x - y, measured along
    the sum of w (p - q), is at least the sum of w (x.p - x.q); divided by that sum's length this bounds the distance from x to the cell from
    below. Taken are the home pivot alone, and the nearest 2, 4, 8 and 16 weighted by how much nearer they are than the next. Rounding is
    allowed for on both sides, so pivots that nearly coincide never lose a guest.
    """
    close = unit @ table.T
    home = close.argmax(1)
    far = lambda gain, length2: gain > reach * np.sqrt(np.maximum(length2, 0) + 1e-13) + 1e-12
    out = far(close.max(1)[:, None] - close, (2 - 2 * table @ table.T)[home])
    for k in TOGETHER:
        if k >= len(table):
            break
        top = np.argpartition(-close, k, axis=1)[:, : k + 1]
        value = np.take_along_axis(close, top, 1)
        weight = value - value.min(1, keepdims=True)
        weight /= np.maximum(weight.sum(1, keepdims=True), 1e-300)
        along = np.einsum("nk,nkd->nd", weight, table[top])
        total = weight.sum(1, keepdims=True)
        out |= far((weight * value).sum(1)[:, None] - total * close, (along**2).sum(1)[:, None] - 2 * total * (along @ table.T) + total**2)
    return home, ~out


def _assign(pivots: dict[int, np.ndarray], cosine: float, kind: str | None) -> Callable[[Iterator[pd.DataFrame]], Iterator[pd.DataFrame]]:
    """Home cell of each vector, and the cells that get it as guest; with ``kind``, the type of its numbers, the vector itself too.

    Of two cells one sends to the other, the one that comes before it on a ring of all cells, so that a pair meets once and all cells get alike much.
    """
    reach = math.sqrt(max(0.0, 2 - 2 * cosine)) + 1e-9

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for dim, part in batch.groupby(batch["embedding"].map(len)):
                raw = np.stack([np.asarray(v, kind or "f8") for v in part["embedding"]])
                n, table = len(raw), pivots.get(dim, np.zeros((0, dim)))
                if len(table):
                    home, near = guest_cells(_unit(raw.astype("f8")), table, reach)
                    ahead = (np.arange(len(table)) - home[:, None]) % len(table)
                    near &= (ahead > 0) & ((2 * ahead < len(table)) | (2 * ahead == len(table)) & (home[:, None] < np.arange(len(table))))
                    at, cell = np.nonzero(near)
                else:
                    home, at, cell = np.full(n, -1), np.zeros(0, int), np.zeros(0, int)
                rows, cells = np.concatenate([np.arange(n), at]), np.concatenate([home, cell])
                out = {"dim": dim, "cell": cells.astype("i4"), "guest": np.arange(len(rows)) >= n}
                if kind:
                    packed = [v.tobytes() for v in raw]
                    out |= {"rep": part["rep"].to_numpy("i8")[rows], "copies": part["copies"].to_numpy("i8")[rows], "vec": [packed[i] for i in rows]}
                yield pd.DataFrame(out)

    return run


def _join(cosine: float, kind: str) -> Callable[[pd.DataFrame], pd.DataFrame]:
    """Links of one block of a cell with one chunk of its guests, and on the first chunk among themselves.

    Vectors are put in order of the angle to the block's first vector, a local pivot; only those whose angles differ by no
    more than the reach are multiplied. Products in single precision decide where they are farther from the threshold than their error can
    be; the others are summed in double precision. Returns for every linked vector its links here, and a root of what it is linked to.
    """
    angle = math.acos(min(1.0, cosine)) + 1e-6

    def run(group: pd.DataFrame) -> pd.DataFrame:
        raw = np.frombuffer(b"".join(group["vec"]), kind).reshape(len(group), -1).astype("f8")
        rep, copies, guest = group["rep"].to_numpy("i8"), group["copies"].to_numpy("i8"), group["guest"].to_numpy()
        n_home, empty = int((~guest).sum()), pd.DataFrame({"rep": np.zeros(0, "i8"), "n": np.zeros(0, "i8"), "root": np.zeros(0, "i8")})
        if not n_home:
            return empty
        unit = _unit(raw)
        theta = np.arccos(np.clip(unit @ unit[int(np.flatnonzero(~guest)[0])], -1, 1))
        order = np.lexsort((theta, guest))
        raw, unit, rep, copies, theta = raw[order], unit[order], rep[order], copies[order], theta[order]
        single, error = unit.astype("f4"), 2.5e-7 * (unit.shape[1] + 16)
        sure, maybe = np.float32(cosine + error), np.float32(cosine - error)
        within, links, forest = bool(group["chunk"].iat[0] == 0), np.zeros(len(rep), "i8"), Forest(len(rep))
        sides = [(0, n_home)] * within + [(n_home, len(rep))]
        for start in range(0, n_home, 256):
            end = min(n_home, start + 256)
            for low, high in sides:
                a = low + np.searchsorted(theta[low:high], theta[start] - angle)
                b = low + np.searchsorted(theta[low:high], theta[end - 1] + angle, "right")
                if low < n_home:
                    a = max(a, start)
                if a >= b:
                    continue
                near = single[start:end] @ single[a:b].T
                if near.max() < maybe:
                    continue
                hit = near >= sure
                i, j = np.nonzero((near >= maybe) & ~hit)
                for k in range(0, len(i), 1 << 16):
                    x, y = i[k : k + (1 << 16)], j[k : k + (1 << 16)]
                    dot = (unit[start + x] * unit[a + y]).sum(1)
                    for z in np.flatnonzero(np.abs(dot - cosine) <= CLOSE):
                        dot[z] = _exact_cosine(raw[start + x[z]], raw[a + y[z]])
                    hit[x, y] = dot >= cosine
                if low < n_home:
                    # among themselves the upper half, and nothing with itself
                    hit &= np.arange(a, b) > np.arange(start, end)[:, None]
                links[a:b] += copies[start:end] @ hit
                links[start:end] += hit @ copies[a:b]
                for i in np.flatnonzero(hit.any(1)):
                    forest.star(start + i, np.flatnonzero(hit[i]) + a)
        held = np.flatnonzero(links)
        roots = np.array([forest.find(int(i)) for i in held], int)
        return pd.DataFrame({"rep": rep[held], "n": links[held], "root": rep[roots]}) if len(held) else empty

    return run


def valid_vectors(vectors: DataFrame, vec_id: str = "vec_id", embedding: str = "embedding") -> DataFrame:
    """vec_id, embedding in single precision if it is given so, else in double (null where the vector is null, empty, zero or holds null or non-finite components)."""
    kind = "array<float>" if vectors.schema[embedding].dataType.simpleString() == "array<float>" else "array<double>"
    x = F.col(embedding).cast(kind)
    bad = lambda v: v.isNull() | F.isnan(v) | (F.abs(v) == float("inf"))
    usable = x.isNotNull() & ~F.exists(x, bad) & F.exists(x, lambda v: v != 0.0)
    return vectors.select(F.col(vec_id).cast("long").alias("vec_id"), F.when(usable, x).alias("embedding"))


def _pivots(reps: DataFrame, n: int) -> dict[int, np.ndarray]:
    """Unit pivots for each length of vector: the first vectors by a hash, bounded in number, without parallel ones."""
    wanted = min(MOST_PIVOTS, max(LEAST_PIVOTS, math.ceil(n / HOME_BLOCK)))
    chosen = [np.asarray(r[0], "f8") for r in reps.orderBy(F.xxhash64("embedding")).limit(wanted).select("embedding").collect()]
    return {d: distinct_directions(_unit(np.stack([v for v in chosen if len(v) == d]))) for d in {len(v) for v in chosen}}


def cell_report(vectors: DataFrame, vec_id: str = "vec_id", embedding: str = "embedding", cosine: float = 0.95) -> DataFrame:
    """dim, cell, homes, guests: how the pivots deal the distinct vectors out. Guests over homes is what the triangle inequality could not spare."""
    reps = valid_vectors(vectors, vec_id, embedding).where("embedding is not null").select("embedding").distinct()
    dealt = reps.mapInPandas(_assign(_pivots(reps, reps.count()), cosine, None), "dim int, cell int, guest boolean")
    return dealt.groupBy("dim", "cell").agg(F.count_if(~F.col("guest")).alias("homes"), F.count_if("guest").alias("guests"))


def cosine_groups(vectors: DataFrame, vec_id: str = "vec_id", embedding: str = "embedding", cosine: float = 0.95) -> DataFrame:
    """Links and group of every vector under cosine >= ``cosine`` (double precision, exact).

    Returns vec_id, n_links (other vectors linked directly), component_id (least vec_id reachable, itself included), kept.
    Copies are one node that carries their number. Pivots split the vectors into cells, cells into blocks of ``HOME_BLOCK``,
    and each block meets chunks of ``GUEST_BLOCK`` guests as a task of its own, so that neither a crowded cell nor a large
    group of copies meets in one task; tasks give counts and forests, never pairs.
    Nulls and ties: null, empty, zero and non-finite vectors link with nothing (n_links 0, own component); vectors of
    different lengths never link; repeated rows of one vec_id count as vectors of their own that share a component; a null
    vec_id links like any other and never names a component while another vector of its group has an id. Other columns are
    ignored; an empty table gives an empty result.
    """
    spark = vectors.sparkSession
    bound_batches(spark)
    rows = valid_vectors(vectors, vec_id, embedding)
    kind = "f4" if "float" in rows.schema["embedding"].dataType.simpleString() else "f8"
    # rows find their node again by 128 bits of hash instead of the vector
    zero = F.transform("embedding", lambda v: v + F.lit(0).cast("float" if kind == "f4" else "double"))
    rows = rows.withColumn("h1", F.xxhash64(zero)).withColumn("h2", F.xxhash64(F.lit(7), zero))
    reps = rows.where("embedding is not null").groupBy("embedding").agg(F.min("vec_id").alias("rep"), F.count("*").alias("copies"), F.min("h1").alias("h1"), F.min("h2").alias("h2"))
    reps = materialize(reps.select("rep", "copies", "embedding", "h1", "h2", F.monotonically_increasing_id().alias("node")), "vectors")
    pivots = _pivots(reps, reps.count())
    nodes = reps.select(F.col("node").alias("rep"), "copies", "embedding")
    counts = nodes.mapInPandas(_assign(pivots, cosine, None), "dim int, cell int, guest boolean")
    counts = counts.groupBy("dim", "cell").agg(F.sum(F.col("guest").cast("long")).alias("guests"), F.sum((~F.col("guest")).cast("long")).alias("homes"))
    counts = counts.select("dim", "cell", F.greatest(F.lit(1), F.ceil(F.col("homes") / HOME_BLOCK)).cast("int").alias("blocks"), F.greatest(F.lit(1), F.ceil((F.col("guests") + F.col("homes")) / GUEST_BLOCK)).cast("int").alias("chunks"))
    dealt = nodes.mapInPandas(_assign(pivots, cosine, kind), "dim int, cell int, guest boolean, rep long, copies long, vec binary")
    # as many rows as cells: at most MOST_PIVOTS for each length of vector
    dealt = dealt.join(F.broadcast(counts), ["dim", "cell"])
    block, chunk = F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int"), F.pmod(F.xxhash64("rep", F.lit(1)), F.col("chunks")).cast("int")
    place = lambda b, c, g: F.struct(b.cast("int").alias("block"), c.cast("int").alias("chunk"), g.alias("guest"))
    as_guest = F.transform(F.sequence(F.lit(0), F.col("blocks") - 1), lambda b: place(b, chunk, F.lit(True)))
    at_home = F.concat(F.transform(F.sequence(F.lit(0), F.col("chunks") - 1), lambda c: place(block, c, F.lit(False))), F.filter(as_guest, lambda p: p["block"] > block))
    dealt = dealt.withColumn("place", F.explode(F.when(F.col("guest"), as_guest).otherwise(at_home)))
    dealt = dealt.select("dim", "cell", "place.block", "place.chunk", "place.guest", "rep", "copies", "vec")
    found = materialize(dealt.groupBy("dim", "cell", "block", "chunk").applyInPandas(_join(cosine, kind), "rep long, n long, root long"), "links")
    links = found.groupBy("rep").agg(F.sum("n").alias("links"))
    comps = connected_components(found.select(F.col("rep").alias("a"), F.col("root").alias("b")))
    at = reps.drop("embedding").join(links, reps["node"] == links["rep"], "left").drop(links["rep"]).join(comps.withColumnRenamed("node", "at"), F.col("node") == F.col("at"), "left")
    at = materialize(at.select("rep", "copies", "h1", "h2", "links", F.coalesce("component", "node").alias("root")), "roots")
    least = at.groupBy("root").agg(F.min("rep").alias("component_id"), F.count("*").alias("members"))
    named = join_groups(at, least, ["root"], "members")
    groups = materialize(named.select("h1", "h2", (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links"), "component_id", "copies"), "groups")
    linked = join_groups(rows.where("embedding is not null").select("vec_id", "h1", "h2"), groups, ["h1", "h2"]).select("vec_id", "n_links", "component_id")
    alone = rows.where("embedding is null").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return linked.unionByName(alone).withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))
