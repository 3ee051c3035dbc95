"""Connected components of a table of links, by alternating large and small stars."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from xlsql.session import materialize

#: Tasks that the links of one hub are dealt over.
HUB_SALTS = 32
#: Links (16 bytes each) of at most this number are united by one task; more go round by round over the cluster.
ONE_TASK = 500_000
#: Groups of more rows than this, and than a thousandth of all, are hot: at most a thousand can be.
HOT_ROWS = 10_000


def join_groups(rows: DataFrame, groups: DataFrame, keys: list[str], copies: str = "copies") -> DataFrame:
    """``rows`` with the columns of their group; ``groups`` has each key once, with the number of its rows in ``copies``.

    Rows of hot groups meet them by a broadcast of the at most 1000 hot ones, all others by an exchange, so no group's rows meet in one task.
    """
    total = groups.agg(F.coalesce(F.sum(copies), F.lit(0))).first()[0]
    hot = F.col(copies) > max(HOT_ROWS, total // 1000)
    few = F.broadcast(groups.where(hot))
    rest = rows.join(F.broadcast(groups.where(hot).select(*keys)), keys, "left_anti").join(groups.where(~hot), keys)
    return rows.join(few, keys).unionByName(rest)


class Forest:
    """Union-find over the positions 0..n-1; the smallest position of a set is its root."""

    def __init__(self, n: int):
        self.up = np.arange(n)

    def find(self, i: int) -> int:
        up = self.up
        while up[i] != i:
            up[i] = up[up[i]]
            i = up[i]
        return int(i)

    def union(self, i: int, j: int) -> None:
        i, j = self.find(i), self.find(j)
        if i != j:
            self.up[max(i, j)] = min(i, j)

    def star(self, i: int, others: np.ndarray) -> None:
        """Join ``i`` with every one of ``others``; at most one find for each distinct parent."""
        for j in np.unique(self.up[others]):
            self.union(i, int(j))

    def edges(self) -> tuple[np.ndarray, np.ndarray]:
        """(position, root) of every position that is not a root."""
        up = self.up
        while not np.array_equal(up[up], up):
            up = up[up]
        held = np.flatnonzero(up != np.arange(len(up)))
        return held, up[held]


def _contract(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Replace the links of a batch by a spanning forest of them."""
    for batch in batches:
        ids, at = np.unique(batch[["a", "b"]].to_numpy("int64").ravel(), return_inverse=True)
        forest = Forest(len(ids))
        for i, j in at.reshape(-1, 2):
            forest.union(int(i), int(j))
        child, root = forest.edges()
        yield pd.DataFrame({"a": ids[child], "b": ids[root]})


def _with_min(links: DataFrame, total: int) -> DataFrame:
    """Add ``m``, the least ``v`` of each ``u``; the links of hubs, and only theirs, are salted over ``HUB_SALTS`` tasks."""
    least = links.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n"))
    hub = F.col("n") > max(HOT_ROWS, total // 1000)
    # at most as many as links by the bound above: 2000, for each link stands twice at most
    hubs = F.broadcast(least.where(hub).select("u", F.lit(True).alias("hub")))
    least = least.withColumn("salt", F.explode(F.sequence(F.lit(0), F.when(hub, HUB_SALTS - 1).otherwise(0))))
    salt = F.when(F.col("hub"), F.pmod(F.xxhash64("v"), F.lit(HUB_SALTS))).otherwise(0).cast("int")
    salted = links.join(hubs, "u", "left").withColumn("salt", salt)
    return salted.join(least, ["u", "salt"]).select("u", "v", "m")


def _large_star(links: DataFrame, total: int) -> DataFrame:
    both = links.unionByName(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
    held = _with_min(both, total).withColumn("m", F.least("m", "u"))
    return held.where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()


def _small_star(links: DataFrame, total: int) -> DataFrame:
    held = _with_min(links, total)
    return held.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(held.select("u", F.col("m").alias("v"))).distinct()


def _unite(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """(node, component) of all links of a bounded table."""
    held = [b.to_numpy("int64") for b in batches]
    if not held:
        return
    ids, at = np.unique(np.concatenate(held).ravel(), return_inverse=True)
    forest = Forest(len(ids))
    for i, j in at.reshape(-1, 2).tolist():
        forest.union(i, j)
    root = np.arange(len(ids))
    child, up = forest.edges()
    root[child] = up
    yield pd.DataFrame({"node": ids, "component": ids[root]})


def connected_components(links: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Least reachable node of every linked node.

    ``links``: columns a, b (long). Links with a null end, loops and repeats count for nothing; no rows give no rows.
    Returns node, component, one row for each node that has a link. What is left after every batch has become a forest is united by
    one task where it has at most ``ONE_TASK`` links; else by rounds of large and small stars, each written to the shared folder, so a
    lost executor costs at most one round. The driver sees two numbers of each round and never the links.
    """
    links = links.where("a is not null and b is not null and a <> b").select("a", "b")
    links = links.mapInPandas(_contract, "a long, b long")
    state = materialize(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "links")
    if state.count() <= ONE_TASK:
        return materialize(state.coalesce(1).mapInPandas(_unite, "node long, component long"), "components")
    before = None
    for _ in range(max_rounds):
        now = tuple(state.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
        if now == before or not now[0]:
            break
        before = now
        state = materialize(_small_star(_large_star(state, now[0]), now[0]), "links")
    else:
        raise RuntimeError(f"components did not settle within {max_rounds} rounds")
    return state.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(
        state.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    )
