"""Connected components of an edge table, by alternating star contractions.

No node's links are gathered: each round takes the smallest neighbour by an
aggregate and joins it back, so a hub of any degree is dealt out by the join.
Tables of up to ONE_TASK edges are a few MB: one task joins their sets, instead of
rounds of shuffles that are mostly tasks without rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridpress.session import cut, ship

#: edges that one task may hold (4 MB); larger tables go by rounds
ONE_TASK = 1 << 18


def joined_sets(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(nodes, the smallest node that each can reach) of edges, by lowering both ends' roots until nothing moves."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = at[: len(a)], at[len(a) :]
    root = np.arange(len(nodes))
    while True:
        low = root.copy()
        least = np.minimum(root[x], root[y])
        for end in (x, y, root[x], root[y]):
            np.minimum.at(low, end, least)
        while (low[low] != low).any():
            low = low[low]
        if (low == root).all():
            return nodes, nodes[root]
        root = low


def _in_one_task(edges: DataFrame) -> DataFrame:
    def run(batches):
        held = [(b.column("a").to_numpy(), b.column("b").to_numpy()) for b in batches]
        if held:
            node, root = joined_sets(*(np.concatenate(x) for x in zip(*held, strict=True)))
            yield pa.RecordBatch.from_arrays([pa.array(node), pa.array(root)], names=["node", "root"])

    ship(edges.sparkSession)
    return edges.coalesce(1).mapInArrow(run, "node long, root long")


def _stars(edges: DataFrame, large: bool) -> DataFrame:
    """Large star: larger neighbours go to the smallest of all; small star: the smaller ones do."""
    both = edges.union(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))) if large else edges
    least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
    linked = both.join(least, "a")
    if large:
        return linked.where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a != b").distinct()
    return linked.select(F.col("b").alias("a"), F.col("m").alias("b")).union(least.select("a", F.col("m").alias("b"))).where("a != b").distinct()


def components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """(node, root) for each node of an edge table (a, b); root is the smallest node it can reach.

    Loops and repeated links change nothing; an empty table gives no rows.
    """
    e = cut(edges.where("a != b").select(F.greatest("a", "b").cast("long").alias("a"), F.least("a", "b").cast("long").alias("b")))
    if e.count() <= ONE_TASK:
        return cut(_in_one_task(e))
    e, before = cut(e.distinct()), None
    for _ in range(rounds):
        e = cut(_stars(_stars(e, True), False))
        # done once each node points at one root and no root points further
        now = e.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(20,0)"))).first()
        if now == before:
            return e.select(F.col("a").alias("node"), F.col("b").alias("root"))
        before = now
    raise RuntimeError("components did not settle")
