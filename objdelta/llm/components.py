"""Connected components of an edge table by alternating large-star and small-star rounds.

Every round is two aggregations and joins over the edges that are left, written to the shared folder; nothing is
collected but a count and a checksum. Hub nodes are aggregated before the shuffle, and joins on them are left to
the adaptive skew handling.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Workspace


def _large_star(edges: DataFrame) -> DataFrame:
    """Every larger neighbour of a node is hung on the smallest of the node and its neighbours."""
    both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
    return both.where(F.col("b") > F.col("a")).join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b")


def _small_star(edges: DataFrame) -> DataFrame:
    """A node and its smaller neighbours are hung on the smallest of them; edges point from a down to b."""
    down = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    least = down.groupBy("a").agg(F.min("b").alias("m"))
    hung = down.join(least, "a").where(F.col("b") != F.col("m")).select(F.col("b").alias("a"), F.col("m").alias("b"))
    return hung.unionByName(least.select("a", F.col("m").alias("b"))).where("a <> b").distinct()


def components(work: Workspace, edges: DataFrame, label: str = "cc", most_rounds: int = 60) -> DataFrame:
    """(node, component): for every node of edges (a, b), the smallest node that it reaches."""
    current = work.table(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), f"{label}-0")
    before = None
    for n in range(1, most_rounds + 1):
        # A forest of stars: every node hangs on one root, and no root hangs on anything.
        state = current.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if state == before or state[0] == 0:
            break
        before = state
        current = work.table(_small_star(_large_star(current)), f"{label}-{n}")
        work.drop(f"{label}-{n - 1}")
    return current.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(current.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())


def forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """A spanning star (node, smallest node reached) of the given links: at most one row for each node."""
    ids, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = at[: len(a)], at[len(a) :]
    low = np.arange(len(ids))
    while True:
        new = low.copy()
        np.minimum.at(new, x, low[y])
        np.minimum.at(new, y, low[x])
        new = np.minimum(new, new[new])
        if (new == low).all():
            break
        low = new
    hung = np.flatnonzero(low != np.arange(len(ids)))
    return ids[hung], ids[low[hung]]
