"""Touched scope: what may have changed is connected to what was accessed."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .workspace import Workspace

#: A frontier loop gives up after so many rounds (pointer jumping needs about the logarithm of the diameter).
MOST_ROUNDS = 64


def components(spark: SparkSession, refs: DataFrame, most_rounds: int = MOST_ROUNDS) -> DataFrame:
    """(node, component) by smallest labels over undirected refs (a, b), with pointer jumping; cycles and loops are fine."""
    work = Workspace(spark, "scope")
    both = work.table(refs.select("a", "b").unionByName(refs.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "edges")
    labels = work.table(both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("node"), F.least("a", "m").alias("component")), "labels-0")
    for n in range(1, most_rounds + 1):
        seen = both.join(labels, both["b"] == labels["node"]).groupBy("a").agg(F.min("component").alias("m"))
        near = labels.join(seen, labels["node"] == seen["a"]).select("node", F.least("component", "m").alias("component"))
        up = near.select(F.col("node").alias("component"), F.col("component").alias("up"))
        new = work.table(near.join(up, "component").select("node", F.least("component", "up").alias("component")), f"labels-{n}")
        moved = new.join(labels.select("node", F.col("component").alias("old")), "node").where(F.col("component") != F.col("old")).limit(1).count()
        if not moved:
            return new
        labels = new
    raise RuntimeError(f"no fixed point after {most_rounds} rounds")


def touched_scope(variables: DataFrame, labels: DataFrame, accessed: list[str]) -> DataFrame:
    """variables (name, node_key) with touched: connected to an accessed name, or new to the labels."""
    named = variables.join(labels.withColumnRenamed("node", "node_key"), "node_key", "left").withColumn("component", F.coalesce("component", "node_key"))
    # At most one row for each accessed name.
    hit = named.where(F.col("name").isin(accessed)).select("component").distinct().withColumn("hit", F.lit(True))
    return named.join(F.broadcast(hit), "component", "left").select("name", "node_key", F.coalesce("hit", F.lit(False)).alias("touched"))


def parcel_closure(spark: SparkSession, refs: DataFrame, roots: DataFrame, most_rounds: int = MOST_ROUNDS) -> DataFrame:
    """(root, parcel) reachable over directed refs (src, dst): a frontier loop with an anti-join, so cycles end."""
    work = Workspace(spark, "closure")
    seen = work.table(roots.select("root", "parcel").distinct(), "seen-0")
    frontier, out = seen, [seen]
    for n in range(1, most_rounds + 1):
        reached = frontier.join(refs, frontier["parcel"] == refs["src"]).select("root", F.col("dst").alias("parcel")).distinct()
        for part in out:
            reached = reached.join(part, ["root", "parcel"], "left_anti")
        frontier = work.table(reached, f"seen-{n}")
        if frontier.limit(1).count() == 0:
            break
        out.append(frontier)
    result = out[0]
    for part in out[1:]:
        result = result.unionByName(part)
    return result


def locality_violations(changed: DataFrame, touched_nodes: DataFrame) -> DataFrame:
    """Changed nodes outside the touched ones: must be empty."""
    return changed.join(touched_nodes.select("node_key"), "node_key", "left_anti")
