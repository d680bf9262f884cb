"""Near duplicates among vectors by a permutation index over pivots.

Equal vectors are one class. A class is described by its `order` nearest pivots; inverted lists hold, for every
pivot, the classes that have it. Two classes of a list become candidates if they share at least `min_shared`
pivots, and are verified by their cosine in double precision in the list of their smallest shared pivot, so that
every pair is counted once. A list of more than `block` classes is worked on in pairs of blocks, each a task of its
own. A task returns counts of links and a spanning star of its links, never all pairs.

The pivots are a sample of at most `max_pivots` classes chosen by hash (a documented bound); all rows are indexed.

Defined cases: a vector that is null, empty, zero, or holds a null or non-finite component links with nothing, and
vectors of different lengths never link; rows that repeat a vec_id are separate vectors; rows without vec_id link
with nothing; an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Workspace, read_table
from .components import components, forest

MIN_COSINE = 0.95


def nearest_pivots(x: np.ndarray, pivots: np.ndarray, order: int) -> np.ndarray:
    """Numbers of the `order` nearest pivots of each row of x (unit vectors), nearest first."""
    sim = x @ pivots.T
    order = min(order, sim.shape[1])
    top = np.argpartition(-sim, order - 1, axis=1)[:, :order]
    rank = np.argsort(-np.take_along_axis(sim, top, axis=1), axis=1, kind="stable")
    return np.take_along_axis(top, rank, axis=1).astype(np.int32)


def list_links(rep, size, order, vec, side, pivot: int, min_shared: int, min_cosine: float):
    """(positions i, j) of verified pairs of one inverted list or block pair; side: block of each row."""
    _, local = np.unique(order, return_inverse=True)
    local = local.reshape(order.shape)
    hot = np.zeros((len(rep), int(local.max()) + 1), np.float32)
    np.put_along_axis(hot, local, 1, axis=1)
    smaller = np.zeros_like(hot)
    np.put_along_axis(smaller, local, (order < pivot).astype(np.float32), axis=1)
    a = np.flatnonzero(side == side.min())
    b = np.flatnonzero(side == side.max())
    shared = hot[a] @ hot[b].T
    ok = (shared >= min_shared) & (smaller[a] @ smaller[b].T == 0)
    if side.min() == side.max():
        ok &= np.triu(np.ones(ok.shape, bool), 1)
    i, j = np.nonzero(ok)
    i, j = a[i], b[j]
    keep = np.zeros(len(i), bool)
    for at in range(0, len(i), 100_000):
        p, q = vec[i[at : at + 100_000]], vec[j[at : at + 100_000]]
        keep[at : at + 100_000] = (p * q).sum(axis=1) / np.sqrt((p * p).sum(axis=1) * (q * q).sum(axis=1)) >= min_cosine
    return i[keep], j[keep]


def near_duplicates(spark: SparkSession, vectors: DataFrame, min_cosine: float = MIN_COSINE, max_pivots: int = 2048, per_pivot: int = 100, order: int = 8, min_shared: int = 3, block: int = 1024) -> DataFrame:
    """vec_id, n_links, component_id, kept for every vector."""
    work = Workspace(spark, "pivots")
    e = F.col("embedding").cast("array<double>")
    good = F.col("vec_id").isNotNull() & F.coalesce(F.size("embedding") > 0, F.lit(False)) & F.coalesce(F.forall(e, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))), F.lit(False)) & F.coalesce(F.exists(e, lambda x: x != 0), F.lit(False))
    keyed = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), "embedding").withColumn("ok", good).withColumn("k1", F.when(F.col("ok"), F.xxhash64("embedding"))).withColumn("k2", F.when(F.col("ok"), F.xxhash64(F.lit(7), "embedding")))
    classes = work.table(
        keyed.where("ok").groupBy("k1", "k2").agg(F.min("vec_id").alias("rep"), F.count(F.lit(1)).alias("size"), F.first("embedding").alias("embedding")), "classes"
    )
    facts = classes.groupBy(F.size("embedding").alias("d")).agg(F.count(F.lit(1)).alias("n"))
    links, stars = [], []
    for d, n in sorted((r[0], r[1]) for r in facts.collect()):
        # One index for each dimension that occurs.
        own = classes.where(F.size("embedding") == d)
        want = int(min(max_pivots, max(order, 128, n // per_pivot)))
        share = min(1.0, 2.0 * want / n)  # only about twice the pivots come to the driver, whatever n
        chosen = own.where((F.pmod(F.xxhash64("k1", "k2"), F.lit(1 << 20)) <= int(share * (1 << 20)))).orderBy(F.xxhash64("k1", "k2"), "k1", "k2").limit(want).select("embedding").collect()
        p = np.array([r[0] for r in chosen], np.float64)
        shipped = spark.sparkContext.broadcast(p / np.sqrt((p * p).sum(axis=1))[:, None])
        few = min(order, len(p))  # a small class of vectors has fewer pivots
        found = _index(spark, work, own, shipped, d, few, min(min_shared, few), block, min_cosine)
        links.append(found.where("kind = 0").select(F.col("a").alias("rep"), F.col("b").alias("n")))
        stars.append(found.where("kind = 1").select("a", "b"))
    if not links:
        return keyed.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.lit(True).alias("kept"))
    for x in (links, stars):
        while len(x) > 1:
            x.append(x.pop().unionByName(x.pop()))
    reach = components(work, stars[0])
    counted = links[0].groupBy("rep").agg(F.sum("n").alias("others"))
    named = (
        classes.select("k1", "k2", "rep", "size").join(counted, "rep", "left").join(reach.withColumnRenamed("node", "rep"), "rep", "left")
        .select("k1", "k2", (F.coalesce("others", F.lit(0)) + F.col("size") - 1).cast("long").alias("n_links"), F.coalesce("component", "rep").alias("component_id"))
    )
    out = keyed.select("vec_id", "k1", "k2").join(named, ["k1", "k2"], "left")
    component = F.coalesce("component_id", "vec_id")
    return out.select("vec_id", F.coalesce("n_links", F.lit(0).cast("long")).alias("n_links"), component.alias("component_id"), F.coalesce(F.col("vec_id") == component, F.lit(True)).alias("kept"))


def _index(spark, work, own, shipped, d, order, min_shared, block, min_cosine) -> DataFrame:
    def describe(batches):
        for batch in batches:
            flat = batch.column(2).values.to_numpy().astype(np.float64)
            x = flat[batch.column(2).offsets[0].as_py() :][: batch.num_rows * d].reshape(-1, d)
            x = x / np.sqrt((x * x).sum(axis=1))[:, None]
            near = nearest_pivots(x, shipped.value, order) if len(x) else np.zeros((0, order), np.int32)
            k = near.shape[1]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(2), pa.ListArray.from_arrays(pa.array(np.arange(0, len(x) * k + 1, k), pa.int32()), pa.array(near.ravel()))], ["rep", "size", "vec", "near"])

    lists = own.select("rep", "size", F.col("embedding").cast("array<float>").alias("vec") if dict(own.dtypes)["embedding"] == "array<float>" else F.col("embedding").cast("array<double>").alias("vec"))
    kind = dict(lists.dtypes)["vec"]
    described = work.table(lists.mapInArrow(describe, f"rep long, size long, vec {kind}, near array<int>"), f"near-{d}")
    posted = described.select("rep", "size", "vec", "near", F.explode("near").alias("pivot"))
    length = dict((r[0], r[1]) for r in described.select(F.explode("near").alias("pivot")).groupBy("pivot").count().where(F.col("count") > block).collect())
    # At most max_pivots entries: the number of blocks of the lists that need more than one.
    blocks = F.lit(1)
    if length:
        blocks = F.coalesce(F.get(F.lit([-(-length.get(p, 0) // block) or 1 for p in range(max(length) + 1)]), F.col("pivot")), F.lit(1))
    mine = posted.withColumn("blocks", blocks).withColumn("side", F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int"))
    tasks = mine.select("*", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other")).select("rep", "size", "vec", "near", "pivot", "side", F.least("side", F.col("other").cast("int")).alias("lo"), F.greatest("side", F.col("other").cast("int")).alias("hi"))

    def verify(table: pa.Table) -> pa.Table:
        rep, size, side = (table.column(c).to_numpy() for c in ("rep", "size", "side"))
        vec = table.column("vec").combine_chunks().flatten().to_numpy().astype(np.float64).reshape(len(rep), -1)
        near = table.column("near").combine_chunks().flatten().to_numpy().reshape(len(rep), -1)
        lo, hi = table.column("lo")[0].as_py(), table.column("hi")[0].as_py()
        a = b = np.zeros(0, np.int64)
        if lo == hi or len(np.unique(side)) == 2:
            a, b = list_links(rep, size, near, vec, side, table.column("pivot")[0].as_py(), min_shared, min_cosine)
        who = np.concatenate([a, b])
        count = np.bincount(who, weights=np.concatenate([size[b], size[a]]), minlength=len(rep)).astype(np.int64) if len(who) else np.zeros(len(rep), np.int64)
        at = np.flatnonzero(count)
        x, y = forest(rep[a], rep[b]) if len(a) else (a, b)
        return pa.table([pa.array(np.concatenate([np.zeros(len(at)), np.ones(len(x))]).astype(np.int32)), pa.array(np.concatenate([rep[at], x]).astype(np.int64)), pa.array(np.concatenate([count[at], y]).astype(np.int64))], names=["kind", "a", "b"])

    return work.table(tasks.groupBy("pivot", "lo", "hi").applyInArrow(verify, "kind int, a long, b long"), f"links-{d}")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(spark, read_table(spark, sf_dir, "embeddings"))
