"""Streaming front end: a micro-batch is an execution; only changed parcels are saved."""

from __future__ import annotations

import hashlib

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.workspace import Workspace


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events file as a stream; ts as a timestamp, so that it can carry a watermark."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{sf_dir}/event[s].parquet").withColumn("ts", F.col("ts").cast("timestamp"))


def run_to_table(stream: DataFrame, work: Workspace, name: str, mode: str = "append") -> DataFrame:
    """Run a query over what is there now, into files (append) that a retried batch overwrites by its id."""
    path = f"{work.root}/{name}"

    def save(df: DataFrame, batch: int) -> None:
        df.write.mode("overwrite").parquet(f"{path}/batch={batch}")

    q = stream.writeStream.foreachBatch(save).outputMode(mode).option("checkpointLocation", f"{work.root}/{name}-checkpoint").trigger(availableNow=True).start()
    q.awaitTermination()
    return work.spark.read.schema(stream.schema).parquet(f"{path}/batch=*")


def incremental_save(spark: SparkSession, stream: DataFrame, work: Workspace) -> DataFrame:
    """Save each batch's parcels (user, fp) unless the index has their fingerprint; idempotent by batch id."""
    base = f"{work.root}/saved"

    def save(df: DataFrame, batch: int) -> None:
        rows = df.select("user_id", F.md5(F.concat_ws("|", "event_id", "event_type", "props")).alias("h"))
        parcels = rows.groupBy("user_id").agg(F.count(F.lit(1)).alias("n_nodes"), F.md5(F.concat_ws(";", F.array_sort(F.collect_list("h")))).alias("fp"))
        if batch:
            known = spark.read.schema(parcels.schema).parquet(*[f"{base}/batch={b}" for b in range(batch)])
            parcels = parcels.join(known.select("fp"), "fp", "left_anti").select("user_id", "n_nodes", "fp")
        parcels.write.mode("overwrite").parquet(f"{base}/batch={batch}")

    q = stream.writeStream.foreachBatch(save).option("checkpointLocation", f"{work.root}/saved-checkpoint").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(f"{base}/batch=*").select("user_id", "n_nodes", "fp")


def window_counts(stream: DataFrame, width: str = "1 day", late: str = "2 days") -> DataFrame:
    w = F.window("ts", width)
    x = stream.withWatermark("ts", late).groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return x.select(F.col("w.start").alias("start"), "event_type", "n")


def dedup(stream: DataFrame, late: str = "2 days") -> DataFrame:
    """Re-delivered executions count once."""
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def late_events(events: DataFrame, watermark: str) -> DataFrame:
    """Side count of rows older than a watermark."""
    return events.where(F.col("ts") < F.lit(watermark).cast("timestamp")).groupBy("event_type").agg(F.count(F.lit(1)).alias("late"))


def interval_join(left: DataFrame, right: DataFrame, width: str, late: str = "2 days") -> DataFrame:
    """Pairs of one user whose right event follows the left one within width; old state is dropped by the watermarks."""
    a = left.withWatermark("ts", late).select("user_id", F.col("event_id").alias("left_id"), F.col("ts").alias("t0"))
    b = right.withWatermark("ts", late).select(F.col("user_id").alias("other"), F.col("event_id").alias("right_id"), F.col("ts").alias("t1"))
    return a.join(b, F.expr(f"user_id = other and t1 > t0 and t1 <= t0 + interval {width}")).select("user_id", "left_id", "right_id")


def change_detector(stream: DataFrame) -> DataFrame:
    """(user_id, fp) of every delivery whose bytes differ from the user's last ones; the state is one fingerprint each."""

    def detect(key, frames, state):
        rows = sorted(f"{i}|{t}" for f in frames for i, t in zip(f["event_id"], f["event_type"], strict=True))
        fp = hashlib.md5("\n".join(rows).encode()).hexdigest()
        if not state.exists or state.get[0] != fp:
            state.update((fp,))
            yield pd.DataFrame({"user_id": [key[0]], "fp": [fp]})

    return stream.groupBy("user_id").applyInPandasWithState(detect, "user_id long, fp string", "fp string", "append", "NoTimeout")
