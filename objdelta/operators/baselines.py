"""Baselines: what each saving method writes and reads, per step, on a session's states.

Every baseline is a rule on (states, accessed variables); bytes are probe sizes, so that methods differ by what they
select and not by how they encode.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Bytes of a process image besides the namespace (a declared simulation).
RUNTIME_BYTES = 50_000_000


def full_snapshot(states: DataFrame) -> DataFrame:
    """The whole namespace each step; a load reads all of it."""
    return _rows(states, "full_snapshot", F.sum("size"), F.sum("size"))


def process_image(states: DataFrame, runtime: int = RUNTIME_BYTES) -> DataFrame:
    return _rows(states, "process_image", F.sum("size") + runtime, F.sum("size") + runtime)


def per_variable(states: DataFrame, wanted: Column) -> DataFrame:
    """Each variable alone at each step; a load reads the variables asked for."""
    return _rows(states, "per_variable", F.sum("size"), F.sum(F.when(wanted, F.col("size")).otherwise(0)))


def versioned_separate(states: DataFrame, wanted: Column, row_bytes: int = 16) -> DataFrame:
    """An object database with a path for each version: every row is written anew, sharing kept."""
    return _rows(states, "versioned_separate", F.sum(F.col("size") + row_bytes), F.sum(F.when(wanted, F.col("size") + row_bytes).otherwise(0)))


def versioned_history(states: DataFrame, wanted: Column, row_bytes: int = 16) -> DataFrame:
    """The same with one path: a past load looks through every version up to the step."""
    seen = (F.col("step") + 1) * (F.col("size") + row_bytes)
    return _rows(states, "versioned_history", F.sum(F.col("size") + row_bytes), F.sum(F.when(wanted, seen).otherwise(0)))


def selective_kinds(states: DataFrame, kinds: list[str]) -> DataFrame:
    """Manual tracking of annotated kinds: changes of other kinds are missed."""
    known = F.col("kind").isin(kinds)
    return states.where("step > 0").groupBy("step").agg(F.count_if(F.col("changed") & known).alias("n_saved"), F.count_if(F.col("changed") & ~known).alias("n_missed"))


def accessed_only(states: DataFrame, named: Column) -> DataFrame:
    """Only what was named in the code: changes through shared structure are missed."""
    return states.where("step > 0").groupBy("step").agg(F.count_if(F.col("changed") & named).alias("n_saved"), F.count_if(F.col("changed") & ~named).alias("n_missed"))


def _rows(states: DataFrame, method: str, written: Column, read: Column) -> DataFrame:
    return states.groupBy("step").agg(F.lit(method).alias("method"), written.cast("long").alias("bytes_written"), read.cast("long").alias("bytes_read"))
