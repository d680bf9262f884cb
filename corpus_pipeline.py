"""Corpus pipeline: documents go through toxicity, line dedup, near-duplicate removal, decontamination and packing.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame, which is written as Parquet and read back as the next
stage's docs. All but the last return the columns of documents.
"""

from __future__ import annotations

import functools

from pyspark.sql import DataFrame, SparkSession

from objdelta.llm import decontaminate, jaccard_join, line_dedup, packing, toxicity
from objdelta.llm.common import Workspace, read_table

STAGES = [
    ("toxicity", toxicity.stage),
    ("line_dedup", line_dedup.stage),
    ("jaccard_join", functools.partial(jaccard_join.stage, keep_empty=False)),  # line dedup empties exact copies
    ("decontamination", decontaminate.stage),
    ("packing", packing.stage),
]

#: Scores, tilings and token ids have no SQL form: the stages are tested against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The packed pieces of what is left of sf_dir's documents."""
    work = Workspace(spark, "pipeline")
    docs, before = read_table(spark, sf_dir, "documents"), None
    for name, stage in STAGES:
        docs = work.table(stage(spark, docs, sf_dir), name)
        if before:
            work.drop(before)
        before = name
    return docs
