"""Readers of the given tables and of execution logs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_log(spark: SparkSession, path: str, fmt: str = "json", schema: str | None = None) -> DataFrame:
    """An execution log in csv, json, orc, text or parquet; a schema spares the inference pass."""
    reader = spark.read if schema is None else spark.read.schema(schema)
    if fmt == "csv":
        reader = reader.option("header", True)
    return reader.format(fmt).load(path)
