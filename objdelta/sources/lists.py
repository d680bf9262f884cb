"""A Python data source of synthetic lists: `lists` lists of `length` strings, one partition for each list."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class ListPartition(InputPartition):
    def __init__(self, number: int):
        self.number = number


class ListReader(DataSourceReader):
    def __init__(self, options: dict):
        self.lists, self.length = int(options.get("lists", 3)), int(options.get("length", 3))

    def partitions(self):
        return [ListPartition(i) for i in range(self.lists)]

    def read(self, partition):
        for j in range(self.length):
            yield f"list:{partition.number}", f"string:{partition.number}:{j}", "x" * (partition.number + j)


class ListSource(DataSource):
    """spark.read.format("objdelta_lists").option("lists", a).option("length", b).load()"""

    @classmethod
    def name(cls):
        return "objdelta_lists"

    def schema(self):
        return "grp string, node_key string, payload string"

    def reader(self, schema):
        return ListReader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(ListSource)
