"""Slots: small numbers inside a parcel, global numbers across parcels, and the pages that map one to the other."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

PAGE = 64
VIRTUAL_BASE = 1 << 31
WIDE_BASE = 1 << 62


def to_virtual(local: Column, global_: Column, same_parcel: Column, base: int = VIRTUAL_BASE) -> Column:
    return F.when(same_parcel, local.cast("long")).otherwise(global_ + F.lit(base))


def to_global(virtual: Column, pages: Column, page: int = PAGE, base: int = VIRTUAL_BASE) -> Column:
    """A slot under the base lies in the parcel's pages; others are global already."""
    at = F.floor(virtual / page).cast("int")
    return F.when(virtual < base, F.get(pages, at) + F.pmod(virtual, F.lit(page))).otherwise(virtual - base)


def page_bases(members: DataFrame, page: int = PAGE, high_water: int = 0, prefix: int = 4) -> DataFrame:
    """(parcel_key, n, base): first global slot of every parcel, in key order.

    A prefix sum in two stages: totals of key prefixes are summed in one small window, then each prefix sums its own
    parcels, so that no task sees more than one prefix.
    """
    n = members.groupBy("parcel_key").agg(F.count(F.lit(1)).alias("n")).withColumn("need", F.floor((F.col("n") + page - 1) / page)).withColumn("head", F.substring("parcel_key", 1, prefix))
    heads = n.groupBy("head").agg(F.sum("need").alias("t"))
    start = heads.select("head", (F.sum("t").over(Window.orderBy("head")) - F.col("t")).alias("start"))
    own = F.sum("need").over(Window.partitionBy("head").orderBy("parcel_key")) - F.col("need")
    return n.withColumn("own", own).join(F.broadcast(start), "head").select("parcel_key", "n", (F.lit(high_water) + (F.col("start") + F.col("own")) * page).cast("long").alias("base"))


def pages(members: DataFrame, page: int = PAGE, high_water: int = 0) -> DataFrame:
    """(parcel_key, page_no, base)."""
    b = page_bases(members, page, high_water)
    return b.select("parcel_key", F.explode(F.sequence(F.lit(0), (F.floor((F.col("n") + page - 1) / page) - 1).cast("int"))).alias("page_no"), "base").select("parcel_key", "page_no", (F.col("base") + F.col("page_no") * page).cast("long").alias("base"))


def page_lists(table: DataFrame) -> DataFrame:
    """(parcel_key, pages): offsets in page order."""
    return table.groupBy("parcel_key").agg(F.transform(F.array_sort(F.collect_list(F.struct("page_no", "base"))), lambda x: x["base"]).alias("pages"))


def assign(members: DataFrame, page: int = PAGE, high_water: int = 0) -> DataFrame:
    """members (parcel_key, node_key, ordinal) with local_slot and global_slot."""
    local = members.withColumn("local_slot", (F.row_number().over(Window.partitionBy("parcel_key").orderBy("ordinal", "node_key")) - 1).cast("int"))
    return local.join(page_bases(members, page, high_water).select("parcel_key", "base"), "parcel_key").withColumn("global_slot", (F.col("base") + F.col("local_slot")).cast("long")).drop("base")
