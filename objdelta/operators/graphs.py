"""Graph builders: node and reference tables of the given tables, as unions of projections."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.portable import NODE_BYTES, cents, stamp
from ..sessions import _LINE, _c, _ts
from ..sources.tables import read_table

# kind, table, key, payload columns (Spark), payload (SQL), references (column -> kind)
_M = lambda c: f"cast(round({c} * 100) as bigint)"
_TRADE = [
    ("region", "region", "r_regionkey", ["r_name"], "r_name", {}),
    ("nation", "nation", "n_nationkey", ["n_name", "n_regionkey"], "concat_ws('|', n_name, n_regionkey)", {}),
    ("customer", "customer", "c_custkey", ["c_name", "c_nationkey", _M("c_acctbal"), "c_mktsegment"], f"concat_ws('|', c_name, c_nationkey, {_c('c_acctbal')}, c_mktsegment)", {}),
    ("supplier", "supplier", "s_suppkey", ["s_name", "s_nationkey", _M("s_acctbal")], f"concat_ws('|', s_name, s_nationkey, {_c('s_acctbal')})", {"s_nationkey": "nation"}),
    ("part", "part", "p_partkey", ["p_name", "p_brand", "p_type", "p_size", _M("p_retailprice")], f"concat_ws('|', p_name, p_brand, p_type, p_size, {_c('p_retailprice')})", {}),
    ("order", "orders", "o_orderkey", ["o_custkey", "o_orderstatus", _M("o_totalprice"), "date_format(o_orderdate, 'yyyy-MM-dd HH:mm:ss.SSSSSS')", "o_orderpriority"], f"concat_ws('|', o_custkey, o_orderstatus, {_c('o_totalprice')}, {_ts('o_orderdate')}, o_orderpriority)", {}),
]
# Containment goes from parent to child; shared references go from lines and suppliers.
_CONTAINS = [("region", "nation", "nation", "n_regionkey", "n_nationkey"), ("nation", "customer", "customer", "c_nationkey", "c_custkey"), ("customer", "order", "orders", "o_custkey", "o_orderkey")]


def line_payload():
    return F.concat_ws("|", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", *(cents(F.col(c)) for c in ("l_quantity", "l_extendedprice", "l_discount", "l_tax")), "l_returnflag", "l_linestatus", stamp(F.col("l_shipdate")))


def trade_nodes(spark: SparkSession, d: str) -> DataFrame:
    """(kind, node_key, payload, size) of the seven tables."""
    out = None
    for kind, table, key, cols, _, _ in _TRADE:
        x = read_table(spark, d, table).select(F.lit(kind).alias("kind"), F.concat(F.lit(kind + ":"), key).alias("node_key"), F.concat_ws("|", *map(F.expr, cols)).alias("payload"))
        out = x if out is None else out.unionByName(x)
    lines = read_table(spark, d, "lineitem").select(F.lit("line").alias("kind"), F.concat(F.lit("line:"), F.md5(line_payload())).alias("node_key"), line_payload().alias("payload"))
    return out.unionByName(lines).withColumn("size", (F.octet_length("payload") + NODE_BYTES).cast("long"))


TRADE_NODES_SQL = (
    "select *, octet_length(encode(payload))::bigint + " + str(NODE_BYTES) + " as size from ("
    + " union all ".join(f"select '{kind}' as kind, '{kind}:' || {key} as node_key, {sql} as payload from {table}" for kind, table, key, _, sql, _ in _TRADE)
    + f" union all select 'line', 'line:' || md5({_LINE}), {_LINE} from lineitem)"
)


def trade_refs(spark: SparkSession, d: str) -> DataFrame:
    """(src_kind, src, dst_kind, dst): containment down to lines, and shared parts, suppliers and nations."""
    out = None

    def add(x):
        nonlocal out
        out = x if out is None else out.unionByName(x)

    for src, dst, table, fk, key in _CONTAINS:
        add(read_table(spark, d, table).select(F.lit(src).alias("src_kind"), F.concat(F.lit(src + ":"), fk).alias("src"), F.lit(dst).alias("dst_kind"), F.concat(F.lit(dst + ":"), key).alias("dst")))
    add(read_table(spark, d, "supplier").select(F.lit("supplier").alias("src_kind"), F.concat(F.lit("supplier:"), "s_suppkey").alias("src"), F.lit("nation").alias("dst_kind"), F.concat(F.lit("nation:"), "s_nationkey").alias("dst")))
    # One scan of the lines gives their three references.
    key = F.concat(F.lit("line:"), F.md5(line_payload()))
    refs = F.array(
        F.struct(F.lit("order").alias("src_kind"), F.concat(F.lit("order:"), "l_orderkey").alias("src"), F.lit("line").alias("dst_kind"), F.col("line").alias("dst")),
        F.struct(F.lit("line").alias("src_kind"), F.col("line").alias("src"), F.lit("part").alias("dst_kind"), F.concat(F.lit("part:"), "l_partkey").alias("dst")),
        F.struct(F.lit("line").alias("src_kind"), F.col("line").alias("src"), F.lit("supplier").alias("dst_kind"), F.concat(F.lit("supplier:"), "l_suppkey").alias("dst")),
    )
    add(read_table(spark, d, "lineitem").withColumn("line", key).select(F.inline(refs)))
    return out


TRADE_REFS_SQL = (
    " union all ".join(f"select '{src}' as src_kind, '{src}:' || {fk} as src, '{dst}' as dst_kind, '{dst}:' || {key} as dst from {table}" for src, dst, table, fk, key in _CONTAINS)
    + " union all select 'supplier', 'supplier:' || s_suppkey, 'nation', 'nation:' || s_nationkey from supplier"
    + "".join(f" union all select {cols} from (select *, 'line:' || md5({_LINE}) as line from lineitem)" for cols in ("'order', 'order:' || l_orderkey, 'line', line", "'line', line, 'part', 'part:' || l_partkey", "'line', line, 'supplier', 'supplier:' || l_suppkey"))
)

# The example of five variables and nine nodes, with a shared node and a self-loop.
FIGURE_VARIABLES = [("fig", "u1"), ("ax", "u3"), ("dataset", "u7"), ("trainer", "u6"), ("model", "u8")]
FIGURE_REFS = [("u1", "u2"), ("u1", "u3"), ("u3", "u4"), ("u3", "u5"), ("u6", "u7"), ("u6", "u8"), ("u7", "u9"), ("u8", "u9"), ("u8", "u8")]
