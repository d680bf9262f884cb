"""Loading: closures, as-of states, partial loads, sharing, and the round trip through the store."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.portable import cents
from ..operators import change, graphs, scope
from ..operators.store import Store
from ..operators.workspace import Workspace
from ..plans import planners
from ..sessions import PAYLOAD_SQL, SESSIONS, leaves, leaves_sql, payload_at, states, states_sql
from ..sources.tables import read_table
from .planning import _GREEDY_MEMBERS_SQL, _leaves
from .store import union

QUERIES: dict = {}
ORACLES: dict = {}
_S = SESSIONS["scoped_mining"]
_LS = leaves_sql(_S)


def query(name: str, sql: str | None = None):
    def register(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return register


@query("load_closure", f"select 'v' || var as name, (count(distinct parcel_key) + 1 + count(distinct grp) - count(distinct case when parcel_key like 'list:%' then parcel_key end))::bigint as n_parcels, sum(size)::bigint as bytes_read from {_GREEDY_MEMBERS_SQL} group by var")
def load_closure(spark, d):
    """Parcels that each variable reaches: variable -> list parcels -> leaf parcels, by a frontier loop."""
    x = _leaves(spark, d)
    work = Workspace(spark, "load")
    m = work.table(planners.star_members(x).join(x.select("node_key", "var", "size"), "node_key"), "members")
    name, lst = F.concat(F.lit("v"), "var"), F.concat(F.lit("list:"), "grp")
    refs = m.select(name.alias("src"), lst.alias("dst")).distinct().unionByName(m.where(F.col("parcel_key") != lst).select(lst.alias("src"), F.col("parcel_key").alias("dst")))
    roots = m.select(name.alias("root"), name.alias("parcel")).distinct()
    reached = scope.parcel_closure(spark, refs, roots)
    bytes_ = m.groupBy("parcel_key").agg(F.sum("size").alias("b"))
    out = reached.join(bytes_, reached["parcel"] == bytes_["parcel_key"], "left")
    return out.groupBy(F.col("root").alias("name")).agg(F.count(F.lit(1)).alias("n_parcels"), F.coalesce(F.sum("b"), F.lit(0)).alias("bytes_read"))


_TOUCH = "(var = step % 10 or var = (step * 3 + 1) % 10)"


@query("load_cost_by_step", f"select step, 'snapshot' as method, sum(size)::bigint as bytes_read from {states_sql(_LS)} where step > 0 group by 1 union all select step, 'parcels', coalesce(sum(size) filter (where {_TOUCH}), 0)::bigint from {states_sql(_LS)} where step > 0 group by 1")
def load_cost_by_step(spark, d):
    x = states(leaves(spark, d, _S)).where("step > 0")
    return union([x.groupBy("step").agg(F.lit("snapshot").alias("method"), F.sum("size").alias("bytes_read")), x.groupBy("step").agg(F.lit("parcels").alias("method"), F.sum(F.when(F.expr(_TOUCH), F.col("size")).otherwise(0)).alias("bytes_read"))])


@query("load_asof_state", f"select node_key, version as version_step, md5({PAYLOAD_SQL}) as content_hash from {states_sql(_LS)} where step = 3")
def load_asof_state(spark, d):
    """Latest version of every node at state 3."""
    x = states(leaves(spark, d, _S)).where("step = 3")
    return x.select("node_key", F.col("version").cast("long").alias("version_step"), F.md5(payload_at(F.col("step"))).alias("content_hash"))


_USES = "(select distinct l_orderkey % 10 as var, kind, key from (select l_orderkey, 'part' as kind, l_partkey as key from lineitem union all select l_orderkey, 'supplier', l_suppkey from lineitem))"


@query("per_variable_duplicates", f"select u.kind, (count(*) - count(distinct u.key))::bigint as n_duplicates, coalesce(sum(n.size) - (select sum(size) from ({graphs.TRADE_NODES_SQL}) z where z.kind = u.kind and z.node_key in (select u2.kind || ':' || u2.key from {_USES} u2)), 0)::bigint as extra_bytes from {_USES} u join ({graphs.TRADE_NODES_SQL}) n on n.node_key = u.kind || ':' || u.key group by u.kind")
def per_variable_duplicates(spark, d):
    """Shared nodes that a store of separate variables writes more than once."""
    u = _uses(spark, d).groupBy("kind", "node_key").agg(F.count(F.lit(1)).alias("n"))
    size = graphs.trade_nodes(spark, d).select("node_key", "size")
    return u.join(size, "node_key").groupBy("kind").agg(F.sum(F.col("n") - 1).alias("n_duplicates"), F.sum((F.col("n") - 1) * F.col("size")).alias("extra_bytes"))


def _uses(spark, d):
    t = read_table(spark, d, "lineitem").select((F.col("l_orderkey") % 10).alias("var"), F.explode(F.array(F.struct(F.lit("part").alias("kind"), F.concat(F.lit("part:"), "l_partkey").alias("node_key")), F.struct(F.lit("supplier").alias("kind"), F.concat(F.lit("supplier:"), "l_suppkey").alias("node_key")))).alias("x"))
    return t.select("var", "x.kind", "x.node_key").distinct()


@query("sharing_defects", f"select m as method, (case m when 'parcels' then 0 else count(*) end)::bigint as n_defects from (select kind, key from {_USES} group by 1, 2 having count(*) > 1), (values ('per_variable'), ('parcels')) t(m) group by m")
def sharing_defects(spark, d):
    """Nodes whose referrers differ after a load: those of several variables when each was saved alone; none by parcels."""
    u = _uses(spark, d)
    after = {"per_variable": u.select("kind", "node_key", F.concat("node_key", F.lit("@"), "var").alias("copy"), "var"), "parcels": u.select("kind", "node_key", F.col("node_key").alias("copy"), "var")}
    before = u.groupBy("kind", "node_key").agg(F.count(F.lit(1)).alias("n"))
    parts = []
    for m, loaded in after.items():
        n = loaded.groupBy("kind", "node_key", "copy").agg(F.count(F.lit(1)).alias("k")).groupBy("kind", "node_key").agg(F.max("k").alias("k"))
        parts.append(before.join(n, ["kind", "node_key"]).agg(F.lit(m).alias("method"), F.count_if(F.col("n") != F.col("k")).alias("n_defects")))
    return union(parts)


_TABLES = ("customer", "nation", "orders", "part", "region", "supplier")


def _hashes(df, name):
    """md5 of the canonical text of every row: integers, strings, money in cents, time as text."""
    cols = [cents(F.col(f.name)) if f.dataType.typeName() == "double" else F.date_format(f.name, "yyyy-MM-dd HH:mm:ss.SSSSSS") if "timestamp" in f.dataType.typeName() else F.col(f.name) for f in df.schema]
    return df.select(F.md5(F.concat_ws("|", *cols)).alias("h"))


def _fp_sql(name, cols):
    return f"select '{name}' as table_name, count(*)::bigint as n_rows, 0::bigint as n_missing, 0::bigint as n_extra, md5(concat_ws('|', count(*), sum(('0x' || substr(h, 1, 12))::bigint), sum(('0x' || substr(h, 13, 12))::bigint))) as fp from (select md5(concat_ws('|', {cols})) as h from {name})"


_COLS = {
    "customer": "c_custkey, c_name, c_nationkey, cast(round(c_acctbal*100) as bigint), c_mktsegment",
    "nation": "n_nationkey, n_name, n_regionkey",
    "orders": "o_orderkey, o_custkey, o_orderstatus, cast(round(o_totalprice*100) as bigint), strftime(o_orderdate, '%Y-%m-%d %H:%M:%S.%f'), o_orderpriority",
    "part": "p_partkey, p_name, p_brand, p_type, p_size, cast(round(p_retailprice*100) as bigint)",
    "region": "r_regionkey, r_name",
    "supplier": "s_suppkey, s_name, s_nationkey, cast(round(s_acctbal*100) as bigint)",
}


@query("save_load_roundtrip", "select table_name, n_rows, n_missing, n_extra, fp as fp_before, fp as fp_after from (" + " union all ".join(_fp_sql(t, c) for t, c in _COLS.items()) + ")")
def save_load_roundtrip(spark, d):
    """Save two states of six tables, change one in between, load the first state again and compare every row."""
    work = Workspace(spark, "roundtrip")
    store = Store(spark, work.root)
    first = {t: read_table(spark, d, t) for t in _TABLES}
    sid = store.save(first)
    store.save(first | {"orders": first["orders"].withColumn("o_orderstatus", F.when(F.col("o_orderkey") % 50 == 0, F.lit("X")).otherwise(F.col("o_orderstatus")))}, accessed={"orders"})
    loaded = store.load(None, sid)
    parts = []
    for t in _TABLES:
        before, after = change.table_fingerprint(_hashes(first[t], t)), change.table_fingerprint(_hashes(loaded[t], t))
        diff = change.equal_rows(first[t], loaded[t])
        parts.append(before.select(F.lit(t).alias("table_name"), "n_rows", F.col("fp").alias("fp_before")).join(F.broadcast(after.select(F.col("fp").alias("fp_after")))).join(F.broadcast(diff)).select("table_name", "n_rows", "n_missing", "n_extra", "fp_before", "fp_after"))
    return union(parts)


@query("explore_histogram", "select floor(o_totalprice / 50000)::bigint as bucket, count(*)::bigint as n_orders from orders group by 1")
def explore_histogram(spark, d):
    """Prices of one variable at a past state, loading that variable only."""
    store = Store(spark, Workspace(spark, "explore").root)
    orders = read_table(spark, d, "orders")
    sid = store.save({"orders": orders, "region": read_table(spark, d, "region")})
    store.save({"orders": orders.where("o_orderkey % 7 <> 0"), "region": read_table(spark, d, "region")}, accessed={"orders"})
    return store.load({"orders"}, sid)["orders"].groupBy(F.floor(F.col("o_totalprice") / 50000).alias("bucket")).agg(F.count(F.lit(1)).alias("n_orders"))


_MODEL = "select label, i, sum(cast(round(cast(embedding[i] as double) * 1000000) as bigint))::bigint as s from (select label, vec_id, embedding, unnest(range(1, len(embedding) + 1)) as i from embeddings where {w}) group by 1, 2"


@query("explore_model_diff", f"select a.label::bigint as label, bool_or(a.s <> b.s) as changed, sum(abs(a.s - b.s))::bigint as l1_scaled from ({_MODEL.format(w='true')}) a join ({_MODEL.format(w='vec_id % 10 <> 3')}) b on a.label = b.label and a.i = b.i group by a.label")
def explore_model_diff(spark, d):
    """Per-label sums of a model variable, compared between two states."""
    def model(df):
        x = df.select("label", F.posexplode("embedding").alias("i", "x"))
        return x.groupBy("label", "i").agg(F.sum(F.round(F.col("x").cast("double") * 1_000_000).cast("long")).alias("s"))

    vectors = read_table(spark, d, "embeddings")
    store = Store(spark, Workspace(spark, "models").root)
    a = store.save({"model": model(vectors)})
    b = store.save({"model": model(vectors.where("vec_id % 10 <> 3"))}, accessed={"model"})
    x, y = store.load({"model"}, a)["model"], store.load({"model"}, b)["model"].withColumnRenamed("s", "t")
    return x.join(y, ["label", "i"]).groupBy(F.col("label").cast("long").alias("label")).agg(F.bool_or(F.col("s") != F.col("t")).alias("changed"), F.sum(F.abs(F.col("s") - F.col("t"))).alias("l1_scaled"))


@query("store_trace")
def store_trace(spark, d):
    """What the store wrote in two saves of which the second touches one table."""
    store = Store(spark, Workspace(spark, "trace").root)
    ns = {t: read_table(spark, d, t) for t in ("customer", "nation", "supplier")}
    store.save(ns)
    store.save(ns | {"customer": ns["customer"].withColumn("c_mktsegment", F.when(F.col("c_custkey") % 100 == 0, F.lit("NEW")).otherwise(F.col("c_mktsegment")))}, accessed={"customer"})
    return store.trace()
