"""Workload sessions: leaves of an object graph and the deterministic changes of every step.

A session's base is a leaf table (var 0-9, grp, node_key, kind, payload); the objects above are one list node for each
grp and one variable node for each var. At step t >= 1 a leaf changes if its portable draw says so and its variable is
accessed: '#t' is appended to its payload. So every state is a projection of the base table; no state is stored to get
the next, and any step can be made alone.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions.portable import NODE_BYTES, cents, draw, draw_sql, mutates, mutates_sql, stamp
from .sources.tables import read_table

STEPS = 5


@dataclass(frozen=True)
class Session:
    name: str
    leaves: str  # builder
    rate_ppm: int
    checkpoints: int  # of the paper's session, for the full run
    scoped: bool = False  # only two variables are accessed by a step
    training: bool = False


# ---------------------------------------------------------------- leaf tables: Spark


def _line_leaves(spark, d):
    t = read_table(spark, d, "lineitem")
    row = F.concat_ws("|", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", cents(F.col("l_quantity")), cents(F.col("l_extendedprice")), cents(F.col("l_discount")), cents(F.col("l_tax")), "l_returnflag", "l_linestatus", stamp(F.col("l_shipdate")))
    b = F.col("l_orderkey") % 100
    return t.select((b / 10).cast("int").alias("var"), b.cast("string").alias("grp"), F.concat(F.lit("n:"), F.md5(row)).alias("node_key"), F.lit("line").alias("kind"), row.alias("payload"))


def _text_leaves(spark, d):
    t = read_table(spark, d, "documents").select("doc_id", F.posexplode(F.split("text", "\n", -1)).alias("i", "line"))
    return t.select((F.col("doc_id") % 10).cast("int").alias("var"), (F.col("doc_id") % 100).cast("string").alias("grp"), F.concat(F.lit("d:"), "doc_id", F.lit(":"), "i").alias("node_key"), F.lit("text").alias("kind"), F.col("line").alias("payload"))


def _turn_leaves(spark, d):
    t = read_table(spark, d, "conversations")
    return t.select((F.col("conv_id") % 10).cast("int").alias("var"), (F.col("conv_id") % 100).cast("string").alias("grp"), F.concat(F.lit("t:"), "conv_id", F.lit(":"), "turn").alias("node_key"), F.lit("turn").alias("kind"), F.concat_ws("|", "role", "text").alias("payload"))


def _vector_payload():
    return F.array_join(F.transform("embedding", lambda x: F.round(x.cast("double") * 1_000_000).cast("long").cast("string")), ",")


def _vector_leaves(spark, d):
    t = read_table(spark, d, "embeddings")
    return t.select((F.col("vec_id") % 10).cast("int").alias("var"), F.col("label").cast("string").alias("grp"), F.concat(F.lit("v:"), "vec_id").alias("node_key"), F.lit("vector").alias("kind"), _vector_payload().alias("payload"))


def _array_leaves(spark, d):
    """Few large objects: all vectors of one label and third in one array."""
    t = read_table(spark, d, "embeddings").select("label", (F.col("vec_id") % 3).alias("third"), "vec_id", _vector_payload().alias("p"))
    g = t.groupBy("label", "third").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("vec_id", "p"))), lambda x: x["p"]), ";").alias("payload"))
    return g.select((F.col("label") % 10).cast("int").alias("var"), F.col("label").cast("string").alias("grp"), F.concat(F.lit("a:"), "label", F.lit(":"), "third").alias("node_key"), F.lit("array").alias("kind"), "payload")


def _summary_leaves(spark, d):
    """Parts and suppliers as nodes of tables that share summaries."""
    p = read_table(spark, d, "part").select((F.col("p_partkey") % 10).cast("int").alias("var"), (F.col("p_partkey") % 100).cast("string").alias("grp"), F.concat(F.lit("p:"), "p_partkey").alias("node_key"), F.lit("part").alias("kind"), F.concat_ws("|", "p_name", "p_brand", "p_type", "p_size", cents(F.col("p_retailprice"))).alias("payload"))
    s = read_table(spark, d, "supplier").select((F.col("s_suppkey") % 10).cast("int").alias("var"), (F.col("s_suppkey") % 100).cast("string").alias("grp"), F.concat(F.lit("s:"), "s_suppkey").alias("node_key"), F.lit("supplier").alias("kind"), F.concat_ws("|", "s_name", "s_nationkey", cents(F.col("s_acctbal"))).alias("payload"))
    return p.unionByName(s)


def _event_rows(spark, d, training=False):
    t = read_table(spark, d, "events").where(F.col("user_id") % 5 == 0 if training else F.col("user_id") % 5 != 0)
    return t.select((F.col("user_id") % 10).cast("int").alias("var"), (F.col("user_id") % 100).cast("string").alias("grp"), F.concat(F.lit("e:"), "event_id").alias("node_key"), F.lit("event").alias("kind"), F.concat_ws("|", stamp(F.col("ts")), "event_type", cents(F.col("value")), "props").alias("payload"))


def _day_leaves(spark, d, training=False):
    t = read_table(spark, d, "events").where(F.col("user_id") % 5 == 0 if training else F.col("user_id") % 5 != 0)
    day = F.date_format("ts", "yyyy-MM-dd")
    g = t.groupBy("user_id", day.alias("day")).agg(F.sum(cents(F.col("value"))).alias("v"), F.count(F.lit(1)).alias("n"))
    return g.select((F.col("user_id") % 10).cast("int").alias("var"), (F.col("user_id") % 100).cast("string").alias("grp"), F.concat(F.lit("y:"), "user_id", F.lit(":"), "day").alias("node_key"), F.lit("day").alias("kind"), F.concat_ws("|", "n", "v").alias("payload"))


def _order_leaves(spark, d):
    t = read_table(spark, d, "orders").where(F.col("o_custkey") % 5 == 0)
    return t.select((F.col("o_custkey") % 10).cast("int").alias("var"), F.date_format("o_orderdate", "yyyy-MM").alias("grp"), F.concat(F.lit("o:"), "o_orderkey").alias("node_key"), F.lit("order").alias("kind"), F.concat_ws("|", "o_custkey", "o_orderstatus", cents(F.col("o_totalprice")), stamp(F.col("o_orderdate")), "o_orderpriority").alias("payload"))


def _token_leaves(spark, d):
    """A dictionary of words that all documents share."""
    w = read_table(spark, d, "documents").select(F.explode(F.split("text", " ", -1)).alias("w")).distinct()
    h = F.conv(F.substring(F.md5("w"), 1, 4), 16, 10).cast("long")
    return w.select((h % 10).cast("int").alias("var"), (h % 100).cast("string").alias("grp"), F.concat(F.lit("w:"), F.md5("w")).alias("node_key"), F.lit("token").alias("kind"), F.col("w").alias("payload"))


LEAVES = {
    "lines": _line_leaves, "texts": _text_leaves, "turns": _turn_leaves, "vectors": _vector_leaves, "arrays": _array_leaves, "summaries": _summary_leaves,
    "events": _event_rows, "days": _day_leaves, "tokens": _token_leaves, "orders_train": _order_leaves,
    "events_train": lambda s, d: _event_rows(s, d, True), "days_train": lambda s, d: _day_leaves(s, d, True),
}

# ---------------------------------------------------------------- leaf tables: DuckDB


def _c(x):
    return f"cast(round({x}*100) as bigint)"


def _ts(x):
    return f"strftime({x}, '%Y-%m-%d %H:%M:%S.%f')"


_LINE = f"concat_ws('|', l_orderkey, l_partkey, l_suppkey, l_linenumber, {_c('l_quantity')}, {_c('l_extendedprice')}, {_c('l_discount')}, {_c('l_tax')}, l_returnflag, l_linestatus, {_ts('l_shipdate')})"
_VEC = "list_aggregate(list_transform(embedding, lambda x: cast(cast(round(cast(x as double) * 1000000) as bigint) as varchar)), 'string_agg', ',')"


def _events_sql(where):
    return f"select (user_id % 10)::int as var, cast(user_id % 100 as varchar) as grp, 'e:' || event_id as node_key, 'event' as kind, concat_ws('|', {_ts('ts')}, event_type, {_c('value')}, props) as payload from events where {where}"


def _days_sql(where):
    return f"select (user_id % 10)::int as var, cast(user_id % 100 as varchar) as grp, 'y:' || user_id || ':' || day as node_key, 'day' as kind, concat_ws('|', n, v) as payload from (select user_id, strftime(ts, '%Y-%m-%d') as day, sum({_c('value')})::bigint as v, count(*) as n from events where {where} group by 1, 2)"


LEAVES_SQL = {
    "lines": f"select ((l_orderkey % 100) // 10)::int as var, cast(l_orderkey % 100 as varchar) as grp, 'n:' || md5({_LINE}) as node_key, 'line' as kind, {_LINE} as payload from lineitem",
    "texts": "select (doc_id % 10)::int as var, cast(doc_id % 100 as varchar) as grp, 'd:' || doc_id || ':' || (i - 1) as node_key, 'text' as kind, parts[i] as payload from (select doc_id, string_split(text, chr(10)) as parts, unnest(range(1, len(string_split(text, chr(10))) + 1)) as i from documents)",
    "turns": "select (conv_id % 10)::int as var, cast(conv_id % 100 as varchar) as grp, 't:' || conv_id || ':' || turn as node_key, 'turn' as kind, concat_ws('|', role, text) as payload from conversations",
    "vectors": f"select (vec_id % 10)::int as var, cast(label as varchar) as grp, 'v:' || vec_id as node_key, 'vector' as kind, {_VEC} as payload from embeddings",
    "arrays": f"select (label % 10)::int as var, cast(label as varchar) as grp, 'a:' || label || ':' || (vec_id % 3) as node_key, 'array' as kind, string_agg({_VEC}, ';' order by vec_id) as payload from embeddings group by label, vec_id % 3",
    "summaries": f"select (p_partkey % 10)::int as var, cast(p_partkey % 100 as varchar) as grp, 'p:' || p_partkey as node_key, 'part' as kind, concat_ws('|', p_name, p_brand, p_type, p_size, {_c('p_retailprice')}) as payload from part union all select (s_suppkey % 10)::int, cast(s_suppkey % 100 as varchar), 's:' || s_suppkey, 'supplier', concat_ws('|', s_name, s_nationkey, {_c('s_acctbal')}) from supplier",
    "events": _events_sql("user_id % 5 <> 0"),
    "events_train": _events_sql("user_id % 5 = 0"),
    "days": _days_sql("user_id % 5 <> 0"),
    "days_train": _days_sql("user_id % 5 = 0"),
    "orders_train": f"select (o_custkey % 10)::int as var, strftime(o_orderdate, '%Y-%m') as grp, 'o:' || o_orderkey as node_key, 'order' as kind, concat_ws('|', o_custkey, o_orderstatus, {_c('o_totalprice')}, {_ts('o_orderdate')}, o_orderpriority) as payload from orders where o_custkey % 5 = 0",
    "tokens": "select (h % 10)::int as var, cast(h % 100 as varchar) as grp, 'w:' || md5(w) as node_key, 'token' as kind, w as payload from (select w, ('0x' || substr(md5(w), 1, 4))::bigint as h from (select distinct unnest(string_split(text, ' ')) as w from documents))",
}

# Rates are the paper's mutation rates of the sessions that these stand in for.
SESSIONS = {
    s.name: s
    for s in (
        Session("text_labels", "texts", 17_000, 44),
        Session("dialogue_eda", "turns", 130_000, 21),
        Session("few_big_arrays", "arrays", 100_000, 15),
        Session("shared_summary", "summaries", 73_000, 28),
        Session("commerce_mining", "lines", 3_000, 41),
        Session("vector_classifier", "vectors", 67_000, 43),
        Session("replay_buffer", "events", 700_000, 256),
        Session("vector_autoenc", "vectors", 46_000, 15),
        Session("daily_series", "days", 12_000, 46),
        Session("token_dictionary", "tokens", 270_000, 83),
        Session("churn_train_events", "events_train", 61_000, 42, training=True),
        Session("churn_train_orders", "orders_train", 61_000, 38, training=True),
        Session("churn_train_users", "days_train", 61_000, 54, training=True),
        Session("scoped_mining", "lines", 73_000, 28, scoped=True),
    )
}


def accessed(step: int) -> list[int]:
    """Variables that a step of a scoped session accesses."""
    return sorted({step % 10, (3 * step + 1) % 10})


def _touches(var, step):
    return (var == step % 10) | (var == (step * 3 + 1) % 10)


def leaves(spark: SparkSession, sf_dir: str, session: Session, steps: int = STEPS, rate_ppm: int | None = None) -> DataFrame:
    """The leaf table with s0 (size at step 0) and chg (steps at which the leaf changes)."""
    rate = session.rate_ppm if rate_ppm is None else rate_ppm
    base = LEAVES[session.leaves](spark, sf_dir).where(F.col("payload").isNotNull())

    def changes(s):
        m = mutates(F.col("node_key"), s, rate)
        return _touches(F.col("var"), s) & m if session.scoped else m  # most draws are never made

    # A draw for every step is made once here; states below only look into the array.
    return base.withColumn("s0", (F.octet_length("payload") + NODE_BYTES).cast("long")).withColumn("chg", F.filter(F.sequence(F.lit(1), F.lit(steps - 1)), changes))


def leaves_sql(session: Session, steps: int = STEPS, rate_ppm: int | None = None) -> str:
    rate = session.rate_ppm if rate_ppm is None else rate_ppm
    m = mutates_sql("node_key", "s", rate) + (" and (var = s % 10 or var = (s * 3 + 1) % 10)" if session.scoped else "")
    return f"(select *, octet_length(encode(payload))::bigint + {NODE_BYTES} as s0, list_filter(range(1, {steps}), lambda s: {m}) as chg from ({LEAVES_SQL[session.leaves]}) where payload is not null)"


def change_mask():
    """The steps at which a leaf changes as bits: bit t - 1 for step t."""
    return F.aggregate("chg", F.lit(0), lambda m, s: m + F.pow(F.lit(2), s - 1).cast("int"))


def star_leaves(spark: SparkSession, sf_dir: str, session: Session, steps: int = STEPS, **more) -> DataFrame:
    """(grp, node_key, var, size, mask, profile, and more columns of the leaf) for one exchange: the changes as bits, and the key of a line as the 16 bytes of its digits, in the same order."""
    x = leaves(spark, sf_dir, session, steps).withColumn("size", F.col("s0"))
    key = F.unhex(F.substring("node_key", 3, 32)) if session.leaves == "lines" else F.col("node_key")
    return x.select("grp", key.alias("node_key"), "var", "size", change_mask().alias("mask"), profile_ppm(F.col("node_key")).cast("int").alias("profile"), *(c.alias(n) for n, c in more.items()))


def size_at(step):
    """Bytes of a leaf in the state after `step` (steps have one digit here)."""
    return F.col("s0") + F.size(F.filter("chg", lambda s: s <= step)) * 2


def states(base: DataFrame, steps: int = STEPS) -> DataFrame:
    """One row for each leaf and step: changed, size."""
    x = base.withColumn("step", F.explode(F.sequence(F.lit(0), F.lit(steps - 1))))
    return x.withColumn("changed", F.array_contains("chg", F.col("step"))).withColumn("size", size_at(F.col("step")).cast("long")).withColumn("version", F.coalesce(F.array_max(F.filter("chg", lambda s: s <= F.col("step"))), F.lit(0)))


def states_sql(base: str, steps: int = STEPS) -> str:
    return f"(select *, list_contains(chg, step) as changed, s0 + 2 * len(list_filter(chg, lambda s: s <= step)) as size, coalesce(list_max(list_filter(chg, lambda s: s <= step)), 0) as version from (select *, unnest(range(0, {steps})) as step from {base}))"


def payload_at(step):
    """Payload of a leaf in the state after `step`."""
    return F.concat("payload", F.array_join(F.transform(F.filter("chg", lambda s: s <= step), lambda s: F.concat(F.lit("#"), s.cast("string"))), ""))


PAYLOAD_SQL = "payload || coalesce(list_aggregate(list_transform(list_filter(chg, lambda s: s <= step), lambda s: '#' || s), 'string_agg', ''), '')"


def profile_ppm(key):
    """A fixed churn profile for planner tests: 1 000 ... 50 000 ppm by key."""
    return (1 + draw(key, F.lit(0)) % 50) * 1000


PROFILE_SQL = f"(1 + {draw_sql('node_key', '0')} % 50) * 1000"
