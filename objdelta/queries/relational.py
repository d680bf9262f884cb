"""Relational operators around the methods, one query each, named by the step that needs them."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions.portable import cents, draw
from ..sessions import SESSIONS, leaves, leaves_sql, states, states_sql
from ..sources.tables import read_table

QUERIES: dict = {}
ORACLES: dict = {}
_S = SESSIONS["scoped_mining"]
_ST = states_sql(leaves_sql(_S))
_C = "cast(round({}*100) as bigint)".format


def query(name: str, sql: str | None = None):
    def register(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return register


def _states(spark, d):
    return states(leaves(spark, d, _S))


@query("op_filter_dirty", f"select node_key, step, size from {_ST} where changed and size > 120")
def op_filter_dirty(spark, d):
    return _states(spark, d).where(F.col("changed") & (F.col("size") > 120)).select("node_key", "step", "size")


@query("op_join_alias", "select o_orderkey, n_name as nation from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey")
def op_join_alias(spark, d):
    """Small lookup sides: nation has one row for each country, so it is broadcast; customers are left to the optimizer."""
    c = read_table(spark, d, "customer").join(F.broadcast(read_table(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))
    return read_table(spark, d, "orders").join(c, F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", F.col("n_name").alias("nation"))


@query("op_join_delta", f"select coalesce(a.node_key, b.node_key) as node_key, a.version as before, b.version as after from (select * from {_ST} where step = 1) a full join (select * from {_ST} where step = 2) b on a.node_key = b.node_key where a.version is distinct from b.version")
def op_join_delta(spark, d):
    x = _states(spark, d)
    a = x.where("step = 1").select("node_key", F.col("version").cast("long").alias("before"))
    b = x.where("step = 2").select("node_key", F.col("version").cast("long").alias("after"))
    return a.join(b.hint("merge"), "node_key", "full").where(~F.col("before").eqNullSafe(F.col("after")))


@query("op_join_fp", "select l_partkey, count(*)::bigint as n from lineitem join part on l_partkey = p_partkey where p_size > 25 group by 1")
def op_join_fp(spark, d):
    return read_table(spark, d, "lineitem").join(read_table(spark, d, "part").where("p_size > 25").hint("shuffle_hash"), F.col("l_partkey") == F.col("p_partkey")).groupBy("l_partkey").agg(F.count(F.lit(1)).alias("n"))


@query("op_semi_touched", "select c_custkey from customer where exists (select 1 from orders where o_custkey = c_custkey and o_orderstatus = 'F')")
def op_semi_touched(spark, d):
    return read_table(spark, d, "customer").join(read_table(spark, d, "orders").where("o_orderstatus = 'F'"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@query("op_anti_new", "select o_orderkey from orders where not exists (select 1 from lineitem where l_orderkey = o_orderkey)")
def op_anti_new(spark, d):
    return read_table(spark, d, "orders").join(read_table(spark, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti").select("o_orderkey")


@query("op_theta_states", f"with t as (select step, sum(size)::bigint as b from {_ST} group by 1) select a.step as s1, b.step as s2, b.b - a.b as grown from t a join t b on a.step < b.step")
def op_theta_states(spark, d):
    t = _states(spark, d).groupBy("step").agg(F.sum("size").alias("b"))  # one row for each state
    return t.select(F.col("step").alias("s1"), F.col("b").alias("x")).join(F.broadcast(t.select(F.col("step").alias("s2"), F.col("b").alias("y"))), F.col("s1") < F.col("s2")).select("s1", "s2", (F.col("y") - F.col("x")).alias("grown"))


@query("op_interval_overlap", "select a.event_id as a, b.event_id as b from events a join events b on a.user_id = b.user_id and a.event_id < b.event_id and b.ts < a.ts + interval 1 hour")
def op_interval_overlap(spark, d):
    """Events of a user within an hour after another: equality on hour buckets bounds the range join."""
    e = read_table(spark, d, "events").select("event_id", "user_id", "ts")
    hour = F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 3_600_000_000)
    a = e.select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("t1"), F.explode(F.array(hour, hour + 1)).alias("h"))
    b = e.select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("t2"), hour.alias("h"))
    return a.join(b, ["user_id", "h"]).where((F.col("a") < F.col("b")) & (F.col("t2") < F.col("t1") + F.expr("interval 1 hour"))).select("a", "b")


@query("op_asof_state", "select o.event_id, (select max(i.event_id) from events i where i.user_id = o.user_id and i.event_type = 'purchase' and i.event_id <= o.event_id) as last_purchase from events o")
def op_asof_state(spark, d):
    """Latest purchase at or before every event, in one window instead of a join for each event."""
    w = Window.partitionBy("user_id").orderBy("event_id")
    return read_table(spark, d, "events").select("event_id", F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w).alias("last_purchase"))


@query("op_agg_parcel", f"select grp, sum(s0)::bigint as bytes, count(*)::bigint as n, min(s0)::bigint as smallest, max(s0)::bigint as largest, round(avg(s0), 6) as mean_bytes from {leaves_sql(_S)} group by grp")
def op_agg_parcel(spark, d):
    return leaves(spark, d, _S).groupBy("grp").agg(F.sum("s0").alias("bytes"), F.count(F.lit(1)).alias("n"), F.min("s0").alias("smallest"), F.max("s0").alias("largest"), F.round(F.avg("s0"), 6).alias("mean_bytes"))


@query("op_distinct_fp", "select count(distinct md5(text))::bigint as n_distinct, count(*)::bigint as n from documents")
def op_distinct_fp(spark, d):
    return read_table(spark, d, "documents").agg(F.countDistinct(F.md5("text")).alias("n_distinct"), F.count(F.lit(1)).alias("n"))


_G = f"(select var, step, changed, size from {_ST})"


def _cubes(kind, sql):
    @query(f"op_{kind}", f"select var, step, sum(size)::bigint as bytes, count(*) filter (where changed)::bigint as n_changed, grouping(var, step)::bigint as gid from {_G} group by {sql}")
    def run(spark, d):
        x = _states(spark, d).select("var", "step", "changed", "size")
        x.createOrReplaceTempView("objdelta_states")
        return spark.sql(f"select var, step, sum(size) as bytes, count_if(changed) as n_changed, grouping_id(var, step) as gid from objdelta_states group by {sql}")


_cubes("rollup_storage", "rollup (var, step)")
_cubes("cube_storage", "cube (var, step)")
_cubes("grouping_sets", "grouping sets ((var), (step), ())")


@query("op_pivot_planner", "select o_orderpriority, count(*) filter (where o_orderstatus = 'F')::bigint as f, count(*) filter (where o_orderstatus = 'O')::bigint as o, count(*) filter (where o_orderstatus = 'P')::bigint as p from orders group by 1")
def op_pivot_planner(spark, d):
    x = read_table(spark, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).count()
    return x.select("o_orderpriority", *(F.coalesce(c, F.lit(0)).alias(c.lower()) for c in ("F", "O", "P")))


@query("op_max_by_state", f"select grp, arg_max(node_key, s0 * 1000000000 + ('0x' || substr(node_key, 3, 6))::bigint) as largest from {leaves_sql(_S)} group by grp")
def op_max_by_state(spark, d):
    return leaves(spark, d, _S).groupBy("grp").agg(F.max_by("node_key", F.col("s0") * 1_000_000_000 + F.conv(F.substring("node_key", 3, 6), 16, 10).cast("long")).alias("largest"))


@query("op_lag_changed", f"select step, count(*) filter (where version <> before)::bigint as n_changed from (select step, version, lag(version) over (partition by node_key order by step) as before from {_ST}) group by step")
def op_lag_changed(spark, d):
    x = _states(spark, d).withColumn("before", F.lag("version").over(Window.partitionBy("node_key").orderBy("step")))
    return x.groupBy("step").agg(F.count_if(F.col("version") != F.col("before")).alias("n_changed"))


@query("op_first_writer", "select doc_id, rn = 1 as writes from (select doc_id, row_number() over (partition by md5(text) order by doc_id) as rn from documents)")
def op_first_writer(spark, d):
    """First document of every text: a combined minimum and a join rather than a window over one hot text."""
    x = read_table(spark, d, "documents").select("doc_id", F.md5("text").alias("fp"))
    return x.join(x.groupBy("fp").agg(F.min("doc_id").alias("first")), "fp").select("doc_id", (F.col("doc_id") == F.col("first")).alias("writes"))


@query("op_version_rank", f"select node_key, step, dense_rank() over (partition by node_key order by version)::int as version_no from {_ST}")
def op_version_rank(spark, d):
    return _states(spark, d).select("node_key", "step", F.dense_rank().over(Window.partitionBy("node_key").orderBy("version")).alias("version_no"))


@query("op_running_bytes", f"select var, step, sum(b) over (partition by var order by step)::bigint as running, sum(b) over (partition by var order by step rows between 1 preceding and current row)::bigint as last_two from (select var, step, sum(size) as b from {_ST} group by 1, 2)")
def op_running_bytes(spark, d):
    w = Window.partitionBy("var").orderBy("step")
    x = _states(spark, d).groupBy("var", "step").agg(F.sum("size").alias("b"))
    return x.select("var", "step", F.sum("b").over(w).alias("running"), F.sum("b").over(w.rowsBetween(-1, 0)).alias("last_two"))


@query("op_ntile_size", "select o_orderkey, ntile(4) over (partition by o_custkey order by o_orderkey)::int as quartile from orders")
def op_ntile_size(spark, d):
    return read_table(spark, d, "orders").select("o_orderkey", F.ntile(4).over(Window.partitionBy("o_custkey").orderBy("o_orderkey")).alias("quartile"))


_SUMMARIES = SESSIONS["shared_summary"]


@query("op_carry_forward", f"select node_key as name, step::int as step, max(case when step = 0 or changed then step end) over (partition by node_key order by step)::int as effective_state from {states_sql(leaves_sql(_SUMMARIES))}")
def op_carry_forward(spark, d):
    """Untouched names (parts and suppliers) keep the entry of the last state that saved them."""
    saved = F.when((F.col("step") == 0) | F.col("changed"), F.col("step"))
    return states(leaves(spark, d, _SUMMARIES)).select(F.col("node_key").alias("name"), "step", F.last(saved, ignorenulls=True).over(Window.partitionBy("node_key").orderBy("step")).alias("effective_state"))


@query("op_topk_parcels", f"select node_key, s0 from {leaves_sql(_S)} order by s0 desc, node_key limit 20")
def op_topk_parcels(spark, d):
    return leaves(spark, d, _S).orderBy(F.desc("s0"), "node_key").limit(20).select("node_key", "s0")


@query("op_topk_per_group", f"select grp, node_key, s0 from (select *, row_number() over (partition by grp order by s0 desc, node_key) as rn from {leaves_sql(_S)}) where rn <= 3")
def op_topk_per_group(spark, d):
    w = Window.partitionBy("grp").orderBy(F.desc("s0"), "node_key")
    return leaves(spark, d, _S).select("grp", "node_key", "s0", F.row_number().over(w).alias("rn")).where("rn <= 3").drop("rn")


@query("op_union_entries", "select c_nationkey as k, 'customer' as kind from customer union all select s_nationkey, 'supplier' from supplier")
def op_union_entries(spark, d):
    return read_table(spark, d, "customer").select(F.col("c_nationkey").alias("k"), F.lit("customer").alias("kind")).unionByName(read_table(spark, d, "supplier").select(F.col("s_nationkey").alias("k"), F.lit("supplier").alias("kind")))


@query("op_intersect_states", "select c_nationkey as k from customer intersect select s_nationkey from supplier")
def op_intersect_states(spark, d):
    return read_table(spark, d, "customer").select(F.col("c_nationkey").alias("k")).intersect(read_table(spark, d, "supplier").select(F.col("s_nationkey").alias("k")))


@query("op_except_delta", f"select node_key, version from {_ST} where step = 4 except select node_key, version from {_ST} where step = 3")
def op_except_delta(spark, d):
    x = _states(spark, d).select("node_key", F.col("version").cast("long").alias("version"), "step")
    return x.where("step = 4").drop("step").exceptAll(x.where("step = 3").drop("step"))


@query("op_sample_hash", "select event_id from events where ('0x' || substr(md5(event_id || '|0'), 1, 6))::bigint % 10 = 0")
def op_sample_hash(spark, d):
    """A sampling operator: one event in ten by its portable draw."""
    return read_table(spark, d, "events").where(draw(F.col("event_id").cast("string"), F.lit(0)) % 10 == 0).select("event_id")


@query("op_scalar_subquery", "select o_orderkey from orders where o_totalprice > (select avg(o_totalprice) * 2 from orders)")
def op_scalar_subquery(spark, d):
    read_table(spark, d, "orders").createOrReplaceTempView("objdelta_orders")
    return spark.sql("select o_orderkey from objdelta_orders where o_totalprice > (select avg(o_totalprice) * 2 from objdelta_orders)")


@query("op_exists", "select s_suppkey from supplier where exists (select 1 from lineitem where l_suppkey = s_suppkey and l_quantity > 49)")
def op_exists(spark, d):
    read_table(spark, d, "supplier").createOrReplaceTempView("objdelta_supplier")
    read_table(spark, d, "lineitem").createOrReplaceTempView("objdelta_lineitem")
    return spark.sql("select s_suppkey from objdelta_supplier where exists (select 1 from objdelta_lineitem where l_suppkey = s_suppkey and l_quantity > 49)")


@query("op_string_fns", "select p_partkey, upper(p_name) as u, length(p_type)::int as n, substr(p_brand, 1, 5) as b, lpad(cast(p_size as varchar), 4, '0') as z, md5(p_name) as h, concat_ws('/', p_brand, p_type) as j, string_split(p_type, ' ')[1] as first_word, replace(p_name, ' ', '_') as r from part")
def op_string_fns(spark, d):
    return read_table(spark, d, "part").select("p_partkey", F.upper("p_name").alias("u"), F.length("p_type").alias("n"), F.substring("p_brand", 1, 5).alias("b"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("z"), F.md5("p_name").alias("h"), F.concat_ws("/", "p_brand", "p_type").alias("j"), F.split("p_type", " ").getItem(0).alias("first_word"), F.replace("p_name", F.lit(" "), F.lit("_")).alias("r"))


@query("op_time_fns", "select date_trunc('day', ts)::timestamp as day, hour(ts)::int as hr, count(*)::bigint as n, max(epoch_us(ts))::bigint as last_us, max(date_diff('day', timestamp '2024-01-01', date_trunc('day', ts)))::int as days from events group by 1, 2")
def op_time_fns(spark, d):
    day = F.date_trunc("day", "ts").cast("timestamp_ntz")
    return read_table(spark, d, "events").groupBy(day.alias("day"), F.hour("ts").alias("hr")).agg(F.count(F.lit(1)).alias("n"), F.max(F.unix_micros(F.col("ts").cast("timestamp"))).alias("last_us"), F.max(F.datediff("ts", F.lit("2024-01-01"))).alias("days"))


@query("op_math_fns", f"select o_orderkey, {_C('o_totalprice')} // 1000 as q, {_C('o_totalprice')} % 1000 as r, round(sqrt(o_totalprice), 6) as s, greatest(o_custkey, o_orderkey) as g, round(ln(o_totalprice + 1), 6) as l, floor(o_totalprice / 7)::bigint as f from orders")
def op_math_fns(spark, d):
    p = F.col("o_totalprice")
    return read_table(spark, d, "orders").withColumn("c", cents(p)).select("o_orderkey", F.expr("c div 1000").alias("q"), F.pmod("c", F.lit(1000)).alias("r"), F.round(F.sqrt(p), 6).alias("s"), F.greatest("o_custkey", "o_orderkey").alias("g"), F.round(F.log(p + 1), 6).alias("l"), F.floor(p / 7).alias("f"))


@query("op_array_fns", "select vec_id, len(list_filter(embedding, lambda x: x > 0))::int as n_positive, list_sum(list_transform(embedding[1:8], lambda x: cast(round(cast(x as double) * 1000000) as bigint)))::bigint as head_sum, list_contains(list_transform(embedding, lambda x: x > 0.3), true) as any_large from embeddings")
def op_array_fns(spark, d):
    e = F.col("embedding")
    head = F.transform(F.slice(e, 1, 8), lambda x: F.round(x.cast("double") * 1_000_000).cast("long"))
    return read_table(spark, d, "embeddings").select("vec_id", F.size(F.filter(e, lambda x: x > 0)).alias("n_positive"), F.aggregate(head, F.lit(0).cast("long"), lambda a, x: a + x).alias("head_sum"), F.exists(e, lambda x: x > F.lit(0.3).cast("float")).alias("any_large"))


@query("op_map_fns", "select user_id, count(distinct event_type)::int as n_types, max(n)::bigint as most from (select user_id, event_type, count(*) as n from events group by 1, 2) group by 1")
def op_map_fns(spark, d):
    x = read_table(spark, d, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n")).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return x.select("user_id", F.size(F.map_keys("m")).alias("n_types"), F.array_max(F.map_values("m")).alias("most"))


@query("op_json_props", "select cast(json_extract_string(props, '$.k') as bigint) as k, count(*)::bigint as n from events group by 1")
def op_json_props(spark, d):
    return read_table(spark, d, "events").groupBy(F.get_json_object("props", "$.k").cast("long").alias("k")).agg(F.count(F.lit(1)).alias("n"))


@query("op_explode_lines", "select line, count(*)::bigint as n from (select unnest(string_split(text, chr(10))) as line from documents) group by line")
def op_explode_lines(spark, d):
    return read_table(spark, d, "documents").select(F.explode(F.split("text", "\n", -1)).alias("line")).groupBy("line").agg(F.count(F.lit(1)).alias("n"))


@query("op_align_by_key", "select count(*) filter (where b.k is null)::bigint as removed, count(*) filter (where a.k is null)::bigint as added, count(*) filter (where a.k is not null and b.k is not null)::bigint as kept from (select o_orderkey as k from orders where o_orderkey % 10 <> 0) a full join (select o_orderkey as k from orders where o_orderkey % 10 <> 1) b on a.k = b.k")
def op_align_by_key(spark, d):
    """Delta by key alignment: what two versions of a table add, remove and keep."""
    o = read_table(spark, d, "orders").select(F.col("o_orderkey").alias("k"))
    a, b = o.where("k % 10 <> 0").withColumn("a", F.lit(1)), o.where("k % 10 <> 1").withColumn("b", F.lit(1))
    return a.join(b, "k", "full").agg(F.count_if(F.col("b").isNull()).alias("removed"), F.count_if(F.col("a").isNull()).alias("added"), F.count_if(F.col("a").isNotNull() & F.col("b").isNotNull()).alias("kept"))
