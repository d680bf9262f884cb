"""Costs, planners, exhaustive search and stability."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.portable import C, PPM, delta_keep, delta_split
from ..operators import graphs
from ..plans import exhaustive, planners
from ..sessions import PROFILE_SQL, SESSIONS, leaves, leaves_sql, profile_ppm
from ..sources.tables import read_table

QUERIES: dict = {}
ORACLES: dict = {}
_LINES = SESSIONS["scoped_mining"]


def query(name: str, sql: str | None = None):
    def register(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return register


def _leaves(spark, d, churn=None):
    """(var, grp, node_key, size, churn) of the lines at step 0."""
    x = leaves(spark, d, _LINES)
    return x.select("var", "grp", "node_key", F.col("s0").alias("size"), (profile_ppm(F.col("node_key")) if churn is None else F.lit(churn)).cast("long").alias("churn"))


def _leaves_sql(churn=None) -> str:
    return f"(select var, grp, node_key, s0 as size, ({PROFILE_SQL if churn is None else churn})::bigint as churn from {leaves_sql(_LINES)})"


# ---------------------------------------------------------------- costs


def _cost_sql(name: str) -> str:
    return f"select '{name}' as planner, count(*)::bigint as n_parcels, round(sum({C * PPM}::hugeint + s::hugeint * l)::double / {PPM}, 6) as cost from (select {planners.POLICY_SQL[name]} as parcel_key, sum(size) as s, sum(churn) as l from {_leaves_sql()} group by 1)"


def _cost(name):
    def run(spark, d):
        members = _leaves(spark, d).withColumn("parcel_key", planners.policy(name))
        return planners.parcelling_cost(members).select(F.lit(name).alias("planner"), "n_parcels", "cost")

    return run


for _n in planners.POLICY_SQL:
    query(f"cost_{_n}", _cost_sql(_n))(_cost(_n))


@query(
    "delta_terms",
    f"with x as (select grp, node_key, size, churn, first(size) over w as ps, first(churn) over w as pl from {_leaves_sql()} window w as (partition by grp order by node_key)) "
    f"select node_key, (ps * churn + size * (pl + churn))::bigint as delta_keep, ({C * PPM} + size * churn)::bigint as delta_split, (ps * churn + size * pl < {C * PPM}) as keep_first from x",
)
def delta_terms(spark, d):
    """Both deltas of every leaf against a parcel that holds the first leaf of its list."""
    first = _leaves(spark, d).groupBy("grp").agg(F.min(F.struct("node_key", "size", "churn")).alias("f"))
    x = _leaves(spark, d).join(first, "grp")
    keep, split = delta_keep(F.col("f.size"), F.col("f.churn"), F.col("size"), F.col("churn")), delta_split(F.col("size"), F.col("churn"))
    return x.select("node_key", keep.alias("delta_keep"), split.alias("delta_split"), (keep < split).alias("keep_first"))


@query("cost_lower_bound", f"select round(({C * PPM}::hugeint + sum(size::hugeint * churn))::double / {PPM}, 6) as bound, count(*)::bigint as n_nodes from {_leaves_sql()}")
def cost_lower_bound(spark, d):
    """c + sum of s * l over nodes: no parcelling costs less."""
    return _leaves(spark, d).agg(F.round((F.sum(F.col("size") * F.col("churn")).cast("decimal(38,0)") + C * PPM).cast("double") / PPM, 6).alias("bound"), F.count(F.lit(1)).alias("n_nodes"))


_WORKED_SQL = """(select (select coalesce(sum(octet_length(encode(c_name)) + octet_length(encode(c_mktsegment)) + 24), 0)::bigint from customer) as data, (select coalesce(sum(octet_length(encode(c_name)) + octet_length(encode(c_mktsegment)) + 24) filter (where c_acctbal < 0), 0)::bigint from customer) as imputed,
  (select coalesce(sum(octet_length(encode(s_name)) + 24), 0)::bigint from supplier) as imputer, (select coalesce(sum(octet_length(encode(p_name)) + 24), 0)::bigint from part) as model)"""


@query("worked_sizes", f"select round((3 * data + 2 * imputer + 2 * model) / 1e6, 6)::double as snapshots_mb, round((data + imputer + 2 * model + imputed) / 1e6, 6)::double as delta_mb, round(data / 1e6, 6)::double as query1_mb, round((data + 3 * imputer) / 2e6, 6)::double as query2_mb, round((3 * data + 2 * imputer + 2 * model)::double / (data + imputer + 2 * model + imputed), 6)::double as ratio from {_WORKED_SQL}")
def worked_sizes(spark, d):
    """The motivating sizes in MB, on given tables: three snapshots against deltas, and what two queries load.

    The dataset is the customers, its imputed part those with a negative balance, the imputer the suppliers, the model the parts.
    """
    size = F.octet_length("c_name") + F.octet_length("c_mktsegment") + 24
    total = lambda c: F.coalesce(F.sum(c), F.lit(0)).cast("long")
    x = read_table(spark, d, "customer").agg(total(size).alias("data"), total(F.when(F.col("c_acctbal") < 0, size)).alias("imputed"))
    x = x.crossJoin(read_table(spark, d, "supplier").agg(total(F.octet_length("s_name") + 24).alias("imputer"))).crossJoin(read_table(spark, d, "part").agg(total(F.octet_length("p_name") + 24).alias("model")))  # one row each
    snap, delta = F.expr("3 * data + 2 * imputer + 2 * model"), F.expr("data + imputer + 2 * model + imputed")
    half = F.expr("data + 3 * imputer")
    return x.select(F.round(snap / 1e6, 6).alias("snapshots_mb"), F.round(delta / 1e6, 6).alias("delta_mb"), F.round(F.col("data") / 1e6, 6).alias("query1_mb"), F.round(half / 2e6, 6).alias("query2_mb"), F.round(snap / delta, 6).alias("ratio"))


# ---------------------------------------------------------------- greedy on stars

_STAR = "grp as bucket, n_keep, n_open, parcel_bytes, parcel_churn_ppm"


def _star(name, build, churn=None):
    @query(name, f"select {_STAR} from {planners.star_fold_sql(_leaves_sql(churn))}")
    def run(spark, d):
        return build(_leaves(spark, d, churn)).withColumnRenamed("grp", "bucket")

    return run


_star("greedy_star_actions", planners.star_fold)
_star("greedy_star_cutoff", planners.star_cutoff)
_star("greedy_lambda0_equals_keep", planners.star_cutoff, 0)
_star("greedy_lambda1_star", planners.star_cutoff, PPM)


def _streamed(leaves_):
    m = planners.star_members(leaves_).join(leaves_.select("node_key", "size", "churn"), "node_key")
    keep = F.col("action") == planners.KEEP
    return m.groupBy("grp").agg(
        F.count_if(keep).alias("n_keep"), F.count_if(~keep).alias("n_open"),
        (F.sum(F.when(keep, F.col("size")).otherwise(0)) + F.first(planners.list_size(F.col("grp")))).alias("parcel_bytes"), F.sum(F.when(keep, F.col("churn")).otherwise(0)).alias("parcel_churn_ppm"),
    )


_star("greedy_star_streamed", _streamed)

_GREEDY_MEMBERS_SQL = f"(select l.*, case when list_contains(f.kept, l.node_key) then 'list:' || l.grp else l.node_key end as parcel_key from {_leaves_sql()} l join {planners.star_fold_sql(_leaves_sql())} f using (grp))"


@query("greedy_parcels_summary", f"select n_nodes, count(*)::bigint as n_parcels, sum(s)::bigint as total_bytes, sum(l)::bigint as total_churn_ppm from (select parcel_key, count(*)::bigint as n_nodes, sum(size) as s, sum(churn) as l from {_GREEDY_MEMBERS_SQL} group by 1) group by 1")
def greedy_parcels_summary(spark, d):
    x = _leaves(spark, d)
    m = planners.star_members(x).select("node_key", "parcel_key").join(x, "node_key")
    return planners.parcel_costs(m).groupBy(F.col("n").alias("n_nodes")).agg(F.count(F.lit(1)).alias("n_parcels"), F.sum("s").alias("total_bytes"), F.sum("l").alias("total_churn_ppm"))


@query("bound_report")
def bound_report(spark, d):
    """Greedy cost beside the bounds that are argued for it: a measure, not a gate."""
    x = _leaves(spark, d)
    m = planners.star_members(x).select("node_key", "parcel_key").join(x, "node_key")
    g = planners.parcelling_cost(m).select(F.col("cost").alias("greedy"))
    s = planners.parcelling_cost(x.withColumn("parcel_key", planners.policy("split_all"))).select(F.col("cost").alias("split_all"))
    b = x.agg((F.sum(F.col("size") * F.col("churn")).cast("double") / PPM + C).alias("bound"), F.avg("size").alias("mean_size"), (F.avg("churn") / PPM).alias("mean_churn"))
    one = g.crossJoin(s).crossJoin(b)  # three one-row frames
    a1 = F.lit(1) + C / (F.col("mean_size") * F.col("mean_churn"))
    a2 = F.lit(1) + F.sqrt(C / (16 * F.col("mean_size") * F.col("mean_churn")))
    return one.select("greedy", "split_all", F.round("bound", 6).alias("lower_bound"), F.round(F.col("greedy") / F.col("bound"), 6).alias("ratio"), F.round(F.least(a1, a2), 6).alias("alpha"), (F.col("greedy") <= F.least(a1, a2) * F.col("bound")).alias("within"))


@query("greedy_tree_actions")
def greedy_tree_actions(spark, d):
    """Deep greedy on customer -> order -> line trees of one nation, streamed in depth-first order."""
    p = tree_preorder(spark, d)
    out = planners.tree_fold(p)
    return out.groupBy("action", "depth").agg(F.count(F.lit(1)).alias("n_nodes"), F.countDistinct("parcel_key").alias("n_parcels"))


def tree_preorder(spark, d):
    """component, path, level, node_key, size, churn: every customer's tree of orders and lines."""
    nodes = graphs.trade_nodes(spark, d)
    refs = graphs.trade_refs(spark, d)
    sized = nodes.select("node_key", "size")
    roots = nodes.where("kind = 'customer'").select(F.col("node_key").alias("component"), F.array("node_key").alias("path"), F.lit(0).alias("level"), "node_key", "size")
    orders = refs.where("dst_kind = 'order'").join(sized, F.col("dst") == F.col("node_key")).select(F.col("src").alias("component"), F.array("src", "dst").alias("path"), F.lit(1).alias("level"), "node_key", "size")
    lines = refs.where("dst_kind = 'line'").join(orders.select("component", "path", F.col("node_key").alias("src")), "src").join(sized, F.col("dst") == F.col("node_key")).select("component", F.concat("path", F.array("dst")).alias("path"), F.lit(2).alias("level"), "node_key", "size")
    return roots.unionByName(orders).unionByName(lines).withColumn("churn", profile_ppm(F.col("node_key")).cast("long"))


# ---------------------------------------------------------------- exhaustive search

_TINY = 8
_TINY_SQL = f"(select row_number() over (order by node_key) - 1 as i, size, churn from (select * from {_leaves_sql()} order by node_key limit {_TINY}))"
_MASKS = f"""(select mask, (count(*) filter (where own))::hugeint * {C * PPM} + coalesce(sum(size::hugeint * churn) filter (where own), 0)
   + {C * PPM} + (coalesce(sum(size) filter (where not own), 0) + 100)::hugeint * coalesce(sum(churn) filter (where not own), 0) as cost
  from (select mask, size, churn, (mask >> i) & 1 = 1 as own from range(0, {1 << _TINY}) r(mask), {_TINY_SQL} x) group by mask)"""


@query("exhaustive_tiny", f"select {_TINY}::bigint as n_decisions, count(*)::bigint as n_assignments, round(min(cost)::double / {PPM}, 6) as best_cost, round(max(cost)::double / {PPM}, 6) as worst_cost from {_MASKS}")
def exhaustive_tiny(spark, d):
    """Every keep/split assignment of the first leaves under one list."""
    tiny = _leaves(spark, d).orderBy("node_key").limit(_TINY)
    return exhaustive.search_star(spark, tiny, root_size=100, root_churn=0)


@query("optimality_tiny")
def optimality_tiny(spark, d):
    """Greedy cost against the optimum on stars of one list and 1 to 12 leaves (optimality_tiny_lists has the lists by leaves)."""
    rows = [(r[0], r[1]) for r in _leaves(spark, d).orderBy("node_key").limit(12).select("size", "churn").collect()]
    out = []
    for n in range(1, 13):
        best, greedy = exhaustive.best_star(rows[:n], 100, 0), exhaustive.greedy_star(rows[:n], 100, 0)
        out.append((n, round(best / PPM, 6), round(greedy / PPM, 6), round(best / greedy, 6)))
    return spark.createDataFrame(out, "n_decisions int, best_cost double, greedy_cost double, optimality double")


# ---------------------------------------------------------------- stability


def _actions(spark, d, step, memo=None):
    """Greedy actions with sizes and churn as estimated at a step."""
    x = leaves(spark, d, _LINES)
    seen = F.size(F.filter("chg", lambda s: s <= step))
    y = x.select("grp", "node_key", (F.col("s0") + 2 * seen).cast("long").alias("size"), seen.alias("k"))
    y = y.select("grp", "node_key", "size", F.expr(f"(k + 1) * {PPM} div ({step} + 2)").cast("long").alias("churn"))
    return planners.star_members(y, memo=memo)


@query("action_similarity_memo", f"select step, count(*)::bigint as n_common, count(*)::bigint as n_equal, 1.0::double as similarity from {leaves_sql(_LINES)}, range(1, 4) t(step) group by step")
def action_similarity_memo(spark, d):
    """With the memo every node keeps its first action: similarity 1."""
    first = _actions(spark, d, 0).select("node_key", "action")
    out, before = None, first
    for step in (1, 2, 3):
        now = _actions(spark, d, step, memo=first).select("node_key", F.col("action").alias("now"))
        row = before.join(now, "node_key").agg(F.lit(step).cast("long").alias("step"), F.count(F.lit(1)).alias("n_common"), F.count_if(F.col("action") == F.col("now")).alias("n_equal")).withColumn("similarity", F.round(F.col("n_equal") / F.col("n_common"), 6))
        out = row if out is None else out.unionByName(row)
    return out


def _nomemo_sql():
    def acts(step):
        base = f"(select grp, node_key, (s0 + 2 * k)::bigint as size, ((k + 1) * {PPM} // ({step} + 2))::bigint as churn from (select *, len(list_filter(chg, lambda s: s <= {step})) as k from {leaves_sql(_LINES)}))"
        return f"(select l.node_key, list_contains(f.kept, l.node_key) as keep from {base} l join {planners.star_fold_sql(base)} f using (grp))"

    return " union all ".join(f"select {t}::bigint as step, count(*)::bigint as n_common, count(*) filter (where a.keep = b.keep)::bigint as n_equal, round(count(*) filter (where a.keep = b.keep) / count(*), 6) as similarity from {acts(t - 1)} a join {acts(t)} b using (node_key)" for t in (1, 2))


@query("action_similarity_nomemo", _nomemo_sql())
def action_similarity_nomemo(spark, d):
    """Without the memo, actions follow the new sizes and rates."""
    out = None
    for step in (1, 2):
        a = _actions(spark, d, step - 1).select("node_key", "action")
        b = _actions(spark, d, step).select("node_key", F.col("action").alias("now"))
        row = a.join(b, "node_key").agg(F.lit(step).cast("long").alias("step"), F.count(F.lit(1)).alias("n_common"), F.count_if(F.col("action") == F.col("now")).alias("n_equal")).withColumn("similarity", F.round(F.col("n_equal") / F.col("n_common"), 6))
        out = row if out is None else out.unionByName(row)
    return out
