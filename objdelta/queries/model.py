"""Object graphs of the given tables, sessions over them, and churn."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..operators import graphs
from ..plans import churn
from ..sessions import SESSIONS, STEPS, leaves, leaves_sql, states, states_sql

QUERIES: dict = {}
ORACLES: dict = {}


def query(name: str, sql: str | None = None):
    def register(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return register


@query("graph_nodes_trade", f"select kind, count(*)::bigint as n_nodes, sum(size)::bigint as total_bytes from ({graphs.TRADE_NODES_SQL}) group by kind")
def graph_nodes_trade(spark, d):
    return graphs.trade_nodes(spark, d).groupBy("kind").agg(F.count(F.lit(1)).alias("n_nodes"), F.sum("size").alias("total_bytes"))


@query("graph_refs_trade", f"select src_kind, dst_kind, count(*)::bigint as n_refs from ({graphs.TRADE_REFS_SQL}) group by 1, 2")
def graph_refs_trade(spark, d):
    return graphs.trade_refs(spark, d).groupBy("src_kind", "dst_kind").agg(F.count(F.lit(1)).alias("n_refs"))


@query("graph_shared_nodes", f"select dst_kind as kind, count(*)::bigint as n_shared, max(n)::bigint as max_in_degree from (select dst_kind, dst, count(*) as n from ({graphs.TRADE_REFS_SQL}) group by 1, 2 having count(*) > 1) group by 1")
def graph_shared_nodes(spark, d):
    degree = graphs.trade_refs(spark, d).groupBy("dst_kind", "dst").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    return degree.groupBy(F.col("dst_kind").alias("kind")).agg(F.count(F.lit(1)).alias("n_shared"), F.max("n").alias("max_in_degree"))


@query("graph_variables", f"select 'v' || var as name, count(distinct grp)::bigint as n_lists, count(*)::bigint as n_leaves, sum(s0)::bigint as total_bytes from {leaves_sql(SESSIONS['scoped_mining'])} group by var")
def graph_variables(spark, d):
    return leaves(spark, d, SESSIONS["scoped_mining"]).groupBy(F.concat(F.lit("v"), "var").alias("name")).agg(F.countDistinct("grp").alias("n_lists"), F.count(F.lit(1)).alias("n_leaves"), F.sum("s0").alias("total_bytes"))


_ALL = [s for s in SESSIONS.values()]


@query("object_counts", " union all ".join(f"select '{s.name}' as session, count(*)::bigint as n_objects, coalesce(sum(s0), 0)::bigint as total_bytes from {leaves_sql(s)}" for s in _ALL))
def object_counts(spark, d):
    parts = [leaves(spark, d, s).agg(F.lit(s.name).alias("session"), F.count(F.lit(1)).alias("n_objects"), F.coalesce(F.sum("s0"), F.lit(0)).alias("total_bytes")) for s in _ALL]
    return _union(parts)


def _union(parts):
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


@query("locality_violations", f"select step, count(*) filter (where changed and not (var = step % 10 or var = (step * 3 + 1) % 10))::bigint as n_violations from {states_sql(leaves_sql(SESSIONS['scoped_mining']))} where step > 0 group by step")
def locality_violations(spark, d):
    """Changed leaves outside the variables that the step accessed: none, by the locality of sessions."""
    x = states(leaves(spark, d, SESSIONS["scoped_mining"])).where("step > 0")
    inside = (F.col("var") == F.col("step") % 10) | (F.col("var") == (F.col("step") * 3 + 1) % 10)
    return x.groupBy("step").agg(F.count_if(F.col("changed") & ~inside).alias("n_violations"))


# ---------------------------------------------------------------- churn

_TRAIN = SESSIONS["churn_train_orders"]


@query("churn_samples", f"select kind, count(*)::bigint as exposures, count(*) filter (where changed)::bigint as changes from {states_sql(leaves_sql(_TRAIN))} where step > 0 group by kind")
def churn_samples(spark, d):
    """Label of every node and step of a training session: changed by the next step."""
    return churn.collect_samples(leaves(spark, d, _TRAIN)).groupBy("kind").agg(F.count(F.lit(1)).alias("exposures"), F.count_if("changed").alias("changes"))


_BUCKETS_SQL = "floor(log2(size))::int as size_bucket, floor(log2(length(payload) + 1))::int as len_bucket"


@query("churn_bucket_rates", f"select kind, size_bucket, len_bucket, ((sum(changed::int) + 1) * 1000000 // (count(*) + 2))::bigint as churn_ppm from (select kind, changed, {_BUCKETS_SQL} from {states_sql(leaves_sql(_TRAIN))} where step > 0) group by 1, 2, 3")
def churn_bucket_rates(spark, d):
    return churn.fit_bucket_churn(churn.collect_samples(leaves(spark, d, _TRAIN)))


@query("mutation_rate_by_step", " union all ".join(f"select '{n}' as session, step, count(*)::bigint as n_common, count(*) filter (where changed)::bigint as n_changed, (count(*) filter (where changed) * 1000000 // count(*))::bigint as rate_ppm from {states_sql(leaves_sql(SESSIONS[n]))} where step > 0 group by step" for n in ("commerce_mining", "dialogue_eda", "scoped_mining")))
def mutation_rate_by_step(spark, d):
    parts = []
    for n in ("commerce_mining", "dialogue_eda", "scoped_mining"):
        x = states(leaves(spark, d, SESSIONS[n])).where("step > 0").groupBy("step").agg(F.count(F.lit(1)).alias("n_common"), F.count_if("changed").alias("n_changed"))
        parts.append(x.select(F.lit(n).alias("session"), "step", "n_common", "n_changed", F.expr("n_changed * 1000000 div n_common").alias("rate_ppm")))
    return _union(parts)


_CLASS = "case when n_changed * 100 < 2 * n then 'under 2' when n_changed * 100 < 10 * n then '2 to 10' when n_changed * 100 <= 15 * n then '10 to 15' else 'over 15' end"


@query("mutation_class", " union all ".join(f"select '{s.name}' as session, n as n_exposed, n_changed, {_CLASS} as mutation_class from (select count(*)::bigint as n, count(*) filter (where changed)::bigint as n_changed from {states_sql(leaves_sql(s))} where step > 0)" for s in _ALL))
def mutation_class(spark, d):
    parts = []
    for s in _ALL:
        # Counted in the array of changes: no row for each state.
        x = leaves(spark, d, s).agg((F.count(F.lit(1)) * (STEPS - 1)).alias("n"), F.coalesce(F.sum(F.size("chg")), F.lit(0)).alias("n_changed"))
        parts.append(x.select(F.lit(s.name).alias("session"), F.col("n").alias("n_exposed"), "n_changed", F.expr(_CLASS).alias("mutation_class")))
    return _union(parts)


@query("cumulative_saved", f"select step, sum(n) over (order by step)::bigint as cum_snapshot, sum(k) over (order by step)::bigint as cum_delta from (select step, count(*) as n, count(*) filter (where changed or step = 0) as k from {states_sql(leaves_sql(SESSIONS['churn_train_events']))} group by step)")
def cumulative_saved(spark, d):
    x = states(leaves(spark, d, SESSIONS["churn_train_events"])).groupBy("step").agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("changed") | (F.col("step") == 0)).alias("k"))
    w = Window.orderBy("step")  # one row for each step
    return x.select("step", F.sum("n").over(w).alias("cum_snapshot"), F.sum("k").over(w).alias("cum_delta"))


def _training_samples(spark, d):
    return _union([churn.collect_samples(leaves(spark, d, s)) for s in SESSIONS.values() if s.training])


@query("churn_gbt_scores")
def churn_gbt_scores(spark, d):
    """Trees trained on the three training sessions, exported to a CASE column and applied to every evaluation session."""
    model = churn.fit_gbt_churn(_training_samples(spark, d))
    parts = []
    for s in SESSIONS.values():
        if not s.training:
            scored = churn.features(leaves(spark, d, s).withColumn("size", F.col("s0"))).withColumn("churn_ppm", model)
            parts.append(scored.groupBy(F.lit(s.name).alias("session"), "kind", "churn_ppm").agg(F.count(F.lit(1)).alias("n_nodes")))
    return _union(parts)


@query("churn_feature_profile")
def churn_feature_profile(spark, d):
    """Gain of every candidate feature over the three training sessions; the best three are kept by the churn model."""
    return churn.profile_features(_training_samples(spark, d))
