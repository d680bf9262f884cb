"""The method comparisons of the store over the five sessions, and the mutation sweep over whole lists."""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions.portable import C
from ..plans import planners
from ..sessions import PROFILE_SQL, SESSIONS, leaves, leaves_sql, profile_ppm, states, states_sql

QUERIES: dict = {}
ORACLES: dict = {}

FIVE = list(SESSIONS.values())[:5]
#: The same sessions when a step changes only the two variables that it accesses.
SCOPED = [replace(s, scoped=True) for s in FIVE]
PLANNERS = ("keep_all", "split_all", "greedy")


def query(name: str, sql: str | None = None):
    def register(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return register


def union(parts):
    return reduce(lambda a, b: a.unionByName(b), parts)


# ---------------------------------------------------------------- parcels of a session


def _parcels(spark, d, session, names):
    """One row for each planner, step and parcel: n, bytes, n_changed, changed_bytes, dirty, var (a list has one variable)."""
    x = leaves(spark, d, session).withColumn("size", F.col("s0"))
    if "greedy" in names:
        members = planners.star_members(x.select("grp", "node_key", "size", profile_ppm(F.col("node_key")).cast("long").alias("churn")))
        x = x.join(members.select("node_key", F.col("parcel_key").alias("greedy")), "node_key")
    keys = F.array(*(F.struct(F.lit(p).alias("planner"), (F.col(p) if p == "greedy" else planners.policy(p)).alias("pk")) for p in names))
    y = states(x.select("node_key", "var", "s0", "chg", F.explode(keys).alias("e")).select("node_key", "var", "s0", "chg", "e.planner", "e.pk"))
    ch = F.col("changed") | (F.col("step") == 0)
    return y.groupBy("planner", "step", "pk").agg(
        F.count(F.lit(1)).alias("n"), F.sum("size").alias("bytes"), F.count_if(ch).alias("n_changed"), F.sum(F.when(ch, F.col("size")).otherwise(0)).alias("changed_bytes"), F.bool_or(ch).alias("dirty"), F.min("var").alias("var"),
    ).withColumn("session", F.lit(session.name))


def _parcels_sql(session, names) -> str:
    base, parts = leaves_sql(session), []
    for p in names:
        if p == "greedy":
            folded = planners.star_fold_sql(f"(select grp, node_key, s0 as size, ({PROFILE_SQL})::bigint as churn from {base})")
            keyed = f"(select l.*, case when list_contains(f.kept, l.node_key) then 'list:' || l.grp else l.node_key end as pk from {base} l join {folded} f using (grp))"
        else:
            keyed = f"(select *, {planners.POLICY_SQL[p].replace('size', 's0')} as pk from {base})"
        parts.append(
            f"select '{session.name}' as session, '{p}' as planner, step, pk, count(*)::bigint as n, sum(size) as bytes, count(*) filter (where changed or step = 0) as n_changed,"
            f" coalesce(sum(size) filter (where changed or step = 0), 0) as changed_bytes, bool_or(changed or step = 0) as dirty, min(var) as var from {states_sql(keyed)} group by step, pk"
        )
    return "(" + " union all ".join(parts) + ")"


def _all_sql(sessions, names) -> str:
    return "(" + " union all ".join(f"select * from {_parcels_sql(s, names)}" for s in sessions) + ")"


# ---------------------------------------------------------------- storage

_FIVE_SQL = _all_sql(FIVE, PLANNERS)
_TRACE_SQL = f"""(select session, step, planner as method, count(*) filter (where dirty)::bigint as n_units, coalesce(sum(bytes + {C}) filter (where dirty), 0)::bigint as bytes_written from {_FIVE_SQL} group by 1, 2, 3
 union all select session, step, 'snapshot', 1::bigint, sum(bytes)::bigint from {_FIVE_SQL} where planner = 'split_all' group by 1, 2
 union all select session, step, 'ideal', sum(n_changed)::bigint, sum(changed_bytes)::bigint from {_FIVE_SQL} where planner = 'split_all' group by 1, 2)"""


def _trace(spark, d):
    parts = []
    for s in FIVE:
        x = _parcels(spark, d, s, PLANNERS)
        sums = x.groupBy("session", "step", "planner").agg(F.count_if("dirty").alias("units"), F.sum(F.when(F.col("dirty"), F.col("bytes") + C).otherwise(0)).alias("written"), F.sum("bytes").alias("bytes"), F.sum("n_changed").alias("n_changed"), F.sum("changed_bytes").alias("changed_bytes"))
        # Snapshot and ideal do not depend on the parcels: they are read off the sums of one planner.
        row = lambda m, n, b: F.struct(m.alias("method"), n.cast("long").alias("n_units"), b.cast("long").alias("bytes_written"))
        own = row(F.col("planner"), F.col("units"), F.col("written"))
        more = F.array(own, row(F.lit("snapshot"), F.lit(1), F.col("bytes")), row(F.lit("ideal"), F.col("n_changed"), F.col("changed_bytes")))
        parts.append(sums.select("session", "step", F.explode(F.when(F.col("planner") == "split_all", more).otherwise(F.array(own))).alias("e")).select("session", "step", "e.*"))
    return union(parts)


@query("save_trace_by_session", f"select * from {_TRACE_SQL}")
def save_trace_by_session(spark, d):
    """Units and bytes that every save of the five sessions writes, by method."""
    return _trace(spark, d)


_BASELINES = ("snapshot", "keep_all", "split_all")


@query("storage_methods_by_session", f"""with t as (select session, method, sum(bytes_written)::bigint as total_bytes from {_TRACE_SQL} group by 1, 2),
  b as (select session, min(total_bytes) as best from t where method in {_BASELINES} group by 1) select session, method, total_bytes, round(best / total_bytes, 6) as ratio_to_best_baseline from t join b using (session)""")
def storage_methods_by_session(spark, d):
    """Total bytes by method against the smallest of snapshot, keep-all and split-all of the same session."""
    t = _trace(spark, d).groupBy("session", "method").agg(F.sum("bytes_written").alias("total_bytes"))
    best = F.min(F.when(F.col("method").isin(*_BASELINES), F.col("total_bytes"))).over(Window.partitionBy("session"))  # five rows each
    return t.select("session", "method", "total_bytes", F.round(best / F.col("total_bytes"), 6).alias("ratio_to_best_baseline"))


# ---------------------------------------------------------------- ablation of change detector and scope

_TOUCH = "(step = 0 or var = step % 10 or var = (step * 3 + 1) % 10)"
_VARIANTS = {"neither": ("true", "true"), "change_detector": ("dirty", "true"), "scope_filter": (_TOUCH, _TOUCH), "both": (f"(dirty and {_TOUCH})", _TOUCH)}


@query("ablation_by_session", " union all ".join(f"select session, '{v}' as variant, coalesce(sum(bytes + {C}) filter (where {w}), 0)::bigint as data_bytes, count(*) filter (where {m})::bigint as metadata_rows, coalesce(sum(n) filter (where {m}), 0)::bigint as encoded_nodes from {_all_sql(SCOPED, ('greedy',))} group by session" for v, (w, m) in _VARIANTS.items()))
def ablation_by_session(spark, d):
    """What the change detector and the scope filter save, apart and together, in the five sessions."""
    parts = []
    for s in SCOPED:
        x = _parcels(spark, d, s, ("greedy",))
        sums = []
        for v, (w, m) in _VARIANTS.items():
            sums.append(F.struct(F.lit(v).alias("variant"), F.sum(F.when(F.expr(w), F.col("bytes") + C).otherwise(0)).alias("data_bytes"), F.count_if(F.expr(m)).alias("metadata_rows"), F.sum(F.when(F.expr(m), F.col("n")).otherwise(0)).alias("encoded_nodes")))
        parts.append(x.groupBy("session").agg(F.array(*sums).alias("v")).select("session", F.explode("v").alias("e")).select("session", "e.*"))
    return union(parts)


# ---------------------------------------------------------------- rows of a graph store

_ROWS_SQL = _all_sql(FIVE, ("greedy",))
_OWN = "(dirty and pk not like 'list:%')"


@query("row_store_by_session", f"""select session, 'rewrite' as variant, sum(n)::bigint as node_rows, sum(n)::bigint as ref_rows, (sum(bytes) + 16 * sum(n))::bigint as bytes_written from {_ROWS_SQL} group by 1
 union all select session, 'per_node', sum(n_changed)::bigint, sum(n_changed)::bigint, (sum(changed_bytes) + 16 * sum(n_changed))::bigint from {_ROWS_SQL} group by 1
 union all select session, 'per_parcel', count(*) filter (where dirty)::bigint, count(*) filter (where {_OWN})::bigint, (coalesce(sum(bytes + {C}) filter (where dirty), 0) + 16 * count(*) filter (where {_OWN}))::bigint from {_ROWS_SQL} group by 1""")
def row_store_by_session(spark, d):
    """Graph rows and bytes that three forms of delta identification write in the five sessions."""
    parts = []
    for s in FIVE:
        x = _parcels(spark, d, s, ("greedy",))
        own = F.expr(_OWN)
        a = x.groupBy("session").agg(
            F.sum("n").alias("n"), F.sum("bytes").alias("b"), F.sum("n_changed").alias("nc"), F.sum("changed_bytes").alias("bc"), F.count_if("dirty").alias("nd"), F.count_if(own).alias("no"), F.sum(F.when(F.col("dirty"), F.col("bytes") + C).otherwise(0)).alias("bd"),
        )
        row = lambda v, n, r, b: F.struct(F.lit(v).alias("variant"), n.alias("node_rows"), r.alias("ref_rows"), b.cast("long").alias("bytes_written"))
        c = F.col
        rows = F.array(row("rewrite", c("n"), c("n"), c("b") + 16 * c("n")), row("per_node", c("nc"), c("nc"), c("bc") + 16 * c("nc")), row("per_parcel", c("nd"), c("no"), c("bd") + 16 * c("no")))
        parts.append(a.select("session", F.explode(rows).alias("e")).select("session", "e.*"))
    return union(parts)


# ---------------------------------------------------------------- mutation sweep over whole lists

#: One first state and nine more; percent of the hundred lists that a state changes, all strings of a list at once.
CELLS = 10
PERCENT = (0, 1, 5, 10, 25, 35, 50, 75, 100)
_SWEPT = SESSIONS["commerce_mining"]


def _list_changes(pct: int) -> str:
    """A list's turn moves on by 37 places a state, so that exactly pct of a hundred lists change."""
    return f"(cast(grp as bigint) + 37 * s) % 100 < {pct}"


def _sweep_sql() -> str:
    parts = []
    for pct in PERCENT:
        base = f"(select grp, node_key, s0, list_filter(range(1, {CELLS}), lambda s: {_list_changes(pct)}) as chg from {leaves_sql(_SWEPT, CELLS, 0)})"
        folded = planners.star_fold_sql(f"(select grp, node_key, s0 as size, {pct * 10_000}::bigint as churn from {base})")
        keyed = f"(select l.*, case when list_contains(f.kept, l.node_key) then 'list:' || l.grp else l.node_key end as pk from {base} l join {folded} f using (grp))"
        parts.append(
            f"select {pct}::bigint as percent, sum(bytes)::bigint as snapshot_bytes, sum(changed)::bigint as ideal_bytes, (sum(changed) + {C} * sum(n))::bigint as split_bytes, (sum(bytes + {C}) filter (where dirty))::bigint as greedy_bytes"
            f" from (select step, pk, sum(size) as bytes, coalesce(sum(size) filter (where changed or step = 0), 0) as changed, count(*) filter (where changed or step = 0) as n, bool_or(changed or step = 0) as dirty from {states_sql(keyed, CELLS)} group by 1, 2)"
        )
    return " union all ".join(parts)


@query("list_mutation_sweep", _sweep_sql())
def list_mutation_sweep(spark, d):
    """Bytes of ten states by the share of lists that each changes: from the initial size at 0 to every state in full at 100 %.

    A list's strings change together, so its sizes and parcels are sums over its leaves, and the states are rows for
    each list, not for each leaf. The greedy planner is given the swept rate.
    """
    base = leaves(spark, d, _SWEPT, 1, 0).select("grp", "node_key", F.col("s0").alias("size"))
    parts = []
    for pct in PERCENT:
        acts = planners.star_members(base.withColumn("churn", F.lit(pct * 10_000).cast("long")))
        kept = F.col("action") == planners.KEEP
        units = acts.groupBy("grp").agg((F.count_if(~kept) + F.max(kept.cast("long"))).alias("units"))
        parts.append(units.withColumn("percent", F.lit(pct).cast("long")))
    lists = base.groupBy("grp").agg(F.count(F.lit(1)).alias("n"), F.sum("size").alias("bytes"))
    x = union(parts).join(lists, "grp").withColumn("s", F.explode(F.sequence(F.lit(0), F.lit(CELLS - 1))))
    # Nine rates by ten states of a list: ninety rows for each list.
    turn = lambda s: (F.col("grp").cast("long") + 37 * s) % 100 < F.col("percent")
    times = F.size(F.filter(F.sequence(F.lit(0), F.col("s")), lambda s: (s > 0) & turn(s)))
    size, ch = F.col("bytes") + 2 * F.col("n") * times, (F.col("s") == 0) | turn(F.col("s"))
    y = x.select("percent", "n", "units", size.alias("size"), ch.alias("ch"))
    put = lambda c: F.sum(F.when(F.col("ch"), c).otherwise(0))
    return y.groupBy("percent").agg(F.sum("size").alias("snapshot_bytes"), put(F.col("size")).alias("ideal_bytes"), put(F.col("size") + C * F.col("n")).alias("split_bytes"), put(F.col("size") + C * F.col("units")).alias("greedy_bytes"))
