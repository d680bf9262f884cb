"""Experiments over sessions and sizes: greedy storage by session, the scale sweep, tiny lists, and times of real saves."""

from __future__ import annotations

import time

import pyarrow as pa
from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions.portable import C, PPM
from ..operators.store import Store
from ..operators.workspace import Workspace
from ..plans import exhaustive, planners
from ..runtime.tracker import Tracker
from ..sessions import SESSIONS, leaves, leaves_sql, states, states_sql
from ..sources.tables import read_table

QUERIES: dict = {}
ORACLES: dict = {}


def query(name: str, sql: str | None = None):
    def register(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return register


# ---------------------------------------------------------------- storage over the evaluation sessions

_EVALUATED = [s for s in SESSIONS.values() if not s.training and not s.scoped]
_DIRTY = f"coalesce(sum(bytes + {C}) filter (where dirty), 0)::bigint"


def _greedy_sql(session) -> str:
    base = leaves_sql(session)
    folded = planners.star_fold_sql(f"(select grp, node_key, s0 as size, {session.rate_ppm}::bigint as churn from {base})")
    keyed = f"(select l.*, case when list_contains(f.kept, l.node_key) then 'list:' || l.grp else l.node_key end as pk from {base} l join {folded} f using (grp))"
    return f"select '{session.name}' as session, sum(all_bytes)::bigint as snapshot_bytes, {_DIRTY} as greedy_bytes, sum(ideal)::bigint as ideal_bytes from (select step, pk, sum(size) as bytes, sum(size) as all_bytes, coalesce(sum(size) filter (where changed or step = 0), 0) as ideal, bool_or(changed or step = 0) as dirty from {states_sql(keyed)} group by 1, 2)"


@query("storage_greedy_by_session", "select *, round(snapshot_bytes / greedy_bytes, 6) as reduction from (" + " union all ".join(map(_greedy_sql, _EVALUATED)) + ")")
def storage_greedy_by_session(spark, d):
    """Bytes of the greedy store, given each session's own mutation rate, against snapshots and the ideal, over the ten evaluation sessions."""
    out = None
    for s in _EVALUATED:
        x = leaves(spark, d, s)
        members = planners.star_members(x.select("grp", "node_key", F.col("s0").alias("size"), F.lit(s.rate_ppm).cast("long").alias("churn")))
        y = states(x.select("node_key", "s0", "chg").join(members.select("node_key", F.col("parcel_key").alias("pk")), "node_key"))
        ch = F.col("changed") | (F.col("step") == 0)
        per = y.groupBy("step", "pk").agg(F.sum("size").alias("bytes"), F.sum(F.when(ch, F.col("size")).otherwise(0)).alias("ideal"), F.bool_or(ch).alias("dirty"))
        one = per.agg(F.lit(s.name).alias("session"), F.sum("bytes").alias("snapshot_bytes"), F.sum(F.when(F.col("dirty"), F.col("bytes") + C).otherwise(0)).alias("greedy_bytes"), F.sum("ideal").alias("ideal_bytes"))
        out = one if out is None else out.unionByName(one)
    return out.withColumn("reduction", F.round(F.col("snapshot_bytes") / F.col("greedy_bytes"), 6))


# ---------------------------------------------------------------- scale sweep

#: Strings of each of the hundred lists: the sweep's parameter.
LENGTHS = (1, 10, 100, 1000)
_SCALE = SESSIONS["commerce_mining"]
_SCALE_PPM = 10_000


def _scale_sql() -> str:
    parts = []
    for n in LENGTHS:
        base = f"(select * exclude (r) from (select *, row_number() over (partition by grp order by node_key) as r from {leaves_sql(_SCALE, 2, _SCALE_PPM)}) where r <= {n})"
        folded = planners.star_fold_sql(f"(select grp, node_key, s0 as size, {_SCALE_PPM}::bigint as churn from {base})")
        keyed = f"(select l.*, case when list_contains(f.kept, l.node_key) then 'list:' || l.grp else l.node_key end as pk from {base} l join {folded} f using (grp))"
        parts.append(f"select {n}::bigint as list_length, sum(n) filter (where step = 0)::bigint as n_nodes, sum(bytes)::bigint as snapshot_bytes, count(*) filter (where dirty)::bigint as n_parcels, {_DIRTY} as greedy_bytes from (select step, pk, count(*) as n, sum(size) as bytes, bool_or(changed or step = 0) as dirty from {states_sql(keyed, 2)} group by 1, 2)")
    return " union all ".join(parts)


def _scale(spark, d):
    """The first strings of every list, two states, one in a hundred strings changed."""
    base = leaves(spark, d, _SCALE, 2, _SCALE_PPM).withColumn("r", F.row_number().over(Window.partitionBy("grp").orderBy("node_key")))
    out = None
    for n in LENGTHS:
        x = base.where(F.col("r") <= n).drop("r")
        members = planners.star_members(x.select("grp", "node_key", F.col("s0").alias("size"), F.lit(_SCALE_PPM).cast("long").alias("churn")))
        y = states(x.select("node_key", "s0", "chg").join(members.select("node_key", F.col("parcel_key").alias("pk")), "node_key"), 2)
        per = y.groupBy("step", "pk").agg(F.count(F.lit(1)).alias("n"), F.sum("size").alias("bytes"), F.bool_or(F.col("changed") | (F.col("step") == 0)).alias("dirty"))
        one = per.agg(F.lit(n).cast("long").alias("list_length"), F.sum(F.when(F.col("step") == 0, F.col("n")).otherwise(0)).alias("n_nodes"), F.sum("bytes").alias("snapshot_bytes"), F.count_if("dirty").alias("n_parcels"), F.sum(F.when(F.col("dirty"), F.col("bytes") + C).otherwise(0)).alias("greedy_bytes"))
        out = one if out is None else out.unionByName(one)
    return out


@query("scale_sweep", _scale_sql())
def scale_sweep(spark, d):
    """Nodes, snapshot and greedy bytes as the lists grow."""
    return _scale(spark, d)


@query("scale_fit", f"select round(regr_slope(greedy_bytes, n_nodes), 6) as bytes_per_node, round(regr_intercept(greedy_bytes, n_nodes), 2) as fixed_bytes, round(regr_r2(greedy_bytes, n_nodes), 6) as r2 from ({_scale_sql()})")
def scale_fit(spark, d):
    """The linear law of the sweep: bytes for each node, and what a save costs besides."""
    y, x = F.col("greedy_bytes").cast("double"), F.col("n_nodes").cast("double")
    return _scale(spark, d).agg(F.round(F.regr_slope(y, x), 6).alias("bytes_per_node"), F.round(F.regr_intercept(y, x), 2).alias("fixed_bytes"), F.round(F.regr_r2(y, x), 6).alias("r2"))


@query("optimality_tiny_lists")
def optimality_tiny_lists(spark, d):
    """One-pass cost against the optimum on {1,2,3} lists of {1,2,3} strings, at most twelve decisions; tested by enumeration."""
    x = leaves(spark, d, _SCALE, 2, _SCALE_PPM).select("node_key", "s0").orderBy("node_key").limit(9).collect()  # nine strings are the workload
    rows = []
    for a in (1, 2, 3):
        for b in (1, 2, 3):
            nodes = [(0, 100, 0)]
            for i in range(a):
                nodes.append((0, 70, 0))
                at = len(nodes) - 1
                nodes += [(at, int(r[1]), _SCALE_PPM * (1 + (3 * i + j) % 9)) for j, r in enumerate(x[3 * i : 3 * i + b])]
            best, greedy = exhaustive.best_tree(nodes), exhaustive.greedy_tree(nodes)
            rows.append((a, b, len(nodes) - 1, round(best / PPM, 6), round(greedy / PPM, 6), round(best / greedy, 6)))
    return spark.createDataFrame(rows, "n_lists int, n_strings int, n_decisions int, best_cost double, greedy_cost double, optimality double")


# ---------------------------------------------------------------- saves of the store


@query("store_minimal_writes", "select * from (values (1, 0::bigint), (2, 1::bigint)) t(state, written)")
def store_minimal_writes(spark, d):
    """Parcels written by the second and third save: none for equal bytes under a second name, one for one changed row that two names hold."""
    c = read_table(spark, d, "customer")
    changed = c.withColumn("c_mktsegment", F.when(F.col("c_custkey") == 7, F.lit("NEW")).otherwise(F.col("c_mktsegment")))
    store, keys = Store(spark, Workspace(spark, "minimal").root), {"customer": ["c_custkey"], "again": ["c_custkey"]}
    store.save({"customer": c}, keys=keys)
    store.save({"customer": c, "again": c}, accessed={"again"}, keys=keys)
    store.save({"customer": changed, "again": changed}, accessed={"customer", "again"}, keys=keys)
    return store.trace().where("state > 0").groupBy("state").agg(F.sum("written").alias("written"))


@query("save_breakdown")
def save_breakdown(spark, d):
    """Share of each step of real saves: planning, serialization, and detection with writing (seconds differ from run to run)."""
    store = Store(spark, Workspace(spark, "breakdown").root)
    ns = {t: read_table(spark, d, t) for t in ("customer", "supplier")}
    store.save(ns)
    store.save(ns | {"customer": ns["customer"].where("c_custkey % 50 <> 0")}, accessed={"customer"})
    rows = [(s, step, sum(x[step] for x in state["steps"].values())) for s, state in sorted(store.states.items()) for step in ("plan", "serialize", "detect_and_write")]
    t = spark.createDataFrame(rows, "state int, step string, seconds double")
    return t.withColumn("share", F.col("seconds") / F.sum("seconds").over(Window.partitionBy("state")))


@query("tracker_overhead")
def tracker_overhead(spark, d):
    """Seconds of the same block with and without access tracking over every hundred balances of the customers, in the tasks that read them, and Welch's t of the difference."""
    code = "total = 0\nfor i in range(2000):\n    total = total + values[i % len(values)]\n"

    def timed(batches):
        for batch in batches:
            balances, out = [x or 0 for x in batch.column(0).to_pylist()], []
            for at in range(0, len(balances), 100):
                for enabled in (True, False):
                    names = {"values": balances[at : at + 100]}
                    began = time.perf_counter()
                    Tracker(enabled).run(code, names)
                    out.append((enabled, time.perf_counter() - began))
            tracked, seconds = zip(*out, strict=True) if out else ((), ())
            yield pa.RecordBatch.from_arrays([pa.array(list(tracked), pa.bool_()), pa.array(list(seconds), pa.float64())], ["tracked", "seconds"])

    t = read_table(spark, d, "customer").select("c_acctbal").mapInArrow(timed, "tracked boolean, seconds double")
    of = lambda f, on: f(F.when(F.col("tracked") == on, F.col("seconds")))
    x = t.agg(of(F.avg, True).alias("with_tracker"), of(F.avg, False).alias("without"), of(F.var_samp, True).alias("v1"), of(F.var_samp, False).alias("v0"), F.count_if("tracked").alias("n"))
    return x.select("with_tracker", "without", ((F.col("with_tracker") - F.col("without")) / F.sqrt((F.col("v1") + F.col("v0")) / F.col("n"))).alias("welch_t"))
