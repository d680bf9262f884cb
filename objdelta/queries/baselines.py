"""Baselines by step, compression, tracking baselines, and the SQL surface."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.portable import C, NODE_BYTES, PPM
from ..operators import baselines
from ..sessions import SESSIONS, leaves, leaves_sql, payload_at, states, states_sql
from ..sources import sqlsurface
from ..sources.tables import read_table
from .store import union

QUERIES: dict = {}
ORACLES: dict = {}
_S = SESSIONS["scoped_mining"]
_ST = states_sql(leaves_sql(_S))
_TOUCH = "(var = step % 10 or var = (step * 3 + 1) % 10)"


def query(name: str, sql: str | None = None):
    def register(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return register


_B = f"""select step, 'full_snapshot' as method, sum(size)::bigint as bytes_written, sum(size)::bigint as bytes_read from {_ST} group by step
 union all select step, 'process_image', sum(size)::bigint + {baselines.RUNTIME_BYTES}, sum(size)::bigint + {baselines.RUNTIME_BYTES} from {_ST} group by step
 union all select step, 'per_variable', sum(size)::bigint, coalesce(sum(size) filter (where {_TOUCH}), 0)::bigint from {_ST} group by step
 union all select step, 'versioned_separate', sum(size + 16)::bigint, coalesce(sum(size + 16) filter (where {_TOUCH}), 0)::bigint from {_ST} group by step
 union all select step, 'versioned_history', sum(size + 16)::bigint, coalesce(sum((step + 1) * (size + 16)) filter (where {_TOUCH}), 0)::bigint from {_ST} group by step"""


@query("baseline_trace", _B)
def baseline_trace(spark, d):
    x, wanted = states(leaves(spark, d, _S)), F.expr(_TOUCH)
    return union([baselines.full_snapshot(x), baselines.process_image(x), baselines.per_variable(x, wanted), baselines.versioned_separate(x, wanted), baselines.versioned_history(x, wanted)])


@query("tracking_misses", f"select step, count(*) filter (where changed and kind = 'part')::bigint as n_saved, count(*) filter (where changed and kind <> 'part')::bigint as n_missed from {states_sql(leaves_sql(SESSIONS['shared_summary']))} where step > 0 group by step")
def tracking_misses(spark, d):
    """Manual tracking of parts alone misses what changes in suppliers."""
    return baselines.selective_kinds(states(leaves(spark, d, SESSIONS["shared_summary"])), ["part"])


@query("implicit_update", f"select step, count(*) filter (where changed and var = step % 10)::bigint as n_saved, count(*) filter (where changed and var <> step % 10)::bigint as n_missed from {_ST} where step > 0 group by step")
def implicit_update(spark, d):
    """The code names one variable but changes another through shared structure: tracking of named objects misses it."""
    return baselines.accessed_only(states(leaves(spark, d, _S)), F.col("var") == F.col("step") % 10)


@query("codec_bakeoff")
def codec_bakeoff(spark, d):
    """Bytes of one session's snapshots and deltas, plain and compressed (zlib level 1), by list and step."""
    import zlib

    import pyarrow as pa

    x = states(leaves(spark, d, SESSIONS["text_labels"])).select("step", "grp", "node_key", "changed", payload_at(F.col("step")).alias("p"))
    texts = x.groupBy("step", "grp").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("node_key", "p"))), lambda e: e["p"]), "\n").alias("t"), F.bool_or(F.col("changed") | (F.col("step") == 0)).alias("dirty"))

    def run(batches):
        for b in batches:
            raw = [t.as_py().encode() for t in b.column(1)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), pa.array([len(t) for t in raw], pa.int64()), pa.array([len(zlib.compress(t, 1)) for t in raw], pa.int64())], ["step", "dirty", "plain", "packed"])

    y = texts.select("step", "t", "dirty").mapInArrow(run, "step int, dirty boolean, plain long, packed long")
    return y.groupBy("step").agg(F.sum("plain").alias("snapshot"), F.sum("packed").alias("snapshot_packed"), F.sum(F.when(F.col("dirty"), F.col("plain")).otherwise(0)).alias("delta"), F.sum(F.when(F.col("dirty"), F.col("packed")).otherwise(0)).alias("delta_packed"))


@query("op_sql_functions", f"select p_partkey, (100 * p_size + p_size * (5 + p_size))::bigint as keep_cost, ({C * PPM} + p_size * 7)::bigint as split_cost, (octet_length(encode(p_name)) + {NODE_BYTES})::bigint as probe from part")
def op_sql_functions(spark, d):
    sqlsurface.register(spark)
    read_table(spark, d, "part").createOrReplaceTempView("objdelta_part")
    return spark.sql("select p_partkey, objdelta_delta_keep(100, 5, p_size, p_size) as keep_cost, objdelta_delta_split(p_size, 7) as split_cost, objdelta_probe_size(p_name) as probe from objdelta_part")


@query("size_probe_corr", "select round(corr(probe, encoded), 6) as correlation, count(*)::bigint as n from (select octet_length(encode(text)) + 60 as probe, octet_length(encode(replace(text, ' ', '__'))) as encoded from documents)")
def size_probe_corr(spark, d):
    """Probe size against an encoded size (every separator escaped)."""
    x = read_table(spark, d, "documents").select((F.octet_length("text") + NODE_BYTES).alias("probe"), F.octet_length(F.replace("text", F.lit(" "), F.lit("__"))).alias("encoded"))
    return x.agg(F.round(F.corr("probe", "encoded"), 6).alias("correlation"), F.count(F.lit(1)).alias("n"))
