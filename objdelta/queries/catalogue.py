"""Checker cells, latency of a session's saves, and the relational operators that the methods need."""

from __future__ import annotations

import contextlib
import io
import pickle
import time

import pyarrow as pa
from pyspark.sql import Window
from pyspark.sql import functions as F

from ..operators import change
from ..runtime.readonly import is_read_only, is_read_only_sql
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


# ---------------------------------------------------------------- read-only checker

# Cells over a small namespace (rows: list of dicts, total: int, names: list of str, grid: list of lists).
READS = [
    "print(total)", "sum([total, 1])", "len(rows)", "rows[0]", "rows[0]['a']", "names[0].upper()", "sorted(names)", "max(names)", "print(len(names), total)", "total + 1", "f'{total} rows'", "names.index('x')", "rows[1:2]", "min(len(rows), 3)", "str(total)", "print(names[-1])",
    "total > 3 and len(names) == 2", "[total, total]", "{'t': total}", "(total, names)", "round(total / 3)", "abs(-total)", "isinstance(total, int)", "print('a' if total else 'b')", "names.copy()", "rows[0].get('a')", "rows[0].keys()", "', '.join(names)", "any([total, 0])", "repr(rows)",
]
HIDDEN_READS = ["[n for n in names]", "import math\nmath.sqrt(total)", "(lambda x: x)(total)", "for n in names: print(n)", "x = total", "max(names, key=len)", "list(map(str, names))", "names.__len__()", "grid[0].count(1)", "vars()"]
WRITES = [
    "names.append('z')", "rows[0]['a'] = 9", "total = 9", "names.sort()", "del rows[0]", "rows.pop()", "names += ['q']", "grid[0][0] = 7", "rows.clear()", "names.extend(['u'])", "rows[0].update(a=5)", "rows[0].setdefault('zz', 1)", "names.insert(0, 'i')", "names.reverse()", "exec('names.append(1)')", "setattr(box, 'v', 3)",
    "box.v = 4", "box.bump()", "rows.append({})", "names.remove('x')", "print(names.append('w'))", "[names.append(c) for c in 'ab']", "(total := 5)", "globals()", "rows[0].pop('a')", "names[0:1] = []", "sum([names.append(1) or 1])", "len(grid.append([]) or [])", "grid[0].append(3)", "next(iter([names.pop()]))",
]
SQLS = [
    ("SELECT 1", True), ("SELECT * FROM t WHERE a > 1", True), ("SELECT a, count(*) FROM t GROUP BY a HAVING count(*) > 1", True), ("WITH x AS (SELECT 1) SELECT * FROM x", True), ("SELECT * FROM a JOIN b ON a.i = b.i ORDER BY 1 LIMIT 3", True), ("SELECT 1 UNION ALL SELECT 2", True),
    ("INSERT INTO t VALUES (1)", False), ("DROP TABLE t", False), ("CREATE VIEW v AS SELECT 1", False), ("SET a = b", False), ("DELETE FROM t", False), ("TRUNCATE TABLE t", False), ("CREATE TABLE t (a INT)", False), ("INSERT OVERWRITE t SELECT 1", False),
]


class Box:
    def __init__(self):
        self.v = 1

    def bump(self):
        self.v += 1


def _namespace():
    return {"rows": [{"a": 1}, {"a": 2}], "total": 7, "names": ["x", "yy"], "grid": [[1, 2], [3]], "box": Box()}


def judge(code: str, ns: dict) -> tuple[bool, bool]:
    """(verdict, truth) of a cell: truth by comparing serialized bytes before and after running it."""
    verdict = is_read_only(code, ns)[0]
    before = {k: pickle.dumps(v) for k, v in ns.items()}
    run = dict(ns)
    with contextlib.redirect_stdout(io.StringIO()), contextlib.suppress(Exception):
        exec(code, {}, run)
    return verdict, run.keys() == before.keys() and all(pickle.dumps(run[k]) == before[k] for k in before)


def checker_cells(spark):
    """(cell, verdict, truth) of every cell over one fixed namespace."""
    out = [(code, *judge(code, _namespace())) for code in (*READS, *HIDDEN_READS, *WRITES)]
    return out + [(sql, is_read_only_sql(spark, sql)[0], truth) for sql, truth in SQLS]


def customer_cells(spark, d):
    """The same for the namespaces of a table: every customer's row is the namespace of one cell, in turn by key."""
    cells = (*READS, *HIDDEN_READS, *WRITES)
    sqls = [(is_read_only_sql(spark, sql)[0], truth) for sql, truth in SQLS]  # a statement needs no namespace

    def judged(batches):
        for batch in batches:
            out = []
            for key, name, nation, balance in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                i = (key or 0) % (len(cells) + len(sqls))
                ns = {"rows": [{"a": key}, {"a": balance}], "total": nation, "names": ["x", name], "grid": [[1, nation], [3]], "box": Box()}
                out.append(sqls[i - len(cells)] if i >= len(cells) else judge(cells[i], ns))
            verdict, truth = zip(*out, strict=True) if out else ((), ())
            yield pa.RecordBatch.from_arrays([pa.array(list(verdict), pa.bool_()), pa.array(list(truth), pa.bool_())], ["verdict", "truth"])

    return read_table(spark, d, "customer").select("c_custkey", "c_name", "c_nationkey", "c_acctbal").mapInArrow(judged, "verdict boolean, truth boolean")


@query("checker_confusion")
def checker_confusion(spark, d):
    return customer_cells(spark, d).groupBy("verdict", "truth").agg(F.count(F.lit(1)).alias("n"))


@query("checker_quality")
def checker_quality(spark, d):
    """Precision must be 1; recall is reported."""
    hit = F.count_if(F.col("verdict") & F.col("truth"))
    return customer_cells(spark, d).agg(F.count(F.lit(1)).alias("n_cells"), F.round(hit / F.count_if("verdict"), 6).alias("precision"), F.round(hit / F.count_if("truth"), 6).alias("recall"))


# ---------------------------------------------------------------- latency of a session's saves

#: Bytes that a save writes in a second: a declared rate, so that a save's latency is fixed by what it writes.
SAVE_RATE = 1000
_SAVED = SESSIONS["shared_summary"]
_CELLS = f"(select step, grp, sum(size)::bigint as snapshot, coalesce(sum(size) filter (where changed or step = 0), 0)::bigint as delta from {states_sql(leaves_sql(_SAVED))} group by 1, 2)"
_T = f"(select *, bytes / {SAVE_RATE}.0::double as latency_s from (select 'snapshot' as method, snapshot as bytes from {_CELLS} union all select 'delta', delta from {_CELLS}))"


def _trace(spark, d):
    """(method, bytes, latency_s): a list's save in a state is a cell, by full snapshot and by the leaves that changed."""
    x = states(leaves(spark, d, _SAVED))
    ch = F.col("changed") | (F.col("step") == 0)
    cells = x.groupBy("step", "grp").agg(F.sum("size").alias("snapshot"), F.sum(F.when(ch, F.col("size")).otherwise(0)).alias("delta"))
    return cells.unpivot([], ["snapshot", "delta"], "method", "bytes").withColumn("latency_s", F.col("bytes") / F.lit(float(SAVE_RATE)))


@query("latency_ecdf", f"select method, round(latency_s, 6) as latency_s, round(cume_dist() over (partition by method order by latency_s), 6) as fraction from {_T}")
def latency_ecdf(spark, d):
    w = Window.partitionBy("method").orderBy("latency_s")
    return _trace(spark, d).select("method", F.round("latency_s", 6).alias("latency_s"), F.round(F.cume_dist().over(w), 6).alias("fraction"))


@query("latency_percentiles", f"select method, round(quantile_cont(latency_s, 0.5), 6) as p50, round(quantile_cont(latency_s, 0.9), 6) as p90, round(avg(latency_s), 6) as mean_s, round(max(latency_s), 6) as max_s from {_T} group by method")
def latency_percentiles(spark, d):
    return _trace(spark, d).groupBy("method").agg(F.round(F.percentile("latency_s", 0.5), 6).alias("p50"), F.round(F.percentile("latency_s", 0.9), 6).alias("p90"), F.round(F.avg("latency_s"), 6).alias("mean_s"), F.round(F.max("latency_s"), 6).alias("max_s"))


@query("share_above_think_time", f"select method, count(*) filter (where latency_s > 23)::bigint as n_above_23s, count(*) filter (where latency_s > 1)::bigint as n_above_1s, round(sum(bytes)::double / 1e9, 6) as final_gb from {_T} group by method")
def share_above_think_time(spark, d):
    return _trace(spark, d).groupBy("method").agg(F.count_if(F.col("latency_s") > 23).alias("n_above_23s"), F.count_if(F.col("latency_s") > 1).alias("n_above_1s"), F.round(F.sum("bytes").cast("double") / 1e9, 6).alias("final_gb"))


@query("async_ablation")
def async_ablation(spark, d):
    """Seconds that executions wait for saves, by how saving is done (timing only). A save reads a given table whole and takes the fingerprint of its rows."""
    from ..runtime.background import BackgroundSaver, ScopeLocks

    tables = {t: read_table(spark, d, t) for t in ("customer", "part", "supplier")}

    def save(name):
        return change.table_fingerprint(tables[name].select(F.md5(F.to_json(F.struct("*"))).alias("h"))).collect()  # one row

    rows = []
    cells = [("customer", "names[0]"), ("part", "print(1)"), ("customer", "customer.append(1)"), ("part", "part.append(1)"), ("supplier", "supplier.append(1)")]
    for mode in ("synchronous", "no_checker", "no_scope_lock", "full"):
        locks = ScopeLocks("namespace" if mode == "no_scope_lock" else "scope")
        saver, waited = BackgroundSaver(locks), 0.0
        for name, code in cells:
            began = time.perf_counter()
            read_only = mode in ("full", "no_scope_lock") and is_read_only(code, {"names": [1], **{t: [] for t in tables}})[0]
            locks.access(name, read_only)
            if mode == "synchronous":
                save(name)
            elif not read_only:
                saver.submit(lambda name=name: save(name), {name})
            waited += time.perf_counter() - began
        saver.join()
        rows.append((mode, len(cells), waited))
    return spark.createDataFrame(rows, "variant string, n_cells int, waited_s double")
