"""Queries of the engine against their SQL on tables that repeat some of their rows."""

from collections import Counter

import duckdb
import pytest

from objdelta import queries
from objdelta.operators import change

TABLES = "customer supplier part orders lineitem events documents conversations embeddings".split()


@pytest.fixture(scope="module")
def repeated(sf, tmp_path_factory):
    """(folder, connection): every table of the smallest size with its first 300 rows twice."""
    folder, con = tmp_path_factory.mktemp("repeated"), duckdb.connect()
    con.execute("set timezone = 'UTC'")
    for t in TABLES:
        con.execute(f"copy (select * from '{sf}/{t}.parquet' union all (select * from '{sf}/{t}.parquet' limit 300)) to '{folder}/{t}.parquet'")
        con.execute(f"create view {t} as select * from '{folder}/{t}.parquet'")
    return str(folder), con


@pytest.mark.parametrize("name", ["op_lateral_top", "cd_scope_ablation", "storage_by_planner", "block_delta_bytes", "new_vs_alias"])
def test_repeated_rows_equal_sql(name, spark, repeated):
    folder, con = repeated
    df = queries.QUERIES[name](spark, folder)
    found = con.execute(queries.ORACLES[name])
    at = [[x[0] for x in found.description].index(c) for c in df.columns]
    assert Counter(tuple(r) for r in df.collect()) == Counter(tuple(r[i] for i in at) for r in found.fetchall())


@pytest.mark.parametrize("name", ["cd_scope_ablation", "storage_by_planner", "new_vs_alias"])
def test_leaves_are_exchanged_once(name, spark, sf):
    """No join on the leaves, and the only exchange that sees one row for each leaf deals them out by list."""
    plan = queries.QUERIES[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan and plan.count("hashpartitioning(grp") == plan.count("MapInArrow") > 0


def test_blocks_of_a_streamed_list(spark):
    """The same blocks as of the whole texts, over lists that end inside a block, at its end, and in an empty payload."""
    rows = [("a", "x" * 7, 0), ("a", "", 1), ("a", "\u00e9" * 9, 3), ("b", "y" * 8, 0), ("c", "", 0), ("d", "z" * 30, 2)]
    df = spark.createDataFrame(rows, "grp string, payload string, mask int").coalesce(1)
    want = Counter()
    for step in range(3):
        texts = {}
        for g, p, m in rows:
            texts.setdefault(g, []).append(p + "".join(f"#{t}" for t in range(1, step + 1) if m >> (t - 1) & 1))
        whole = spark.createDataFrame([(step, "\n".join(t)) for t in texts.values()], "step int, t string")
        want += Counter(tuple(r) for r in change.blocks(whole, 8).collect())
    assert Counter(tuple(r) for r in change.list_blocks(df, 8, 3).collect()) == want
