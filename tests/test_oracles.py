"""Queries of the engine against their SQL on the smallest tables."""

import math
import os

import duckdb
import pytest

import __spark_entry__ as entry
from objdelta import queries, sessions

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def plain(v):
    if v is None:
        return None
    if isinstance(v, float):
        return "nan" if math.isnan(v) else round(v, 6)
    if hasattr(v, "tzinfo"):
        return v.replace(tzinfo=None)
    return v


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    con.execute("set timezone = 'UTC'")
    for t in TABLES:
        if os.path.exists(f"{sf}/{t}.parquet"):
            con.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_query_equals_sql(name, spark, sf, duck):
    df = queries.QUERIES[name](spark, sf)
    cols = sorted(df.columns)
    got = sorted(repr([plain(r[c]) for c in cols]) for r in df.collect())
    found = duck.execute(queries.ORACLES[name])
    names = [d[0] for d in found.description]
    assert sorted(names) == cols
    want = sorted(repr([plain(dict(zip(names, r, strict=True))[c]) for c in cols]) for r in found.fetchall())
    assert [x.replace(".0,", ",").replace(".0]", "]") for x in got] == [x.replace(".0,", ",").replace(".0]", "]") for x in want]


def test_entry_has_rows(spark):
    assert entry.entry(spark).count() > 0


def test_oracles_belong_to_queries():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_planner_comparison_is_whole(duck):
    rows = duck.execute(queries.ORACLES["storage_by_planner"]).fetchall()
    assert len({r[0] for r in rows}) == 5 and len({r[1] for r in rows}) == 7 and len(rows) == 35


def test_sweep_ends_at_one_state_and_at_all(duck):
    rows = {r[0]: r[1:] for r in duck.execute(queries.ORACLES["list_mutation_sweep"]).fetchall()}
    bytes_of_lines = duck.execute("select sum(s0) from " + sessions.leaves_sql(sessions.SESSIONS["commerce_mining"])).fetchone()[0]
    assert sorted(rows) == [0, 1, 5, 10, 25, 35, 50, 75, 100]
    assert rows[0][1] == bytes_of_lines and rows[0][0] == 10 * bytes_of_lines
    assert rows[100][1] == rows[100][0]
    ideal = [rows[p][1] for p in sorted(rows)]
    assert ideal == sorted(ideal) and all(rows[p][3] <= rows[p][2] for p in rows)


def test_ablation_filters_never_add_bytes(duck):
    rows = {(s, v): (b, m) for s, v, b, m, _ in duck.execute(queries.ORACLES["ablation_by_session"]).fetchall()}
    assert len(rows) == 20
    for s in {k[0] for k in rows}:
        assert rows[s, "both"][0] == rows[s, "change_detector"][0] <= rows[s, "scope_filter"][0] <= rows[s, "neither"][0]
        assert rows[s, "both"][1] <= rows[s, "neither"][1]
