"""Queries of the training-data operators against their SQL on the smallest tables."""

import duckdb
import pytest

from objdelta.llm import queries


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_query_equals_sql(name, spark, sf):
    con = duckdb.connect()
    for t in ("documents", "embeddings", "pages"):
        con.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    found = con.execute(queries.ORACLES[name])
    names = [d[0] for d in found.description]
    df = queries.QUERIES[name](spark, sf)
    assert sorted(df.columns) == sorted(names)
    assert sorted(repr([r[c] for c in sorted(names)]) for r in df.collect()) == sorted(repr([dict(zip(names, r, strict=True))[c] for c in sorted(names)]) for r in found.fetchall())
