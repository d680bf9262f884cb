"""Queries that once made their data up read a given table: without it they fail."""

import pytest
from pyspark.errors import AnalysisException

from objdelta import queries

READERS = ["async_ablation", "checker_confusion", "checker_quality", "figure_example_scope", "fingerprint_collision_odds", "latency_ecdf", "latency_percentiles", "op_carry_forward", "share_above_think_time", "source_python_lists", "tracker_overhead", "worked_sizes"]


@pytest.mark.parametrize("name", READERS)
def test_query_needs_its_table(name, spark, tmp_path):
    with pytest.raises(AnalysisException, match="PATH_NOT_FOUND"):
        queries.QUERIES[name](spark, str(tmp_path)).collect()


def test_checker_over_customers(spark, sf):
    assert queries.QUERIES["checker_quality"](spark, sf).first()[:2] == (spark.read.parquet(f"{sf}/customer.parquet").count(), 1.0)


def copied(spark, sf, folder, n):
    """A folder with part and supplier, every row n times."""
    for t in ("part", "supplier"):
        x = spark.read.parquet(f"{sf}/{t}.parquet")
        x.crossJoin(spark.range(n).select()).write.parquet(f"{folder}/{n}/{t}.parquet")
    return f"{folder}/{n}"


def by_method(name, spark, d):
    return {r[0]: r[1:] for r in queries.QUERIES[name](spark, d).collect()}


def test_latency_percentiles_follow_every_row(spark, sf, tmp_path):
    """Every row three times: each cell has three times the bytes, so each figure is three times as long."""
    once, thrice = (by_method("latency_percentiles", spark, d) for d in (sf, copied(spark, sf, tmp_path, 3)))
    assert {m: pytest.approx([3 * v for v in x], abs=1e-5) for m, x in once.items()} == {m: list(x) for m, x in thrice.items()}


def test_share_above_think_time_follows_every_row(spark, sf, tmp_path):
    """A list's cell grows with the copies of its rows, over one second and then over 23; the bytes grow as much."""
    once, few, many = (by_method("share_above_think_time", spark, d) for d in (sf, copied(spark, sf, tmp_path, 8), copied(spark, sf, tmp_path, 150)))
    assert [x["snapshot"][:2] for x in (once, few, many)] == [(0, 0), (0, 500), (500, 500)]
    assert all(x[m][2] == pytest.approx(n * many[m][2] / 150, abs=1e-6) for m in once for n, x in ((1, once), (8, few)))
