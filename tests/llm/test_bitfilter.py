"""Bit filters grow with their keys: none is missed, and few others pass."""

import numpy as np

from objdelta.llm import bitfilter, suffix_dedup
from objdelta.llm.common import Workspace


def test_filter_grows_with_its_keys(spark):
    keys = np.random.default_rng(5).integers(-(2**63), 2**63 - 1, 60_000)
    bits = bitfilter.bits_for(30_000, least=14)
    assert bits == 18 and bitfilter.bits_for(10**8) == 30 and bitfilter.bits_for(10**12) == 30 and bitfilter.bits_for(0) == bitfilter.FILTER_BITS
    df = spark.createDataFrame([(int(x),) for x in keys[:30_000]], "key long")
    field = bitfilter.build_filter(df, bits, rounds=4)
    assert np.array_equal(field, bitfilter.build_filter(df, bits))
    hit = bitfilter.in_filter(field, keys.view(np.uint64))
    assert hit[:30_000].all() and hit[30_000:].mean() < 0.06


def test_small_filters_are_enlarged(spark, sf, monkeypatch):
    """From too few bits the operator comes to as many as its keys need, with the same intervals."""
    docs, sizes = spark.read.parquet(f"{sf}/documents.parquet"), []
    build = bitfilter.build_filter
    monkeypatch.setattr(suffix_dedup, "build_filter", lambda keys, bits, **more: sizes.append((keys.count(), bits)) or build(keys, bits, **more))
    found = [set(suffix_dedup.repeated_intervals(spark, docs, Workspace(spark, f"bits{b}"), filter_bits=b).collect()) for b in (13, 27)]
    assert found[0] == found[1] and all(8 * n <= 1 << bits for n, bits in sizes)
