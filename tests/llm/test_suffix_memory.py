"""Memory of op9's tasks does not grow with their bucket or filter, and the result is that of plain search."""

import tracemalloc

import numpy as np
import pytest

from objdelta.llm import bitfilter, suffix_dedup

WIDTH, GRAM = 50, 16


def merged(n, grams, seed):
    """Sorted records of n documents, as a LoserTree yields them, in random text around few grams."""
    rng = np.random.default_rng(seed)
    heads = [bytes(rng.integers(97, 123, GRAM, np.uint8)) for _ in range(grams)]
    sides = [bytes(rng.integers(97, 123, 40, np.uint8)) for _ in range(12)]
    rows = []
    for doc in range(n):
        left, right = int(rng.integers(0, 12)), int(rng.integers(0, 12))
        suffix = heads[rng.integers(grams)] + sides[rng.integers(12)][:WIDTH - GRAM] + bytes(rng.integers(97, 123, right, np.uint8))
        rows.append((suffix, (sides[rng.integers(12)][40 - left :], doc, doc % 3, 7, left + right + 1)))
    rows.sort()
    before = b""
    for suffix, payload in rows:
        yield suffix_dedup._common(before, suffix, 0), suffix, payload
        before = suffix


def by_search(records):
    """(doc, text, byte) that a window of a smaller document covers."""
    records, least, out = list(records), {}, set()
    for _, suffix, (left, doc, _text, _start, n) in records:
        for i in range(n):
            w = suffix[:GRAM], (left + suffix)[i : i + WIDTH]
            least[w] = min(doc, least.get(w, doc))
    for _, suffix, (left, doc, text, start, n) in records:
        for i in range(n):
            if least[suffix[:GRAM], (left + suffix)[i : i + WIDTH]] < doc:
                out |= {(doc, text, start + j) for j in range(i, i + WIDTH)}
    return out


@pytest.mark.parametrize(("most", "windows"), [(1 << 13, 1 << 18), (16, 1 << 18), (16, 100), (1, 50)])
@pytest.mark.parametrize("grams", [1, 40])
def test_windows_by_parts_are_those_of_plain_search(most, windows, grams):
    found = suffix_dedup.repeated_windows(merged(600, grams, 3), WIDTH, GRAM, most, windows)
    got = {(d, t, i) for part in found for d, t, a, b in zip(*(x.tolist() for x in part), strict=True) for i in range(a, b)}
    assert got == by_search(merged(600, grams, 3)) and got


def test_memory_of_a_merge_does_not_grow_with_its_bucket():
    records = list(merged(60_000, 3_000, 5))
    list(suffix_dedup.repeated_windows(iter(records[:100]), WIDTH, GRAM))
    tracemalloc.start()
    for _ in suffix_dedup.repeated_windows(iter(records), WIDTH, GRAM):
        pass
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 48 << 20


def test_workers_map_a_filter(spark):
    keys = np.random.default_rng(5).integers(-(2**63), 2**63 - 1, 40_000)
    df = spark.createDataFrame([(int(x),) for x in keys[:20_000]], "key long")
    shared = bitfilter.SharedFilter(spark, lambda head: bitfilter.build_filter(df, 18, head=head))

    def look(batches):
        import pyarrow as pa

        field = shared.field()
        for batch in batches:
            hit = bitfilter.in_filter(field, batch.column(0).to_numpy().view(np.uint64))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(hit), pa.array([isinstance(field.base, np.memmap)] * len(hit))], ["key", "hit", "mapped"])

    rows = spark.createDataFrame([(int(x),) for x in keys], "key long").mapInArrow(look, "key long, hit boolean, mapped boolean").collect()
    alone = bitfilter.build_filter(df, 18)
    want = dict(zip(keys.tolist(), bitfilter.in_filter(alone, keys.view(np.uint64)).tolist(), strict=True))
    assert all(r.mapped for r in rows) and {r.key: r.hit for r in rows} == want
    assert sum(want.values()) < 21_500
