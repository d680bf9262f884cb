"""Pivot index and components against brute force."""

import random

import numpy as np

from objdelta.llm import components, pivot_index
from objdelta.llm.common import Workspace


def test_pivot_index(spark):
    r = np.random.default_rng(4)
    base = r.normal(size=(300, 16))
    rows = []
    for i in range(700):
        x = base[r.integers(300)]
        rows.append((i * 2, (x + r.normal(size=16) * r.choice([0, 0, 0.2, 0.35])).astype(np.float32).tolist(), 1))
    rows += [(5000, None, 1), (5001, [0.0] * 16, 1), (5002, [float("nan")] * 16, 1), (5003, [], 1), (5004, [None] * 16, 1), (5005, [1.0, 2.0], 1), (5006, [2.0, 4.0], 1), (5007, [float("inf")] * 16, 1), (5008, [x * 3 for x in rows[0][1]], 1)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, n_links int")
    got = {x.vec_id: (x.n_links, x.component_id, x.kept) for x in pivot_index.near_duplicates(spark, df, per_pivot=5, block=16).collect()}
    good = [(i, np.array(v, float)) for i, v, _ in rows if v and all(x is not None and np.isfinite(x) for x in v) and any(v)]
    links = {i: set() for i, *_ in rows}
    for n, (i, a) in enumerate(good):
        for j, b in good[n + 1 :]:
            if len(a) == len(b) and a @ b / np.sqrt((a @ a) * (b @ b)) >= 0.95:
                links[i].add(j)
                links[j].add(i)
    low = {i: i for i in links}
    for _ in range(60):
        for i, js in links.items():
            for j in js:
                low[i] = low[j] = min(low[i], low[j])
    found = sum(got[i][0] for i in links) / sum(len(v) for v in links.values())
    assert 0.97 <= found <= 1  # recall of links; verified pairs only, so never above 1
    assert all(got[i][0] <= len(links[i]) for i in links)
    assert sum(got[i][1] == low[i] for i in links) / len(links) > 0.97
    assert all(got[i] == (0, i, True) for i in (5000, 5001, 5002, 5003, 5004, 5007))
    assert got[5005][0] == got[5006][0] == 1 and got[5006][1] == 5005 and got[5008][0] >= 1
    assert pivot_index.near_duplicates(spark, df.limit(0)).count() == 0


def test_components(spark):
    r = random.Random(6)
    edges = [(r.randint(0, 150), r.randint(0, 150)) for _ in range(90)] + [(1000 + i, 1001 + i) for i in range(40)] + [(2000, 3000 + i) for i in range(50)] + [(7, 7)]
    label = {x: x for e in edges for x in e}
    for _ in label:
        for a, b in edges:
            label[a] = label[b] = min(label[a], label[b])
    got = {x.node: x.component for x in components.components(Workspace(spark, "t"), spark.createDataFrame(edges, "a long, b long")).collect()}
    assert all(label[n] == c for n, c in got.items())
    assert set(got) == {x for a, b in edges if a != b for x in (a, b)}
    a, b = components.forest(np.array([5, 9, 3]), np.array([3, 5, 11]))
    assert sorted(zip(a.tolist(), b.tolist(), strict=True)) == [(5, 3), (9, 3), (11, 3)]
