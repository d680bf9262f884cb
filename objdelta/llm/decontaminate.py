"""Benchmark decontamination by greedy string tiling with Karp-Rabin seeds.

Documents and items are token sequences (ASCII lower-cased, punctuation left out). Rolling hashes of `min_tile`
tokens are joined; runs of joined seeds on one diagonal are the maximal matches of a document and an item. Tiling
then marks the longest match whose tokens are free on both sides, again and again, so that moved and swapped parts
of an item all count once. A document is contaminated by an item when the marked share of the item's tokens
reaches `min_cover`.

The item index is shipped to every task while the benchmark has at most `max_tokens` tokens (checked); beyond
that, seeds are joined as a table and only the candidate pairs meet. Rows meet by a hash of doc_id and text there, items
by a hash of item_id and text, so null and shared ids give the same result on both ways.

Defined cases: null and empty texts match nothing; an item with fewer tokens than `min_tile` must occur whole; rows
without doc_id are checked like others; equal rows give equal rows (distinct pairs); an empty benchmark leaves
every document; further columns pass through `clean` unchanged.
"""

from __future__ import annotations

import heapq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import PUNCT, chunks, mix, read_table, text_buffers, word_hashes

MIN_TILE, MIN_COVER, MAX_TOKENS = 5, 0.75, 2_000_000
SCHEMA = "doc_id long, item_id long, n_tiles int, matched_tokens int, item_tokens int, coverage double"
_STEP = np.uint64(0x9FB21C651E98DF25)


def grams(words: np.ndarray, k: int) -> np.ndarray:
    """Hash of every k consecutive tokens."""
    out = np.zeros(max(0, len(words) - k + 1), np.uint64)
    for j in range(k):
        out = out * _STEP + words[j : j + len(out)]
    return mix(out + np.uint64(k))


def tile(doc: np.ndarray, item: np.ndarray, pairs: list[tuple[int, int]], k: int) -> tuple[int, int]:
    """(tiles, marked tokens) of greedy tiling; pairs: positions where k tokens of doc and item agree."""
    runs: list[tuple[int, int, int]] = []
    by_diagonal: dict[int, list[int]] = {}
    for i, j in pairs:
        by_diagonal.setdefault(i - j, []).append(i)
    for d, at in by_diagonal.items():
        at.sort()
        begin = prev = at[0]
        for i in [*at[1:], None]:
            if i is None or i != prev + 1:
                runs.append((-(prev - begin + k), begin, begin - d))
                begin = i
            prev = i
    heapq.heapify(runs)
    used_doc: set[int] = set()
    used_item = bytearray(len(item))
    tiles = marked = 0
    while runs:
        length, i, j = heapq.heappop(runs)
        length = -length
        free = [x for x in range(length) if not used_item[j + x] and i + x not in used_doc]
        if len(free) == length:
            tiles, marked = tiles + 1, marked + length
            for x in range(length):
                used_item[j + x] = 1
                used_doc.add(i + x)
            if marked == len(item):
                break
            continue
        begin = prev = None
        for x in [*free, None]:
            if prev is None:
                begin = x
            elif x is None or x != prev + 1:
                if prev - begin + 1 >= k:
                    heapq.heappush(runs, (-(prev - begin + 1), i + begin, j + begin))
                begin = x
            prev = x
    return tiles, marked


class Index:
    """Seeds of all items by their length, sorted, with (item, position) postings."""

    def __init__(self, items: list[tuple[int, np.ndarray]], min_tile: int):
        self.items = [x for x in items if len(x[1])]
        self.by_k: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]] = {}
        seeds: dict[int, list] = {}
        for n, (_, words) in enumerate(self.items):
            k = min(min_tile, len(words))
            g = grams(words, k)
            seeds.setdefault(k, []).append((g, np.full(len(g), n), np.arange(len(g))))
        for k, parts in seeds.items():
            g, n, j = (np.concatenate(x) for x in zip(*parts, strict=True))
            order = np.argsort(g, kind="stable")
            self.by_k[k] = g[order], n[order], j[order]

    def hits(self, words: np.ndarray, owner: np.ndarray):
        """{(document number, item number): (k, [(position, item position)])} over one chunk's tokens."""
        found: dict[tuple[int, int], tuple[int, list]] = {}
        for k, (seeds, item, place) in self.by_k.items():
            g = grams(words, k)
            if not len(g):
                continue
            lo = np.searchsorted(seeds, g)
            hit = np.flatnonzero((seeds[np.minimum(lo, len(seeds) - 1)] == g) & (owner[: len(g)] == owner[k - 1 :]))
            hi = np.searchsorted(seeds, g[hit], side="right")
            for i, a, b in zip(hit.tolist(), lo[hit].tolist(), hi.tolist(), strict=True):
                for x in range(a, b):
                    found.setdefault((int(owner[i]), int(item[x])), (k, []))[1].append((i, int(place[x])))
        return found

    def leaks(self, words: np.ndarray, owner: np.ndarray, min_cover: float):
        """(document number, item number, tiles, marked) of the pairs that reach min_cover."""
        for (d, n), (k, pairs) in self.hits(words, owner).items():
            item = self.items[n][1]
            reach = np.zeros(len(item) + k, bool)
            for j in {j for _, j in pairs}:
                reach[j : j + k] = True
            if reach.sum() < min_cover * len(item):
                continue  # tiles can't cover more than the seeds do
            tiles, marked = tile(words, item, pairs, k)
            if marked >= min_cover * len(item):
                yield d, n, tiles, marked


def _items(rows) -> list[tuple[int, np.ndarray]]:
    out = []
    for item_id, text in rows:
        data = np.frombuffer((text or "").encode(), np.uint8)
        out.append((item_id, word_hashes(data, np.array([0, len(data)]), PUNCT)[0]))
    return out


def small_enough(benchmark: DataFrame, max_tokens: int) -> bool:
    """Tokens are never more than (characters + 1) / 2."""
    return (benchmark.agg(F.sum(F.length("text") + 1)).first()[0] or 0) / 2 <= max_tokens


def _leaky(batch: pa.RecordBatch, column: int, index: Index, min_cover: float):
    data, offsets = text_buffers(batch.column(column))
    for first, part, offs in chunks(data, offsets):
        words, owner = word_hashes(part, offs, PUNCT)
        for d, n, tiles, marked in index.leaks(words, owner, min_cover):
            yield first + d, n, tiles, marked


def leaks(spark: SparkSession, docs: DataFrame, benchmark: DataFrame, min_tile: int = MIN_TILE, min_cover: float = MIN_COVER, max_tokens: int = MAX_TOKENS) -> DataFrame:
    """One row per contaminated (doc_id, item_id)."""
    benchmark = benchmark.select(F.col("item_id").cast("long").alias("item_id"), "text")
    if not small_enough(benchmark, max_tokens):
        return _leaks_by_join(docs, benchmark, min_tile, min_cover).drop("key", "digest").distinct()
    shipped = spark.sparkContext.broadcast(Index(_items([(r[0], r[1]) for r in benchmark.collect()]), min_tile))

    def scan(batches):
        index = shipped.value
        for batch in batches:
            ids = batch.column(0).to_pylist()
            yield _rows([(ids[d], index.items[n][0], tiles, marked, len(index.items[n][1])) for d, n, tiles, marked in _leaky(batch, 1, index, min_cover)])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(scan, SCHEMA).distinct()


def _rows(rows: list[tuple]) -> pa.RecordBatch:
    d, n, t, m, size = zip(*rows, strict=True) if rows else ([],) * 5
    return pa.RecordBatch.from_arrays(
        [pa.array(list(d), pa.int64()), pa.array(list(n), pa.int64()), pa.array(list(t), pa.int32()), pa.array(list(m), pa.int32()), pa.array(list(size), pa.int32()), pa.array([a / b for a, b in zip(m, size, strict=True)], pa.float64())],
        ["doc_id", "item_id", "n_tiles", "matched_tokens", "item_tokens", "coverage"],
    )


def _leaks_by_join(docs: DataFrame, benchmark: DataFrame, min_tile: int, min_cover: float) -> DataFrame:
    """For a benchmark of any size: join distinct seeds, tile the pairs that share any.

    Every pair is tiled with its own texts, so equal hashes of different rows only add pairs to check. Rows of SCHEMA
    with the row's key and the digest of its text.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").withColumn("key", F.xxhash64("doc_id", "text"))
    benchmark = benchmark.withColumn("item_key", F.xxhash64("item_id", "text"))

    def seeds(sizes):
        def run(batches):
            for batch in batches:
                data, offsets = text_buffers(batch.column(1))
                ids = batch.column(0)
                for first, part, offs in chunks(data, offsets):
                    words, owner = word_hashes(part, offs, PUNCT)
                    count = np.bincount(owner, minlength=len(offs) - 1)
                    for k in sizes:
                        g = grams(words, k)
                        ok = owner[: len(g)] == owner[k - 1 :] if len(g) else np.zeros(0, bool)
                        if sizes is not every and k < min_tile:
                            ok &= count[owner[: len(g)]] == k
                        who = owner[: len(g)][ok]
                        pair = np.unique(np.stack([who.astype(np.uint64), g[ok]]), axis=1)
                        yield pa.RecordBatch.from_arrays([ids.take(pa.array(first + pair[0].astype(np.int64))), pa.array(pair[1].view(np.int64))], ["id", "seed"])

        return run

    every = tuple(range(1, min_tile + 1))
    items = benchmark.select("item_key", "text").mapInArrow(seeds((*every,)), "id long, seed long").select(F.col("id").alias("item_key"), "seed")
    found = docs.select("key", "text").mapInArrow(seeds(every), "id long, seed long").select(F.col("id").alias("key"), "seed")
    pairs = found.join(items, "seed").select("key", "item_key").distinct()
    both = pairs.join(docs.distinct(), "key").join(benchmark.withColumnRenamed("text", "item").distinct(), "item_key").select("doc_id", "item_id", "text", "item", "key", F.md5("text").alias("digest"))

    def check(batches):
        for batch in batches:
            out, at = [], []
            for i, (d, n, text, item) in enumerate(zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True)):
                index = Index(_items([(n, item)]), min_tile)
                words = _items([(0, text)])[0][1]
                for _, _, tiles, marked in index.leaks(words, np.zeros(len(words), np.int64), min_cover):
                    out.append((d, n, tiles, marked, len(index.items[0][1])))
                    at.append(i)
            rows, which = _rows(out), pa.array(at, pa.int64())
            yield pa.RecordBatch.from_arrays([*rows.columns, batch.column(4).take(which), batch.column(5).take(which)], [*rows.schema.names, "key", "digest"])

    return both.mapInArrow(check, SCHEMA + ", key long, digest string")


def clean(spark: SparkSession, docs: DataFrame, benchmark: DataFrame, min_tile: int = MIN_TILE, min_cover: float = MIN_COVER, max_tokens: int = MAX_TOKENS) -> DataFrame:
    """docs without the contaminated rows; same columns."""
    if not small_enough(benchmark, max_tokens):
        bad = _leaks_by_join(docs, benchmark.select(F.col("item_id").cast("long").alias("item_id"), "text"), min_tile, min_cover)
        keyed = docs.select(F.struct(*docs.columns).alias("row"), F.xxhash64(F.col("doc_id").cast("long"), "text").alias("key"), F.md5("text").alias("digest"))
        return keyed.join(bad.select("key", "digest").distinct(), ["key", "digest"], "left_anti").select("row.*")
    shipped = spark.sparkContext.broadcast(Index(_items([(r[0], r[1]) for r in benchmark.select("item_id", "text").collect()]), min_tile))
    at = docs.columns.index("text")

    def scan(batches):
        for batch in batches:
            keep = np.ones(batch.num_rows, bool)
            for d, *_ in _leaky(batch, at, shipped.value, min_cover):
                keep[d] = False
            yield batch.filter(pa.array(keep))

    return docs.mapInArrow(scan, docs.schema)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return leaks(spark, read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "benchmark"))


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: contaminated documents go."""
    return clean(spark, docs, read_table(spark, sf_dir, "benchmark"))
