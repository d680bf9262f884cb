"""Removal of repeated byte strings by a sparse, distributed suffix sort.

A byte goes if a string of WIDTH bytes that covers it also starts in a document with a smaller id. Sorting every
suffix would exchange many times the input, so only suffixes at anchors are exchanged: the anchor of a WIDTH-byte
window is the leftmost smallest of its K-byte grams, hence equal windows have equal anchors at equal places. The
consecutive windows of one anchor form a span.

1. (gram, span) hashes with their smallest and largest document are aggregated. Grams of one document only end here.
2. Bit filters that grow with their keys, up to a bound, hold the spans that are left; a second pass emits only their occurrences, with their
   bytes only in the span's smallest document. A span seen in a smaller document goes as a whole.
3. What is left are spans whose gram occurs elsewhere with other surroundings (the rims of repeated passages). Their
   suffixes are exchanged as sorted, front-coded runs and combined by a loser tree that compares only beyond the
   known common prefix; suffixes that share the gram are then neighbours, and their windows are looked up in turn.

Defined cases: a null or empty text, or one under WIDTH bytes, loses nothing; rows without doc_id neither lose nor
remove; rows that repeat a doc_id are treated apart by their text; an empty table gives an empty result; further
columns are ignored.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from array import array

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .bitfilter import FILTER_BITS, SharedFilter, bits_for, build_filter, in_filter
from .common import Workspace, chunks, mix, prefix_sums, read_table, slide_hashes, span_hashes, text_buffers

WIDTH, GRAM = 50, 16
#: Bytes of the longest span that a run can hold.
MAX_RECORD = 255
#: Text over which equal spans are combined before the exchange.
COMBINE_BYTES = 8 << 20
#: Records that one task sorts into runs at a time, and of a bucket at most, on average.
RUN_RECORDS, BUCKET_RECORDS = 1 << 16, 1 << 18
#: Merged records, and their windows, that are looked up at a time.
MERGE_RECORDS, MERGE_WINDOWS = 1 << 13, 1 << 18
_LOW = np.uint64(0xFFFFFFFF)


def anchors(data: np.ndarray, offsets: np.ndarray, width: int = WIDTH, gram: int = GRAM):
    """(gram hash, span hash, text number, first window, windows, anchor - first window) of every anchor."""
    n = len(data) - gram + 1
    z = np.zeros(0, np.int64)
    if len(data) < width:
        return z.view(np.uint64), z.view(np.uint64), z, z, z, z
    sums = prefix_sums(data)
    h = slide_hashes(sums, gram)
    low = (h & ~_LOW) | np.arange(n, dtype=np.uint64)  # the smallest gram, leftmost among equals
    take, have = width - gram + 1, 1
    while have * 2 <= take:
        low = np.minimum(low[: len(low) - have], low[have:])
        have *= 2
    if have < take:
        low = np.minimum(low[: len(low) - (take - have)], low[take - have :])
    anchor = (low & _LOW).astype(np.int64)
    owner = np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))[: len(anchor)]
    inside = np.arange(len(anchor)) + width <= offsets[owner + 1]
    start, anchor, owner = np.flatnonzero(inside), anchor[inside], owner[inside]
    if not len(start):
        return z.view(np.uint64), z.view(np.uint64), z, z, z, z
    new = np.ones(len(start), bool)
    new[1:] = (anchor[1:] != anchor[:-1]) | (owner[1:] != owner[:-1])
    first = np.flatnonzero(new)
    last = np.append(first[1:], len(start)) - 1
    a, s, e = anchor[first], start[first], start[last]
    span = mix(span_hashes(sums, s, e + width) + (a - s).astype(np.uint64))
    return h[a], span, owner[first], s, e - s + 1, a - s


def key_of(gram: np.ndarray, span: np.ndarray) -> np.ndarray:
    return mix(gram * np.uint64(0x9E3779B97F4A7C15) ^ span)


def in_document(key: np.ndarray, doc: np.ndarray) -> np.ndarray:
    """Key of a span in one document."""
    return mix(key ^ mix(doc.view(np.uint64) + np.uint64(1)))


# ---------------------------------------------------------------- sorted front-coded runs


def encode_run(records: list[tuple[bytes, tuple]]) -> bytes:
    """Sorted (suffix, payload) as common-prefix length, rest and payload."""
    records.sort()
    out, before = [], b""
    for suffix, (before_part, doc, text, start, n) in records:
        common = _common(before, suffix, 0)
        out.append(struct.pack("<BBBqiiH", common, len(suffix) - common, len(before_part), doc, text, start, n) + suffix[common:] + before_part)
        before = suffix
    return zlib.compress(b"".join(out), 1)


def decode_run(blob: bytes):
    """Yields (common prefix with the run's last suffix, suffix, payload)."""
    raw, at, before, head = zlib.decompress(blob), 0, b"", struct.calcsize("<BBBqiiH")
    while at < len(raw):
        common, rest, left, doc, text, start, n = struct.unpack_from("<BBBqiiH", raw, at)
        at += head
        before = before[:common] + raw[at : at + rest]
        at += rest
        yield common, before, (raw[at : at + left], doc, text, start, n)
        at += left


def _common(a: bytes, b: bytes, known: int) -> int:
    """Length of the common prefix of a and b, at least `known` bytes of which are known to agree."""
    n = min(len(a), len(b))
    if a[known:n] == b[known:n]:
        return n
    while a[known] == b[known]:
        known += 1
    return known


class LoserTree:
    """Merges sorted runs. Every waiting suffix knows its common prefix with the last winner; of two that know
    different lengths the longer is smaller, and only equal lengths are compared, from there on."""

    def __init__(self, runs):
        self.runs = [iter(r) for r in runs]
        self.k = 1
        while self.k < max(1, len(self.runs)):
            self.k *= 2
        self.head: list = [self._next(i) for i in range(self.k)]
        self.known = [0] * self.k
        self.loser = [-1] * self.k
        self.winner = self._build(1)

    def _next(self, i: int):
        return next(self.runs[i], None) if i < len(self.runs) else None

    def _build(self, node: int) -> int:
        if node >= self.k:
            return node - self.k
        a, b = self._build(2 * node), self._build(2 * node + 1)
        win, lose = self._play(a, b)
        self.loser[node] = lose
        return win

    def _play(self, a: int, b: int) -> tuple[int, int]:
        x, y = self.head[a], self.head[b]
        if x is None or y is None:
            return (a, b) if y is None else (b, a)
        p, q = self.known[a], self.known[b]
        if p != q:
            return (a, b) if p > q else (b, a)
        s, t = x[1], y[1]
        c = _common(s, t, p)
        if s[c : c + 1] <= t[c : c + 1]:
            self.known[b] = c
            return a, b
        self.known[a] = c
        return b, a

    def __iter__(self):
        """Yields (common prefix with the suffix before, suffix, payload) in order."""
        while (top := self.head[self.winner]) is not None:
            w = self.winner
            yield self.known[w], top[1], top[2]
            self.head[w] = self._next(w)
            self.known[w] = self.head[w][0] if self.head[w] is not None else 0
            node = (w + self.k) // 2
            while node >= 1:
                win, lose = self._play(w, self.loser[node])
                self.loser[node], w = lose, win
                node //= 2
            self.winner = w


def repeated_windows(records, width: int, gram: int, most: int = MERGE_RECORDS, windows: int = MERGE_WINDOWS):
    """Yields arrays (doc, text, begin, end) of the windows that a smaller document has; records come from a LoserTree.

    Suffixes that share the gram follow each other, so about `most` records are looked up at a time, a gram's together."""

    def empty():
        return bytearray(), array("q", [0]), array("q"), array("i"), array("i"), array("H"), array("Q")

    data, offsets, docs, texts, starts, counts, group = held = empty()
    g = 0
    for common, suffix, (left, doc, text, start, n) in records:
        if common < gram:
            g += 1
            if len(docs) >= most:
                yield _repeated(*(np.frombuffer(x, getattr(x, "typecode", np.uint8)) for x in held), width, windows)
                data, offsets, docs, texts, starts, counts, group = held = empty()
        data += left
        data += suffix
        offsets.append(len(data))
        docs.append(doc)
        texts.append(text)
        starts.append(start)
        counts.append(n)
        group.append(g)
    if docs:
        yield _repeated(*(np.frombuffer(x, getattr(x, "typecode", np.uint8)) for x in held), width, windows)


def _repeated(data, offsets, docs, texts, starts, counts, group, width: int, windows: int):
    """Intervals of the repeated windows of some records; beside a hash for each, about `windows` windows are sorted at a time."""
    before = np.concatenate([[0], np.cumsum(counts, dtype=np.int64)])
    h = np.empty(before[-1], np.uint64)
    for i, part, offs in chunks(data, offsets):
        j = i + len(offs) - 1
        row = np.repeat(np.arange(j - i), counts[i:j])
        at = offs[row] + np.arange(len(row)) - (before[i:j] - before[i])[row]
        h[before[i] : before[j]] = mix(span_hashes(prefix_sums(part), at, at + width) ^ group[i:j][row])
    out = np.zeros(len(h), bool)
    classes = -(-len(h) // windows)
    for c in range(classes):
        at = np.flatnonzero(h % np.uint64(classes) == c)
        key, doc = h[at], docs[np.searchsorted(before, at, side="right") - 1]
        order = np.lexsort((doc, key))
        key, doc = key[order], doc[order]
        first = np.ones(len(order), bool)
        first[1:] = key[1:] != key[:-1]
        least = doc[np.flatnonzero(first)][np.cumsum(first) - 1]
        out[at[order[doc > least]]] = True
    hit = np.flatnonzero(out)
    row = np.searchsorted(before, hit, side="right") - 1
    new = np.ones(len(hit), bool)
    new[1:] = (hit[1:] != hit[:-1] + 1) | (row[1:] != row[:-1])
    a = np.flatnonzero(new)
    b = np.append(a[1:], len(hit))[: len(a)] - 1
    r = row[a]
    return docs[r], texts[r], starts[r] + (hit[a] - before[r]), starts[r] + (hit[b] - before[r]) + width


# ---------------------------------------------------------------- the operator


def _source(docs: DataFrame) -> DataFrame:
    text = F.coalesce(F.col("text"), F.lit(""))
    return docs.select(F.col("doc_id").cast("long").alias("doc"), F.hash(text).alias("th"), text.alias("text"))


def repeated_intervals(spark: SparkSession, docs: DataFrame, work: Workspace, width: int = WIDTH, gram: int = GRAM, filter_bits: int = FILTER_BITS) -> DataFrame:
    """(doc, th, begin, end): byte intervals to remove, which may overlap."""
    if not 0 < gram <= width or 2 * width - gram > MAX_RECORD:
        raise ValueError(f"width {width} and gram {gram}: a run's lengths are bytes, so 2 * width - gram is at most {MAX_RECORD}")
    source = _source(docs).where(F.col("doc").isNotNull() & (F.octet_length("text") >= width))

    def grams(batches):
        for batch in batches:
            ids = batch.column(0).to_numpy()
            data, offsets = text_buffers(batch.column(1))
            got, size = [], 0
            for first, part, offs in chunks(data, offsets):
                g, s, o, *_ = anchors(part, offs, width, gram)
                got.append((g, s, ids[first + o]))
                size += len(part)
                if size >= COMBINE_BYTES:
                    yield combined(got)
                    got, size = [], 0
            yield combined(got)

    def combined(got):
        """Equal spans of some texts as one row with their smallest and largest document."""
        g, s, d = (np.concatenate(x) for x in zip(*got, strict=True)) if got else (np.zeros(0, np.uint64),) * 2 + (np.zeros(0, np.int64),)
        key = key_of(g, s)
        order = np.lexsort((d, key))
        new = np.ones(len(order), bool)
        new[1:] = key[order][1:] != key[order][:-1]
        first = np.flatnonzero(new)
        last = np.append(first[1:], len(order)) - 1 if len(order) else first
        low, high = d[order][first], d[order][last]
        return pa.RecordBatch.from_arrays([pa.array(g[order][first].view(np.int64)), pa.array(s[order][first].view(np.int64)), pa.array(low), pa.array(high, mask=low == high)], ["g", "s", "lo", "hi"])

    seen = source.select("doc", "text").mapInArrow(grams, "g long, s long, lo long, hi long")
    whole = seen.repartition("g").groupBy("g", "s").agg(F.min("lo").alias("m"), F.greatest(F.max("lo"), F.max("hi")).alias("x"))
    by_gram = Window.partitionBy("g")
    shared = (
        whole.withColumn("lo", F.min("m").over(by_gram)).withColumn("hi", F.max("x").over(by_gram)).withColumn("n", F.count(F.lit(1)).over(by_gram))
        .where((F.col("lo") < F.col("hi")) & ((F.col("m") < F.col("x")) | (F.col("n") > 1)))
        .select("g", "s", "m", (F.col("m") < F.col("x")).alias("again"), (F.col("n") > 1).alias("rim"))
    )

    def name(batches):
        for batch in batches:
            k = key_of(batch.column(0).to_numpy().view(np.uint64), batch.column(1).to_numpy().view(np.uint64))
            rim = in_document(k, batch.column(2).to_numpy())
            yield pa.RecordBatch.from_arrays([pa.array(k.view(np.int64)), batch.column(2), batch.column(3), batch.column(4), pa.array(rim.view(np.int64))], ["key", "m", "again", "rim", "at"])

    spans = work.table(shared.mapInArrow(name, "key long, m long, again boolean, rim boolean, at long"), "spans")
    del seen, whole, shared
    work.release()
    # A full filter lets nearly every span's bytes into the exchange below, so filters grow with their keys.
    n_again, n_rim = spans.agg(F.count_if("again"), F.count_if("rim")).first()

    def held(keys, n):
        bits = bits_for(n, filter_bits)
        return SharedFilter(spark, lambda head: build_filter(keys, bits, rounds=1 << (bits - filter_bits), head=head))

    again = held(spans.where("again").select("key"), n_again)
    rim = held(spans.where("rim").select(F.col("at").alias("key")), n_rim)

    def occurrences(batches):
        in_again, in_rim = again.field(), rim.field()
        for batch in batches:
            ids, texts = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            data, offsets = text_buffers(batch.column(2))
            for first, part, offs in chunks(data, offsets):
                g, s, o, start, n, rel = anchors(part, offs, width, gram)
                key, doc = key_of(g, s), ids[first + o]
                edge = in_filter(in_rim, in_document(key, doc))
                hit = np.flatnonzero(edge | in_filter(in_again, key))
                a, b = start[hit], start[hit] + n[hit] - 1 + width
                raw = part.tobytes()
                bytes_ = [raw[x:y] if e else None for x, y, e in zip(a.tolist(), b.tolist(), edge[hit].tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays(
                    [pa.array(key[hit].view(np.int64)), pa.array(doc[hit]), pa.array(texts[first + o[hit]]), pa.array((a - offs[o[hit]]).astype(np.int32)), pa.array(n[hit].astype(np.int16)), pa.array(rel[hit].astype(np.int16)), pa.array(bytes_, pa.binary())],
                    ["key", "doc", "th", "start", "n", "rel", "bytes"],
                )

    found = source.mapInArrow(occurrences, "key long, doc long, th int, start int, n short, rel short, bytes binary")
    met = work.table(
        found.join(spans.select("key", "m", "rim"), "key").where((F.col("doc") > F.col("m")) | F.col("rim"))
        .withColumn("settled", F.col("doc") > F.col("m")).withColumn("bytes", F.when(~F.col("settled"), F.col("bytes")))
        .select("key", "doc", "th", "start", "n", "rel", "bytes", "settled"), "met", ("settled",),
    )
    del found, spans
    work.drop("spans")
    work.release()
    settled = met.where("settled").select("doc", "th", F.col("start").cast("int").alias("begin"), (F.col("start") + F.col("n") - 1 + width).cast("int").alias("end"))
    buckets = max(64, int(spark.conf.get("spark.sql.shuffle.partitions", "200")), n_rim // BUCKET_RECORDS)

    def runs(batches):
        by_bucket: dict[int, list] = {}
        waiting = 0
        for batch in batches:
            for doc, th, start, n, rel, raw in zip(*(batch.column(i).to_pylist() for i in range(6)), strict=True):
                # Equal windows share the gram at the anchor, so a gram's suffixes meet in one bucket.
                by_bucket.setdefault(zlib.crc32(raw[rel : rel + gram]) % buckets, []).append((raw[rel:], (raw[:rel], doc, th, start, n)))
            waiting += batch.num_rows
            if waiting >= RUN_RECORDS:
                yield encoded(by_bucket)
                by_bucket, waiting = {}, 0
        yield encoded(by_bucket)

    def encoded(by_bucket: dict[int, list]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(list(by_bucket), pa.int32()), pa.array([encode_run(r) for r in by_bucket.values()], pa.binary())], ["bucket", "run"])

    def merge(table: pa.Table) -> pa.Table:
        found = list(repeated_windows(LoserTree([decode_run(b.as_buffer()) for b in table.column("run")]), width, gram))
        cols = [np.concatenate(c) for c in zip(*found, strict=True)] or [[]] * 4
        return pa.table([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int32(), pa.int32(), pa.int32()), strict=True)], names=["doc", "th", "begin", "end"])

    rims = met.where(~F.col("settled")).select("doc", "th", "start", "n", "rel", "bytes").mapInArrow(runs, "bucket int, run binary")
    return settled.unionByName(rims.groupBy("bucket").applyInArrow(merge, "doc long, th int, begin int, end int"))


def union_of(intervals: np.ndarray) -> np.ndarray:
    """Maximal disjoint intervals; touching ones join."""
    intervals = intervals[np.argsort(intervals[:, 0], kind="stable")]
    reach = np.maximum.accumulate(intervals[:, 1])
    new = np.ones(len(intervals), bool)
    new[1:] = intervals[1:, 0] > reach[:-1]
    first = np.flatnonzero(new)
    return np.stack([intervals[first, 0], reach[np.append(first[1:], len(intervals)) - 1]], axis=1)


def remove(spark: SparkSession, docs: DataFrame, **options) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept (binary) for every row of docs."""
    work = Workspace(spark, "suffix")
    found = repeated_intervals(spark, docs, work, **options)
    lists = found.groupBy("doc", "th").agg(F.collect_list("begin").alias("begins"), F.collect_list("end").alias("ends"))

    def cut(batches):
        for batch in batches:
            out = []
            for text, begins, ends in zip(*(batch.column(i) for i in (1, 2, 3)), strict=True):
                raw = text.as_py().encode()
                gone = 0
                spans = np.zeros((0, 2), np.int64)
                kept = raw
                if begins.is_valid:
                    spans = union_of(np.stack([begins.values.to_numpy(), ends.values.to_numpy()], axis=1))
                    at, parts = 0, []
                    for a, b in spans.tolist():
                        parts.append(raw[at:a])
                        at, gone = b, gone + b - a
                    kept = b"".join([*parts, raw[at:]])
                out.append((len(raw), gone, len(spans), hashlib.sha256(kept).hexdigest(), kept))
            n, r, s, d, k = zip(*out, strict=True) if out else ([],) * 5
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(list(n), pa.int64()), pa.array(list(r), pa.int64()), pa.array(list(s), pa.int64()), pa.array(list(d), pa.string()), pa.array(list(k), pa.binary())], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"])

    both = _source(docs).join(lists, ["doc", "th"], "left").select("doc", "text", "begins", "ends")
    return both.mapInArrow(cut, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove(spark, read_table(spark, sf_dir, "documents")).drop("kept")
