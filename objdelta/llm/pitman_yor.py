"""Language-model scoring with a hierarchical Pitman-Yor process, its seating sampled by Gibbs.

Two levels of restaurants: one for each context, all sharing the unigram restaurant as parent. A context is the word
before itself, so there are as many restaurants as words. A customer of a context is a training token; each of its
tables sends one customer to the parent, whose own new tables are words never seen: their mass is the probability of
an unknown word. Contexts of two and more words are not built.

Given the totals of all restaurants, the tables of one (context, word) depend only on its customers and on the
word's mass in the parent: p(t) is proportional to the generalised Stirling number S_d(c, t) times the odds of a new
table to the power t. So a sweep resamples all words in parallel, each where its counts lie, and only the totals of
the contexts meet in between. Predictive probabilities are averaged over the samples after burn-in.

Data flow: a pass over the texts deals word counts to buckets by word hash for the model (pairs met only in held-out
rows have count 0), and a second pass deals them with document numbers for scoring, so neither is kept on disk; model rows go first in each bucket, scored
rows stream past them. After a sweep every bucket sends its contexts' tables to shards by context hash; a shard adds
them up and answers each bucket about its own contexts, so no task holds the totals of all contexts. Words that make
up over 1/256 of a sample are dealt by the word before to buckets of their own; the driver adds up those few words'
counts, so that no word's occurrences meet in one task. The draws are keyed by word, context and sweep, so the scores are
the same however the rows are dealt. Buckets follow the bytes of the texts.

Defined cases: a null or empty text is its end token alone; rows that share a doc_id are summed; rows without doc_id
are left out; with no training row every word is unknown (probability 1); an empty table gives an empty result;
further columns are ignored.
"""

from __future__ import annotations

import copy
import pickle
import zlib

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Workspace, chunks, id_bucket, mix, read_table, text_buffers, word_hashes

FOLD, HELD = 5, 1
END = np.uint64(0xE4D0F7E4D0F7E4D1)  # the end token's word hash
START = np.uint64(0xA3B19C5D2E87F461)  # the context of a text's first token
HOT_SHARE, SEGMENT_BYTES, BUCKET_BYTES = 1 / 256, 4 << 20, 12 << 20
#: A context is named by so many high bits of its word's hash.
CONTEXT_BITS = 48
SWEEPS, BURN_IN = 3, 1
EXACT = 32  # customers up to which tables are drawn from the exact conditional


def pack(obj) -> bytes:
    return zstandard.ZstdCompressor(level=1).compress(pickle.dumps(obj, protocol=5))


def unpack(blob: bytes):
    return pickle.loads(zstandard.ZstdDecompressor().decompress(blob))


def squeeze(x: np.ndarray) -> bytes:
    """Sorted hashes as differences, byte planes apart: the high planes are nearly all zero and pack to nothing."""
    return np.ascontiguousarray(np.diff(x, prepend=np.uint64(0)).view(np.uint8).reshape(-1, 8).T).tobytes()


def expand(raw: bytes) -> np.ndarray:
    return np.cumsum(np.ascontiguousarray(np.frombuffer(raw, np.uint8).reshape(8, -1).T).view(np.uint64).ravel(), dtype=np.uint64)


def small(x: np.ndarray) -> np.ndarray:
    """The same numbers in the narrowest unsigned type."""
    top = int(x.max()) if len(x) else 0
    return x.astype(np.uint8 if top < 256 else np.uint16 if top < 65536 else np.uint32)


# ---------------------------------------------------------------- tokens


def tokens(data: np.ndarray, offsets: np.ndarray):
    """(word, whether it is a text's first, text number) of all words, and of one end token for each text."""
    words, owner = word_hashes(data, offsets)
    n_texts = len(offsets) - 1
    count = np.bincount(owner, minlength=n_texts)
    after = np.cumsum(count)
    word = np.insert(words, after, END)
    who = np.insert(owner, after, np.arange(n_texts))
    first = np.ones(len(word), bool)
    first[1:] = who[1:] != who[:-1]
    return word, first, who


def _runs(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct values of a sorted array and how often each occurs."""
    new = np.ones(len(x), bool)
    new[1:] = x[1:] != x[:-1]
    at = np.flatnonzero(new)
    return x[at], np.diff(np.append(at, len(x)))


def hot_buckets(buckets: int) -> int:
    return max(8, buckets // 4)


def segment_blobs(word, first, who, ids, train, buckets: int, hot: np.ndarray, kind: int):
    """(kind, bucket, blob) of one segment: kind 0 counts for the model, kind 2 occurrences to score."""
    vocabulary, at = np.unique(word, return_inverse=True)
    contexts = np.append(vocabulary, START)
    before = np.empty(len(word), np.int64)
    before[1:] = at[:-1]
    before[first] = len(vocabulary)
    n_docs, n_contexts = len(ids), len(contexts)
    key, n = _runs(np.sort((at.astype(np.int64) * n_contexts + before) * n_docs + who))
    pair, doc = key // n_docs, key % n_docs
    w, u = pair // n_contexts, pair % n_contexts
    home = (vocabulary >> np.uint64(33)).astype(np.int64)[w] % buckets
    is_hot = np.isin(vocabulary, hot)[w]
    home[is_hot] = buckets + (contexts[u[is_hot]] >> np.uint64(17)).astype(np.int64) % hot_buckets(buckets)
    order = np.argsort(home, kind="stable")
    home, doc, n, pair = home[order], doc[order], n[order], pair[order]
    edges = np.searchsorted(home, np.arange(buckets + hot_buckets(buckets) + 1))
    for b in np.flatnonzero(np.diff(edges)).tolist():
        part = slice(edges[b], edges[b + 1])
        pairs, docs_of = _runs(pair[part])
        words, lens = _runs(pairs // n_contexts)
        mine, u = np.unique(pairs % n_contexts, return_inverse=True)
        common = (squeeze(vocabulary[words]), small(lens), squeeze(contexts[mine] >> np.uint64(64 - CONTEXT_BITS)), small(u))
        if kind == 0:
            yield 0, b, pack((*common, small(np.add.reduceat(n[part] * train[doc[part]], np.cumsum(docs_of) - docs_of))))
        else:
            some, which = np.unique(doc[part], return_inverse=True)
            yield 2, b, pack((*common, small(docs_of), small(which), small(n[part]), np.diff(ids[some], prepend=0)))


# ---------------------------------------------------------------- seating


def log_stirling(d: float, most: int = EXACT) -> np.ndarray:
    """log S_d(c, t) for c, t <= most."""
    out = np.full((most + 1, most + 1), -np.inf)
    out[0, 0] = 0
    for c in range(most):
        for t in range(1, c + 2):
            stay = c - d * t
            a, b = out[c, t - 1], out[c, t] + np.log(stay) if t <= c and stay > 0 else -np.inf
            out[c + 1, t] = np.logaddexp(a, b)
    return out


class Keyed:
    """Uniform numbers that depend on each pair's key, the sweep and the call alone, not on where the pair lies."""

    def __init__(self, key: np.ndarray, sweep: int):
        self.key, self.calls = key, 64 * sweep

    def random(self, n: int) -> np.ndarray:
        self.calls += 1
        return ((mix(self.key + mix(np.array([self.calls], np.uint64))) >> np.uint64(11)).astype(np.float64) + 0.5) / float(1 << 53)


def poisson(mean: np.ndarray, u: np.ndarray, v: np.ndarray) -> np.ndarray:
    """Poisson numbers from two uniform ones: by inversion up to a mean of 50, beyond by the normal approximation."""
    k, p = np.zeros(len(mean)), np.exp(-np.minimum(mean, 50))
    left = u - p
    for i in range(1, 200):
        more = left > 0
        if not more.any():
            break
        k += more
        p = p * np.minimum(mean, 50) / i
        left -= p
    return np.where(mean <= 50, k, np.maximum(0, np.rint(mean + np.sqrt(mean) * np.sqrt(-2 * np.log(u)) * np.cos(2 * np.pi * v)))).astype(np.int64)


def draw_tables(c: np.ndarray, odds: np.ndarray, stirling: np.ndarray, rng: np.random.Generator | Keyed) -> np.ndarray:
    """Tables of every (context, word) given its customers and the odds of a new table."""
    u, v, w = (rng.random(len(c)) for _ in range(3))
    t = np.ones(len(c), np.int64)
    first = np.minimum(c, EXACT)
    for size in range(2, EXACT + 1):
        rows = np.flatnonzero(first == size)
        if not len(rows):
            continue
        k = np.arange(1, size + 1)
        for at in range(0, len(rows), 200_000):
            r = rows[at : at + 200_000]
            logp = stirling[size, 1 : size + 1][None] + np.log(odds[r])[:, None] * k[None]
            p = np.exp(logp - logp.max(axis=1, keepdims=True)).cumsum(axis=1)
            t[r] = 1 + (p < u[r][:, None] * p[:, -1:]).sum(axis=1)
    # Beyond EXACT customers, new tables arrive at the rate odds / (odds + i); their number over a stretch is Poisson.
    rest = np.flatnonzero(c > EXACT)
    if len(rest):
        mean = odds[rest] * np.log((c[rest] + odds[rest]) / (EXACT + odds[rest]))
        t[rest] = np.minimum(c[rest], t[rest] + poisson(mean, v[rest], w[rest]))
    t[c == 0] = 0
    return t


class Totals:
    """What the restaurants share: numbers, the hot words' counts, and the totals of one bucket's contexts."""

    def __init__(self, contexts: int):
        self.customers = np.zeros(contexts)  # of each context
        self.tables: list[np.ndarray] = []  # of each context, by sweep
        self.all_tables: list[float] = []
        self.n = self.v = 0
        self.d1 = self.d2 = 0.5
        self.theta1 = self.theta2 = 1.0
        self.hot = np.zeros(0, np.uint64)  # sorted
        self.hot_count = np.zeros(0)
        self.hot_parent: list[np.ndarray] = []  # by sweep

    def local(self, customers: np.ndarray, tables: list[np.ndarray]) -> Totals:
        """The same with one bucket's contexts."""
        out = copy.copy(self)
        out.customers, out.tables = customers.astype(float), [x.astype(float) for x in tables]
        return out


class Bucket:
    """Counts of one bucket's words and their seating after each sweep."""

    def __init__(self, bucket: int, blob: bytes | tuple, contexts: int, names: np.ndarray | None = None):
        self.bucket, self.contexts, self.names = bucket, contexts, names
        self.words, lens, self.u, self.c = blob if isinstance(blob, tuple) else unpack(blob)
        self.u, self.c = self.u.astype(np.int64), self.c.astype(np.int64)
        self.w = np.repeat(np.arange(len(self.words)), lens)
        self.pair = self.w * contexts + self.u
        self.count = np.bincount(self.w, weights=self.c, minlength=len(self.words))
        self.seats = [(self.c > 0).astype(np.int64)]
        self.parent = [np.bincount(self.w, weights=self.seats[0], minlength=len(self.words))]

    def resume(self, seats: list[np.ndarray]) -> Bucket:
        """The bucket with the seatings of earlier sweeps."""
        self.seats = [x.astype(np.int64) for x in seats]
        self.parent = [np.bincount(self.w, weights=x, minlength=len(self.words)) if len(x) else None for x in self.seats]
        return self

    def _overall(self, own: np.ndarray, hot: np.ndarray, totals: Totals) -> np.ndarray:
        """The words' own numbers; those of hot words, which lie in several buckets, from the totals."""
        if not len(totals.hot) or not len(self.words):
            return own
        at = np.minimum(np.searchsorted(totals.hot, self.words), len(totals.hot) - 1)
        return np.where(totals.hot[at] == self.words, hot[at], own)

    def counts(self, totals: Totals) -> np.ndarray:
        return self._overall(self.count, totals.hot_count, totals)

    def parents(self, s: int, totals: Totals) -> np.ndarray:
        return self._overall(self.parent[s], totals.hot_parent[s] if len(totals.hot) else self.parent[s], totals)

    def sweep(self, totals: Totals) -> Bucket:
        """Sample the tables given the totals and the parent's customers of the sweep before."""
        s = len(self.seats)
        rng = Keyed(mix(self.words)[self.w] ^ (self.u if self.names is None else self.names[self.u]).astype(np.uint64), s)
        mass = (self.parents(s - 1, totals) - totals.d1) / (totals.theta1 + totals.all_tables[s - 1])
        odds = (totals.theta2 + totals.d2 * totals.tables[s - 1][self.u]) * mass[self.w]
        t = draw_tables(self.c, np.maximum(odds, 1e-12), log_stirling(totals.d2), rng)
        self.seats.append(t)
        self.parent.append(np.bincount(self.w, weights=t, minlength=len(self.words)))
        return self

    def predictive(self, w: np.ndarray, known: np.ndarray, u: np.ndarray, totals: Totals) -> np.ndarray:
        """Probability of the words (their numbers, or unknown) in their contexts, averaged over the samples."""
        key = np.where(known, w * self.contexts + u, -1)
        at = np.minimum(np.searchsorted(self.pair, key), max(0, len(self.pair) - 1))
        met = (self.pair[at] == key) if len(self.pair) else np.zeros(len(key), bool)
        c = np.where(met, self.c[at] if len(self.c) else 0, 0)
        out = np.zeros(len(key))
        samples = range(min(BURN_IN, len(self.seats) - 1) + 1, len(self.seats)) or [len(self.seats) - 1]
        for s in samples:
            unseen = (totals.theta1 + totals.d1 * totals.v) / (totals.theta1 + totals.all_tables[s])
            p1 = np.full(len(key), unseen)
            if len(self.words):
                p1 = np.where(known, (self.parents(s, totals)[w] - totals.d1) / (totals.theta1 + totals.all_tables[s]), unseen)
            t = np.where(met, self.seats[s][at] if len(self.c) else 0, 0)
            inside = totals.theta2 + totals.customers[u]
            out += (c - totals.d2 * t) / inside + (totals.theta2 + totals.d2 * totals.tables[s][u]) / inside * p1
        return out / len(samples)


def merge_counts(blobs: list[bytes]) -> tuple:
    """(words, pairs of each, contexts, context of each pair, count) from a bucket's blobs of all segments."""
    parts = [(expand(p[0]), p[1], expand(p[2]), *p[3:]) for p in map(unpack, blobs)]
    vocabulary = np.unique(np.concatenate([p[0] for p in parts]))
    contexts = np.unique(np.concatenate([p[2] for p in parts]))
    keys, counts = [], []
    for words, lens, before, u, c in parts:
        keys.append(np.repeat(np.searchsorted(vocabulary, words), lens) * len(contexts) + np.searchsorted(contexts, before)[u])
        counts.append(c)
    pair, at = np.unique(np.concatenate(keys), return_inverse=True)
    c = np.bincount(at, weights=np.concatenate(counts)).astype(np.int64)
    _, lens = _runs(pair // len(contexts))
    return vocabulary, small(lens), contexts, small(pair % len(contexts)), small(c)


class State:
    """One bucket between two sweeps, as it is written: its model, its seatings and what it knows of its contexts."""

    def __init__(self, model: tuple):
        self.words, self.lens, self.contexts, self.u, self.c = model
        self.seats: list[np.ndarray] = []
        self.customers: np.ndarray | None = None
        self.tables: list[np.ndarray] = []

    def __getstate__(self):
        return self.__dict__ | {"words": squeeze(self.words), "contexts": squeeze(self.contexts)}

    def __setstate__(self, kept):
        self.__dict__ |= kept | {"words": expand(kept["words"]), "contexts": expand(kept["contexts"])}

    def hear(self, answers: list[bytes]) -> None:
        """Answers of all shards, in their order: (customers, tables) of this bucket's contexts."""
        parts = [unpack(b) for b in answers]
        if self.customers is None:  # they don't change
            self.customers = np.concatenate([p[0] for p in parts])
        self.tables.append(np.concatenate([p[-1] for p in parts]))

    def forget(self) -> None:
        """Samples before the burn-in's end are needed for the next sweep only."""
        for kept in (self.seats, self.tables):
            for s in range(min(BURN_IN + 1, len(kept) - 1)):
                kept[s] = kept[s][:0]

    def load(self, bucket: int) -> Bucket:
        own = Bucket(bucket, (self.words, self.lens, self.u, self.c), len(self.contexts), self.contexts)
        return own.resume(self.seats) if self.seats else own

    def messages(self, own: Bucket, shards: int):
        """(shard, blob): contexts, customers and tables; a shard is a range of context hashes."""
        edges = np.searchsorted(self.contexts, np.arange(shards, dtype=np.uint64) * np.uint64((1 << CONTEXT_BITS) // shards))
        customers = np.bincount(own.u, weights=own.c, minlength=own.contexts).astype(np.int64) if self.customers is None else None
        tables = np.bincount(own.u, weights=own.seats[-1], minlength=own.contexts).astype(np.int64)
        for k, (a, b) in enumerate(zip(edges, np.append(edges[1:], len(self.contexts)), strict=True)):
            if a < b:
                yield k, pack((squeeze(self.contexts[a:b]), *(small(x[a:b]) for x in (customers, tables) if x is not None)))


def answer(table: pa.Table) -> pa.Table:
    """What a shard tells every bucket that sent it something: totals over all buckets."""
    senders, parts = table.column("bucket").to_pylist(), [(expand(p[0]), *p[1:]) for p in (unpack(b.as_py()) for b in table.column("blob"))]
    contexts, at = np.unique(np.concatenate([p[0] for p in parts]), return_inverse=True)
    sums = [np.bincount(at, weights=np.concatenate([p[i] for p in parts])).astype(np.int64) for i in range(1, len(parts[0]))]
    blobs = [pack(tuple(small(x[np.searchsorted(contexts, p[0])]) for x in sums)) for p in parts]
    return rows_of(zip([1] * len(blobs), senders, table.column("shard").to_pylist(), blobs, strict=True))


def rows_of(rows) -> pa.Table:
    kind, bucket, shard, blob = zip(*rows, strict=True)
    return pa.table([pa.array(kind, pa.int32()), pa.array(bucket, pa.int32()), pa.array(shard, pa.int32()), pa.array(blob, pa.binary())], names=["kind", "bucket", "shard", "blob"])


ROWS = "kind int, bucket int, shard int, blob binary"


# ---------------------------------------------------------------- the operator


def _hot_words(source: DataFrame) -> np.ndarray:
    """Hashes of words that make up over HOT_SHARE of one in 64 documents."""

    def count(batches):
        for batch in batches:
            data, offsets = text_buffers(batch.column(1))
            for _, part, offs in chunks(data, offsets):
                word, n = np.unique(tokens(part, offs)[0], return_counts=True)
                top = n >= HOT_SHARE / 4 * n.sum()
                yield pa.RecordBatch.from_arrays([pa.array(np.append(word[top].view(np.int64), 0)), pa.array(np.append(n[top], 0)), pa.array(np.append(np.zeros(top.sum(), np.int64), n.sum()))], ["w", "n", "all"])

    found = source.where(F.pmod(F.xxhash64("doc"), F.lit(64)) == 0).mapInArrow(count, "w long, n long, all long")
    rows = found.groupBy("w").agg(F.sum("n").alias("n"), F.sum("all").alias("all")).select("w", "n", "all", F.sum("all").over(_everything()).alias("total")).where(F.col("n") > HOT_SHARE * F.col("total")).collect()
    return np.sort(np.array([r[0] for r in rows if r[1]], np.int64).view(np.uint64))


def _everything():
    from pyspark.sql import Window

    return Window.partitionBy(F.lit(1))


def score(spark: SparkSession, docs: DataFrame, sweeps: int = SWEEPS) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score."""
    work = Workspace(spark, "pitman-yor")
    source = docs.select(F.col("doc_id").cast("long").alias("doc"), F.coalesce(F.col("text"), F.lit("")).alias("text")).where("doc is not null")
    buckets = max(32, (source.agg(F.sum(F.octet_length("text"))).first()[0] or 0) // BUCKET_BYTES)
    hot = _hot_words(source)

    def deal(kind):
        def run(batches):
            for batch in batches:
                ids = batch.column(0).to_numpy()
                train = np.array([zlib.crc32(str(i).encode()) % FOLD != HELD for i in ids.tolist()], bool)
                data, offsets = text_buffers(batch.column(1))
                for begin, part, offs in chunks(data, offsets, SEGMENT_BYTES):
                    n = len(offs) - 1
                    got = [(w, f, at + o) for at, piece, po in chunks(part, offs) for w, f, o in [tokens(piece, po)]]
                    word, first, who = (np.concatenate(x) for x in zip(*got, strict=True))
                    rows = segment_blobs(word, first, who, ids[begin : begin + n], train[begin : begin + n], buckets, hot, kind)
                    yield from rows_of((*row[:2], 0, row[2]) for row in rows).to_batches()

        return source.mapInArrow(run, ROWS)

    totals = Totals(0)
    totals.hot = hot
    rows = deal(0)
    for s in range(sweeps + 1):
        rows = _round(spark, work, rows, totals, s, buckets)
        if s:
            work.drop(f"round{s - 1}", f"answers{s - 1}")
        work.release()
    shipped = spark.sparkContext.broadcast(totals)

    def rate(batches):
        base_all = shipped.value.n + 0.5 * (shipped.value.v + 1)
        own = state = t = None
        answers: list[bytes] = []
        for batch in batches:
            for kind, bucket, blob in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), (x.as_py() for x in batch.column(3)), strict=True):
                if kind == 0:
                    state, own, answers = unpack(blob), None, []
                    continue
                if kind == 1:
                    answers.append(blob)
                    continue
                if own is None:
                    state.hear(answers)
                    own, t = state.load(bucket), shipped.value.local(state.customers, state.tables)
                    total = own.counts(t)
                words, lens, before, u, docs_of, doc, n, steps = unpack(blob)
                words, before = expand(words), expand(before)
                ids, n, doc = np.cumsum(steps), n.astype(np.float64), doc.astype(np.int64)
                w = np.repeat(np.searchsorted(own.words, words), lens)
                known = total[w] > 0
                rated = np.log10(own.predictive(w, known, np.searchsorted(state.contexts, before)[u], t))
                base = np.log10((total[w] + 0.5) / base_all)
                known, base, rated = (n * np.repeat(x, docs_of) for x in (known, base, rated))
                some = np.unique(doc)
                sums = [np.bincount(doc, weights=x, minlength=len(ids))[some] for x in (n, known, base, rated)]
                yield pa.RecordBatch.from_arrays([pa.array(ids[some]), pa.array(sums[0].astype(np.int64)), pa.array(sums[1].astype(np.int64)), pa.array(sums[2]), pa.array(sums[3])], ["doc_id", "n_tokens", "n_known", "base_score", "score"])

    both = rows.unionByName(deal(2)).repartition(buckets + hot_buckets(buckets), "bucket").sortWithinPartitions("bucket", "kind", "shard")
    parts = both.mapInArrow(rate, "doc_id long, n_tokens long, n_known long, base_score double, score double")
    out = parts.groupBy("doc_id").agg(*(F.sum(c).alias(c) for c in ("n_tokens", "n_known", "base_score", "score")))
    return out.select("doc_id", (id_bucket(F.col("doc_id"), FOLD) == HELD).alias("held_out"), "n_tokens", "n_known", F.lit(int(totals.n)).cast("long").alias("train_tokens"), "base_score", "score")


def _round(spark: SparkSession, work: Workspace, rows: DataFrame, totals: Totals, s: int, buckets: int) -> DataFrame:
    """Sweep s in every bucket (sweep 0 merges the dealt counts and seats one table for each pair), then the exchange.

    Returns the buckets' states (kind 0) with the shards' answers (kind 1), and adds the sweep to the totals.
    """
    shipped = spark.sparkContext.broadcast(totals)

    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by([("kind", "ascending"), ("shard", "ascending")])
        bucket, kinds = table.column("bucket")[0].as_py(), table.column("kind").to_pylist()
        blobs = [x.as_py() for x in table.column("blob")]
        if s == 0:
            state = State(merge_counts(blobs))
            own = state.load(bucket)
        else:
            state = unpack(blobs[kinds.index(0)])
            state.hear(blobs[kinds.index(1) :])
            own = state.load(bucket).sweep(shipped.value.local(state.customers, state.tables))
        state.seats = [small(x) for x in own.seats]
        state.forget()
        met, c, p = own.count > 0, own.c, own.parent[-1]
        is_hot = np.isin(own.words, shipped.value.hot)
        p_cold = p[~is_hot]
        sums = [c.sum(), p.sum(), (met & ~is_hot).sum(), (c == 1).sum(), (c == 2).sum(), (p_cold == 1).sum(), (p_cold == 2).sum()]
        hot = (own.words[is_hot], own.count[is_hot], p[is_hot])
        out = [(0, bucket, 0, pack(state)), (2, bucket, 0, pack(([int(x) for x in sums], hot)))]
        return rows_of(out + [(1, bucket, k, blob) for k, blob in state.messages(own, max(8, buckets // 8))])

    done = work.table(rows.groupBy("bucket").applyInArrow(run, ROWS), f"round{s}", ("kind",)).select("kind", "bucket", "shard", "blob")
    answers = work.table(done.where("kind = 1").groupBy("shard").applyInArrow(answer, ROWS), f"answers{s}")
    work.drop(f"round{s}/kind=1")
    sums, count, parent = np.zeros(7), np.zeros(len(totals.hot)), np.zeros(len(totals.hot))
    for r in done.where("kind = 2").select("blob").collect():  # a few numbers of each bucket
        some, (words, c, p) = unpack(r[0])
        sums += some
        at = np.searchsorted(totals.hot, words)
        count[at] += c
        parent[at] += p
    if s == 0:
        totals.n, totals.v, totals.hot_count = int(sums[0]), int(sums[2]) + int((count > 0).sum()), count
        for name, once, twice in (("d2", *sums[3:5]), ("d1", *sums[5:7])):
            setattr(totals, name, min(0.95, max(0.05, once / (once + 2 * twice))) if once else 0.5)
    totals.hot_parent.append(parent)
    totals.all_tables.append(float(sums[1]))
    return done.where("kind = 0").unionByName(answers)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score(spark, read_table(spark, sf_dir, "documents"))
