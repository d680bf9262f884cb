"""Quality of a document from a linear-chain conditional random field over its lines.

Every line is good or bad; its features are byte statistics of the line and of its neighbours. Weights are fitted on
at most `max_docs` labelled documents, whose label stands for each of their lines. The marginals of forward-backward,
weighted by the lines' lengths, are averaged over the document and calibrated to a probability.

Defined cases: a null or empty text is one empty line and is scored like any other; without labelled rows every
score is 0.5; null labels are ignored; repeated rows are scored once each; rows without doc_id are scored and count as
not held out; an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import SPACE, chunks, id_bucket, read_table, span_hashes, prefix_sums, text_buffers, word_bounds

FOLD, THRESHOLD, MAX_DOCS = 5, 0.3, 3000
_KIND = np.zeros((5, 256), bool)
_KIND[0, [*range(48, 58)]] = True
_KIND[1, [*range(65, 91)]] = True
_KIND[2, [*range(97, 123), *range(128, 256)]] = True
_KIND[3] = SPACE
_KIND[4] = ~(_KIND[0] | _KIND[1] | _KIND[2] | _KIND[3])
N_OWN = 13


def line_features(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(features, lengths in bytes, lines per text) of all lines of some texts."""
    n_texts = len(offsets) - 1
    breaks = np.flatnonzero(data == 10)
    owner = np.searchsorted(offsets, breaks, side="right") - 1
    counts = np.bincount(owner, minlength=n_texts) + 1
    first = np.zeros(n_texts, np.int64)
    np.cumsum(counts[:-1], out=first[1:])
    total = int(counts.sum())
    start = np.empty(total, np.int64)
    start[first] = offsets[:-1]
    inner = np.ones(total, bool)
    inner[first] = False
    start[inner] = breaks + 1
    end = np.empty(total, np.int64)
    end[first + counts - 1] = offsets[1:]
    last = np.ones(total, bool)
    last[first + counts - 1] = False
    end[last] = breaks
    length = end - start
    size = np.maximum(length, 1).astype(np.float64)

    sums = np.zeros((5, len(data) + 1), np.int32)
    for k in range(5):
        np.cumsum(_KIND[k][data], out=sums[k, 1:])
    share = (sums[:, end] - sums[:, start]) / size
    ws, we, _ = word_bounds(data, offsets)
    wh = span_hashes(prefix_sums(data), ws, we)
    lo, hi = np.searchsorted(ws, start), np.searchsorted(ws, end)
    words = np.maximum(hi - lo, 1).astype(np.float64)

    def per_line(values: np.ndarray) -> np.ndarray:
        acc = np.concatenate([[0.0], np.cumsum(values)])
        return acc[hi] - acc[lo]

    alpha = np.zeros(len(data) + 1, np.int32)
    np.cumsum((_KIND[1] | _KIND[2])[data], out=alpha[1:])
    pure = (alpha[we] - alpha[ws]) == 0
    again = np.zeros(len(ws))
    again[1:] = wh[1:] == wh[:-1]
    line_of = np.repeat(np.arange(total), hi - lo)
    order = np.lexsort((wh, line_of))
    twin = np.zeros(len(ws))
    twin[1:] = (wh[order][1:] == wh[order][:-1]) & (line_of[order][1:] == line_of[order][:-1])
    wide = per_line((we - ws).astype(np.float64)) / words
    ends = np.isin(data[np.maximum(end - 1, 0)], np.frombuffer(b".!?", np.uint8)) if len(data) else np.zeros(total, bool)
    own = np.stack(
        [np.log1p(length) / 8, *share, np.log1p(hi - lo) / 6, np.minimum(wide, 40) / 20, per_line(pure) / words, per_line(again) / words, per_line(twin) / words, (ends & (length > 0)).astype(float), (length == 0).astype(float)],
        axis=1,
    )
    before = np.zeros_like(own)
    before[1:] = own[:-1]
    before[first] = 0
    after = np.zeros_like(own)
    after[:-1] = own[1:]
    after[first + counts - 1] = 0
    edge = np.zeros((total, 2))
    edge[first, 0] = 1
    edge[first + counts - 1, 1] = 1
    square = own[:, [1, 3, 5, 8, 9, 10]] ** 2
    return np.concatenate([own, square, before, after, edge, np.ones((total, 1))], axis=1), length, counts


def marginals(unary: np.ndarray, trans: np.ndarray, counts: np.ndarray, want_pairs: bool = False):
    """P(good) of every line by forward-backward in log space, all documents at once, step by step.

    unary: score of 'good' against 'bad' for each line; trans: 2 x 2. With want_pairs, also the sum of the pair
    marginals over all documents.
    """
    n = len(counts)
    order = np.argsort(-counts, kind="stable")
    size = counts[order]
    base = np.concatenate([[0], np.cumsum(counts)])[:-1][order]
    longest = int(size[0]) if n else 0
    active = np.searchsorted(-size, -np.arange(longest), side="left")  # texts with more than t lines
    score = np.stack([np.zeros_like(unary), unary], axis=1)
    alpha, beta = np.empty_like(score), np.zeros_like(score)
    e = trans[None]
    if n:
        alpha[base] = score[base]
    for t in range(1, longest):
        at = base[: active[t]] + t
        alpha[at] = np.logaddexp.reduce(alpha[at - 1][:, :, None] + e, axis=1) + score[at]
    for t in range(longest - 2, -1, -1):
        at = base[: active[t + 1]] + t
        beta[at] = np.logaddexp.reduce(e + (score[at + 1] + beta[at + 1])[:, None, :], axis=2)
    both = alpha + beta
    good = 1 / (1 + np.exp(np.clip(both[:, 0] - both[:, 1], -500, 500)))
    if not want_pairs:
        return good
    inner = np.ones(len(unary), bool)
    inner[base] = False
    at = np.flatnonzero(inner)
    pair = alpha[at - 1][:, :, None] + e + (score[at] + beta[at])[:, None, :]
    pair = np.exp(pair - np.logaddexp.reduce(pair.reshape(len(at), 4), axis=1)[:, None, None]) if len(at) else np.zeros((0, 2, 2))
    return good, pair.sum(axis=0)


class LineField:
    """Fitted weights; picklable and of fixed size."""

    def __init__(self, weights=None, trans=None, mean=None, scale=None, calibration=(0.0, 0.0)):
        self.weights, self.trans, self.mean, self.scale, self.calibration = weights, trans, mean, scale, calibration

    def fit(self, x: np.ndarray, length: np.ndarray, counts: np.ndarray, label: np.ndarray, rounds: int = 150) -> LineField:
        self.mean, self.scale = x.mean(axis=0), x.std(axis=0) + 1e-6
        self.mean[-1], self.scale[-1] = 0, 1
        z = (x - self.mean) / self.scale
        y = np.repeat(label, counts).astype(float)
        share = np.array([(label == v).sum() for v in (0, 1)], float)
        per_doc = (len(label) / (2 * np.maximum(share, 1)))[label]
        weight = np.repeat(per_doc / counts, counts)  # each document counts once, each label alike
        params = np.zeros(z.shape[1] + 4)
        m, v = np.zeros_like(params), np.zeros_like(params)
        n_pairs = max(1, int((counts - 1).sum()))
        truth = np.zeros((2, 2))
        for k in (0, 1):
            truth[k, k] = (counts[label == k] - 1).sum()
        for r in range(1, rounds + 1):
            good, pairs = marginals(z @ params[:-4], params[-4:].reshape(2, 2), counts, True)
            g = np.concatenate([z.T @ (weight * (good - y)) / len(label), (0.2 * (pairs - truth) / n_pairs).ravel()])
            g += 1e-4 * params
            m, v = 0.9 * m + 0.1 * g, 0.99 * v + 0.01 * g * g
            params -= 0.15 / (1 + r / 60) * (m / (1 - 0.9**r)) / (np.sqrt(v / (1 - 0.99**r)) + 1e-9)
        self.weights, self.trans = params[:-4], params[-4:].reshape(2, 2)
        raw = self._raw(x, length, counts)
        a, b = 1.0, 0.0
        for _ in range(50):  # Newton steps of a one-feature logistic regression
            p = 1 / (1 + np.exp(-np.clip(a * raw + b, -30, 30)))
            s, d = np.maximum(p * (1 - p), 1e-6), p - label
            h = np.array([[(s * raw * raw).sum() + 1e-3, (s * raw).sum()], [(s * raw).sum(), s.sum() + 1e-3]])
            step = np.linalg.solve(h, np.array([(d * raw).sum() + 1e-3 * (a - 1), d.sum()]))
            a, b = a - step[0], b - step[1]
        self.calibration = (float(a), float(b))
        return self

    def _raw(self, x: np.ndarray, length: np.ndarray, counts: np.ndarray) -> np.ndarray:
        good = marginals(((x - self.mean) / self.scale) @ self.weights, self.trans, counts)
        w = (length + 1).astype(float)
        first = np.concatenate([[0], np.cumsum(counts)])[:-1]
        p = np.add.reduceat(good * w, first) / np.add.reduceat(w, first) if len(counts) else np.zeros(0)
        p = np.clip(p, 1e-4, 1 - 1e-4)
        return np.log(p / (1 - p))

    def score(self, x: np.ndarray, length: np.ndarray, counts: np.ndarray) -> np.ndarray:
        if self.weights is None:
            return np.full(len(counts), 0.5)
        a, b = self.calibration
        return 1 / (1 + np.exp(-np.clip(a * self._raw(x, length, counts) + b, -30, 30)))


def fit(docs: DataFrame, labels: DataFrame, max_docs: int = MAX_DOCS) -> LineField:
    """From at most max_docs labelled documents outside the held-out fold, chosen by a hash of the id."""
    rows = (
        labels.where(F.col("quality").isNotNull() & F.col("doc_id").isNotNull() & (id_bucket(F.col("doc_id"), FOLD) != 0))
        .select("doc_id", F.col("quality").cast("int").alias("quality"))
        .groupBy("doc_id").agg(F.max("quality").alias("quality"))
        .orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_docs)
    )
    sample = docs.select("doc_id", "text").join(F.broadcast(rows), "doc_id").orderBy(F.xxhash64("doc_id"), "doc_id", "text").limit(max_docs).select("text", "quality").collect()
    if len({r[1] for r in sample}) < 2:
        return LineField()
    parts = []
    for r in sample:
        data = np.frombuffer((r[0] or "").encode(), np.uint8)
        parts.append(line_features(data, np.array([0, len(data)])))
    x, length, counts = (np.concatenate(p) for p in zip(*parts, strict=True))
    return LineField().fit(x, length, counts, np.array([r[1] for r in sample]))


def score(spark: SparkSession, docs: DataFrame, labels: DataFrame, max_docs: int = MAX_DOCS, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, held_out, score, predicted for every document."""
    model = spark.sparkContext.broadcast(fit(docs, labels, max_docs))

    def run(batches):
        for batch in batches:
            data, offsets = text_buffers(batch.column(1))
            out = [model.value.score(*line_features(part, offs)) for _, part, offs in chunks(data, offsets)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.concatenate(out) if out else np.zeros(0), pa.float64())], ["doc_id", "score"])

    doc_id = F.col("doc_id").cast("long")
    scored = docs.select(doc_id.alias("doc_id"), "text").mapInArrow(run, "doc_id long, score double")
    held = F.coalesce(id_bucket(F.col("doc_id"), FOLD) == 0, F.lit(False))
    return scored.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score(spark, read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels"))
