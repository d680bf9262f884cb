"""Toxicity by a weighted finite-state grammar of clauses.

Two transducers are composed. The lexicon transducer reads characters and writes word classes (insult, threat,
target, negation, reported speech); its insult arcs are a fixed word list and stems learned from labels. The clause
transducer reads classes and writes kinds of matched clauses: an insult that is plain, aimed at a target, negated or
reported, and a threat that is plain or aimed. Each kind has a weight; a document's score is the logistic of the
weighted kinds that its clauses match. Words outside a matching clause weigh nothing.

At most `max_toxic` + `max_clean` labelled documents outside the held-out fold are read for fitting. Near copies
among them count once, so that a stem isn't learned from one text's copies.

Defined cases: a null or empty text matches nothing and gets the score of such texts; without labels the fixed word
list and default weights hold; null labels are ignored; repeated rows are scored once each; rows without doc_id
are scored and count as not held out; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import math
import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import id_bucket, read_table

FOLD, THRESHOLD, MAX_TOXIC, MAX_CLEAN, MAX_STEMS = 3, 0.7, 1500, 2500, 2000

# Word lists of the lexicon.
INSULTS = "idiot moron loser scum trash clown stupid pathetic worthless disgusting imbecile jerk fool dumb filth vermin bastard".split()
THREATS = "kill hurt destroy beat smash punish stab shoot crush".split()
TARGETS = "you your yours yourself he him she her they them du dich ihr tu te vous usted ustedes".split()
NEGATIONS = "not no never isn't aren't wasn't don't nicht kein keine pas jamais nunca".split()
REPORTS = "said says called calls claimed wrote told quoted sagte dit dijo".split()
# The default weights of the clause kinds, used when there are no labels.
KINDS = ("plain", "aimed", "negated", "reported", "threat", "aimed_threat")
DEFAULT = {"plain": 5.0, "aimed": 6.0, "negated": 0.5, "reported": 1.0, "threat": 0.3, "aimed_threat": 4.0}
DEFAULT_BIAS = -2.5

CLAUSE_END = re.compile(r"[.!?;:\n]+")
WORD = re.compile(r"[^\W\d_]+(?:'[^\W\d_]+)?")

# The clause transducer: state -> class -> (next state, kind written). States: 0 start, 1 target seen, 2 negated,
# 3 reported; classes: i insult, t threat, g target, n negation, r reported speech.
ARCS = {
    0: {"i": (0, "plain"), "t": (0, "threat"), "g": (1, None), "n": (2, None), "r": (3, None)},
    1: {"i": (1, "aimed"), "t": (1, "aimed_threat"), "g": (1, None), "n": (2, None), "r": (3, None)},
    2: {"i": (0, "negated"), "t": (0, None), "g": (2, None), "n": (0, None), "r": (3, None)},
    3: {"i": (3, "reported"), "t": (3, None), "g": (3, None), "n": (3, None), "r": (3, None)},
}
#: A negation reaches over so many plain words.
REACH = 3


class Grammar:
    """The composed transducers with their weights; small and picklable."""

    def __init__(self, stems: dict[str, float] | None = None, weights: dict[str, float] | None = None, bias: float = DEFAULT_BIAS):
        self.stems = stems or {}
        self.weights, self.bias = weights or dict(DEFAULT), bias
        self._triggers = None

    def __getstate__(self):
        return self.__dict__ | {"_triggers": None}

    def _build(self):
        import ahocorasick

        self.words = {w: c for c, ws in (("g", TARGETS), ("n", NEGATIONS), ("r", REPORTS), ("t", THREATS), ("i", INSULTS)) for w in ws}
        self.lengths = sorted({len(s) for s in self.stems})
        found = ahocorasick.Automaton()
        for w in (*INSULTS, *THREATS, *self.stems):
            found.add_word(w, len(w))
        found.make_automaton()
        self._triggers = found

    def classify(self, word: str) -> tuple[str | None, float]:
        """Lexicon transducer: class and weight of a word."""
        c = self.words.get(word)
        if c is None:
            for n in self.lengths:
                if (s := self.stems.get(word[:n])) is not None and len(word) >= n:
                    return "i", s
        return c, 1.0

    def clauses(self, low: str):
        """The clauses that hold a trigger at the start of a word."""
        if self._triggers is None:
            self._build()
        done = -1
        for last, n in self._triggers.iter(low):
            at = last - n + 1
            if at < done or (at and (low[at - 1].isalpha() or low[at - 1] == "'")):
                continue
            begin = max(low.rfind(ch, 0, at) for ch in ".!?;:\n") + 1
            stop = CLAUSE_END.search(low, last)
            done = stop.start() if stop else len(low)
            yield low[begin:done]

    def kinds(self, text: str) -> dict[str, float]:
        """Weight of the matched clauses by kind."""
        out: dict[str, float] = {}
        for clause in self.clauses(text.lower()):
            state, since = 0, 0
            for word in WORD.findall(clause):
                c, weight = self.classify(word)
                if c is None:
                    since += 1
                    if state == 2 and since > REACH:
                        state = 0
                    continue
                since = 0
                state, kind = ARCS[state][c]
                if kind:
                    out[kind] = out.get(kind, 0.0) + weight
        return out

    def features(self, text: str) -> np.ndarray:
        got = self.kinds(text)
        return np.array([math.log1p(got.get(k, 0.0)) for k in KINDS])

    def score(self, text: str) -> float:
        z = self.bias + sum(self.weights[k] * math.log1p(v) for k, v in self.kinds(text).items())
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, z))))


def _distinct_docs(rows: list[tuple[str, int]]) -> list[tuple[set[str], int, str]]:
    """(words, label, text) of documents that aren't near copies of one before with the same label: of the minima of
    three hash functions over their three-word runs, at most one has been seen."""
    import xxhash

    seen: set[tuple[int, int, int]] = set()
    out = []
    for text, label in rows:
        w = text.lower().split()
        grams = {" ".join(w[i : i + 3]) for i in range(max(1, len(w) - 2))}
        marks = [(label, s, min(xxhash.xxh64_intdigest(g, s) for g in grams)) for s in (1, 2, 3)]
        if sum(m in seen for m in marks) < 2:
            out.append((set(WORD.findall(text.lower())), label, text))
        seen.update(marks)
    return out


def learn_stems(docs: list[tuple[set[str], int, str]], most: int = MAX_STEMS) -> dict[str, float]:
    """Word beginnings of 4 to 7 letters that documents labelled 1 have and the others lack (by log-likelihood ratio)."""
    size = Counter(label for _, label, _ in docs)
    a, b = size[1], size[0]
    if not a or not b:
        return {}

    def parts(words):
        return {w[:n] for w in words for n in (4, 5, 6, 7) if len(w) >= n}

    toxic = Counter()
    for words, label, _ in docs:
        if label:
            toxic.update(parts(words))
    toxic = Counter({s: n for s, n in toxic.items() if n >= max(4, 0.01 * a)})
    clean = Counter()
    for words, label, _ in docs:
        if not label:
            clean.update(s for s in parts(words) if s in toxic)
    out: dict[str, float] = {}
    for s in sorted(toxic, key=lambda s: (len(s), s)):
        x, y = toxic[s], clean[s]
        if x / a < 20 * (y + 0.5) / b or any(s[:n] in out for n in range(4, len(s))):
            continue
        p = (x + y) / (a + b)
        g2 = 2 * (x * math.log(x / (a * p)) + (y * math.log(y / (b * p)) if y else 0))
        if g2 >= 20:
            out[s] = 1.0
    return dict(list(out.items())[:most])


def fit(docs: DataFrame, labels: DataFrame, max_toxic: int = MAX_TOXIC, max_clean: int = MAX_CLEAN) -> Grammar:
    known = (
        labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & (id_bucket(F.col("doc_id"), FOLD) != 1))
        .groupBy("doc_id").agg(F.max(F.col("toxic").cast("int")).alias("toxic"))
    )
    rows = []
    for value, most in ((1, max_toxic), (0, max_clean)):
        ids = known.where(F.col("toxic") == value).orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
        got = docs.select("doc_id", "text").join(F.broadcast(ids), "doc_id").orderBy(F.xxhash64("doc_id"), "doc_id", "text").limit(most).collect()
        rows += [(r[1] or "", value) for r in got]
    if len({v for _, v in rows}) < 2:
        return Grammar()
    sample = _distinct_docs(rows)
    grammar = Grammar(learn_stems(sample))
    x = np.array([grammar.features(t) for _, _, t in sample])
    y = np.array([v for _, v, _ in sample], float)
    w, bias = np.array([DEFAULT[k] for k in KINDS]), DEFAULT_BIAS
    prior = w.copy()
    for step in range(400):  # gradient descent towards the labels, held near the default weights
        p = 1 / (1 + np.exp(-np.clip(x @ w + bias, -30, 30)))
        w -= 2.0 * (x.T @ (p - y) / len(y) + 1e-3 * (w - prior))
        bias -= 2.0 * (p - y).mean()
    grammar.weights, grammar.bias = dict(zip(KINDS, w.tolist(), strict=True)), float(bias)
    return grammar


def score(spark: SparkSession, docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD, **bounds) -> DataFrame:
    """doc_id, held_out, score, predicted for every document."""
    grammar = spark.sparkContext.broadcast(fit(docs, labels, **bounds))

    def run(batches):
        for batch in batches:
            scores = [grammar.value.score(t.as_py() or "") for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(scores, pa.float64())], ["doc_id", "score"])

    scored = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, score double")
    held = F.coalesce(id_bucket(F.col("doc_id"), FOLD) == 1, F.lit(False))
    return scored.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score(spark, read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels"))


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: documents scored toxic go; same columns."""
    grammar = spark.sparkContext.broadcast(fit(docs, read_table(spark, sf_dir, "labels")))
    at = docs.columns.index("text")

    def run(batches):
        for batch in batches:
            yield batch.filter(pa.array([grammar.value.score(t.as_py() or "") < THRESHOLD for t in batch.column(at)], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
