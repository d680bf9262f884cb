"""Packing of token ids into fixed windows: bounded-space online best fit.

Each partition keeps at most `open_windows` windows open. A document's tail goes to the open window that it fits
best; if none fits and no window may be opened, the fullest is topped up by a cut of the piece (or left with a gap
under `min_cut` tokens) and emitted. Windows still open at the end of a partition are merged, piece by piece, in
groups of GROUP partitions, so that no task sees more than GROUP * open_windows of them.

Defined cases: a null or empty text is its end id alone; a row without doc_id is packed like any other (doc_id null);
repeated rows are packed once each; an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

import unicodedata
import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Workspace, read_table

WINDOW = 4096
END_ID = 2
GROUP = 32
SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
NAMES = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]
#: Words of at most this many characters are remembered, and so many of them.
CACHED_CHARS, CACHED_WORDS = 48, 1_500_000


def tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def _byte_alphabet() -> dict[int, str]:
    """The usual byte-level alphabet: printable bytes stand for themselves, the others for code points from 256."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    out = {b: chr(b) for b in plain}
    for i, b in enumerate(b for b in range(256) if b not in out):
        out[b] = chr(256 + i)
    return out


class Encoder:
    """Ids of whole texts, as little-endian 32-bit bytes, by way of a bounded cache of white-space-free chunks.

    This vocabulary's pieces never reach over white space, so a text's ids are those of its chunks in order.
    A chunk of Latin letters is one piece and goes to the model itself; letters with one full stop or comma are
    two pieces; all others go through the whole tokenizer.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.full = Tokenizer.from_file(path)
        self.model = self.full.model
        self.cache: dict[str, bytes] = {"": b""}
        self.letters = {b: c for b, c in _byte_alphabet().items()}

    def ids(self, text: str) -> bytes:
        words = text.replace("\n", " ").split(" ")
        cache = self.cache
        try:
            return b"".join([cache[w] for w in words])
        except KeyError:
            return b"".join([cache[w] if w in cache else self._add(w) for w in words])

    def _add(self, chunk: str) -> bytes:
        ids = self._chunk(chunk)
        if len(chunk) <= CACHED_CHARS:
            if len(self.cache) >= CACHED_WORDS:
                self.cache = {"": b""}
            self.cache[chunk] = ids
        return ids

    def _chunk(self, chunk: str) -> bytes:
        if len(chunk) <= CACHED_CHARS and max(chunk) < "İ":
            if chunk[-1] in ".," and chunk[:-1].isalpha():
                return self._word(chunk[:-1]) + self._word(chunk[-1])
            if chunk.isalpha():
                return self._word(chunk)
        return np.array(self.full.encode(chunk, add_special_tokens=False).ids, dtype="<u4").tobytes()

    def _word(self, word: str) -> bytes:
        word = unicodedata.normalize("NFC", word).lower()
        if (known := self.cache.get(word)) is not None:
            return known
        piece = word if word.isascii() else "".join([self.letters[b] for b in word.encode()])
        ids = np.array([t.id for t in self.model.tokenize(piece)], dtype="<u4").tobytes()
        if len(self.cache) < CACHED_WORDS:
            self.cache[word] = ids
        return ids


class Packer:
    """At most `most` open windows; every placed piece is (doc_id, start, length, crc, doc_tokens)."""

    def __init__(self, window: int, most: int, min_cut: int, first_id: int):
        self.window, self.most, self.min_cut, self.next_id = window, most, min_cut, first_id
        self.open: list[list] = []  # [used, pieces]
        self.done: list[tuple] = []

    def document(self, doc_id, ids: bytes) -> None:
        n = len(ids) // 4
        at = 0
        while n - at >= self.window:
            self._emit([self._piece(doc_id, ids, at, self.window, n)])
            at += self.window
        while at < n:
            at += self._place(doc_id, ids, at, n)

    @staticmethod
    def _piece(doc_id, ids: bytes, at: int, length: int, n: int) -> tuple:
        return doc_id, at, length, zlib.crc32(ids[4 * at : 4 * (at + length)]), n

    def _place(self, doc_id, ids: bytes, at: int, n: int) -> int:
        rest = n - at
        fits = [w for w in self.open if self.window - w[0] >= rest]
        if fits:
            self._put(max(fits, key=lambda w: w[0]), self._piece(doc_id, ids, at, rest, n))
            return rest
        if len(self.open) < self.most:
            self.open.append([0, []])
            self._put(self.open[-1], self._piece(doc_id, ids, at, rest, n))
            return rest
        fullest = max(self.open, key=lambda w: w[0])
        gap = self.window - fullest[0]
        if gap >= self.min_cut:
            self._put(fullest, self._piece(doc_id, ids, at, gap, n))
            return gap
        self._close(fullest)
        return 0

    def _put(self, w: list, piece: tuple) -> None:
        w[0] += piece[2]
        w[1].append(piece)
        if w[0] == self.window:
            self._close(w)

    def _close(self, w: list) -> None:
        self.open = [x for x in self.open if x is not w]
        self._emit(w[1])

    def _emit(self, pieces: list[tuple]) -> None:
        offset = 0
        for p in pieces:
            self.done.append((*p, self.next_id, offset))
            offset += p[2]
        self.next_id += 1


def merge_leftovers(pieces: list[tuple], window: int, first_id: int) -> list[tuple]:
    """Best-fit decreasing over whole pieces of one bounded group."""
    import bisect

    room: list[tuple[int, int]] = []  # (gap, bin), sorted
    bins: list[list[tuple]] = []
    for p in sorted(pieces, key=lambda p: (-p[2], p[0] is None, p[0] or 0, p[1], p[3])):
        k = bisect.bisect_left(room, (p[2], -1))
        if k < len(room):
            gap, b = room.pop(k)
        else:
            gap, b = window, len(bins)
            bins.append([])
        bins[b].append(p)
        bisect.insort(room, (gap - p[2], b))
    out = []
    for b, content in enumerate(bins):
        offset = 0
        for p in content:
            out.append((*p, first_id + b, offset))
            offset += p[2]
    return out


def _batch(rows: list[tuple], left: bool | None = None, group: int = 0) -> pa.RecordBatch:
    cols = list(zip(*rows, strict=True)) if rows else [[] for _ in NAMES]
    arrays, names = [pa.array(list(c), pa.int64()) for c in cols], list(NAMES)
    if left is not None:
        arrays += [pa.array([left] * len(rows), pa.bool_()), pa.array([group] * len(rows), pa.int64())]
        names += ["left", "grp"]
    return pa.RecordBatch.from_arrays(arrays, names)


def pack(spark: SparkSession, docs: DataFrame, path: str | None = None, window: int = WINDOW, open_windows: int = 8, min_cut: int = 64) -> DataFrame:
    """One row per piece."""
    path = path or tokenizer_path()

    def fill(batches):
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        encoder, end = Encoder(path), np.array([END_ID], "<u4").tobytes()
        part = TaskContext.get().partitionId()
        packer = Packer(window, open_windows, min_cut, part << 32)
        for batch in batches:
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                packer.document(doc_id, encoder.ids(text.as_py() or "") + end)
                if len(packer.done) >= 20_000:
                    yield _batch(packer.done, False)
                    packer.done = []
        yield _batch(packer.done, False)
        yield _batch([(*p, 0, 0) for w in packer.open for p in w[1]], True, part // GROUP)

    def merge(table: pa.Table) -> pa.Table:
        group = table.column("grp")[0].as_py()
        rows = [tuple(r[c] for c in NAMES[:5]) for r in table.to_pylist()]
        return pa.Table.from_batches([_batch(merge_leftovers(rows, window, (1 << 60) + (group << 32)))])

    work = Workspace(spark, "packing")
    placed = work.table(docs.select("doc_id", "text").mapInArrow(fill, SCHEMA + ", left boolean, grp long"), "placed")
    left = placed.where("left").groupBy("grp").applyInArrow(merge, SCHEMA)
    return placed.where(~F.col("left")).select(*NAMES).unionByName(left)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(spark, read_table(spark, sf_dir, "documents"))


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: the packed pieces of every document that is left."""
    return pack(spark, docs)
