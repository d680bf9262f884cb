"""Shared plumbing: table readers, the shared work folder, and vectorised tokens and hashes over Arrow text buffers."""

from __future__ import annotations

import atexit
import contextlib
import gc
import tempfile
import time
import uuid

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

# The white space of the contracts, [\x20\x09-\x0D].
SPACE_CHARS = "\x20\x09\x0a\x0b\x0c\x0d"
SPACE = np.zeros(256, dtype=bool)
SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
#: Bytes outside words when punctuation does not count: ASCII that is neither letter nor digit.
PUNCT = np.array([i < 128 and not chr(i).isalnum() for i in range(256)])
UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

#: Bytes of text that one numpy pass takes at a time (a longer document is a pass of its own).
CHUNK_BYTES = (1 << 19) - 64


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ascii_lower(col):
    """Lower-case A-Z only, whatever the locale."""
    return F.translate(col, UPPER, UPPER.lower())


def id_bucket(col, n: int):
    """crc32 of the id written as text, modulo n: the fold rule of the contracts."""
    return F.pmod(F.crc32(col.cast("string").cast("binary")), F.lit(n))


class Workspace:
    """Tables in the folder that driver and executors share (spark.checkpoint.dir).

    A lost executor costs nothing that is written here. On a local master without the setting, a folder
    of its own is made; on a cluster the setting is required.
    """

    def __init__(self, spark: SparkSession, label: str):
        self.spark = spark
        base = spark.conf.get("spark.checkpoint.dir", None)
        if not base:
            if not spark.sparkContext.master.startswith("local"):
                raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
            base = "file://" + tempfile.mkdtemp(prefix="objdelta-")
        self.root = f"{base.rstrip('/')}/objdelta-{label}-{uuid.uuid4().hex}"
        atexit.register(self.close)

    def table(self, df: DataFrame, name: str, partition_by: tuple[str, ...] = ()) -> DataFrame:
        """Write df once and read it back: the lineage ends at the files."""
        path = f"{self.root}/{name}"
        writer = df.write.option("compression", "zstd")
        (writer.partitionBy(*partition_by) if partition_by else writer).parquet(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def drop(self, *names: str) -> None:
        """Delete tables that no later plan reads."""
        for name in names:
            self._delete(f"{self.root}/{name}")

    def release(self) -> None:
        """Let Spark's cleaner delete the shuffle files of plans that are no longer referenced."""
        for _ in range(2):  # Python's references go first, the cleaner follows the JVM's collection
            gc.collect()
            self.spark.sparkContext._jvm.System.gc()
            time.sleep(0.5)

    def close(self) -> None:
        with contextlib.suppress(Exception):
            self._delete(self.root)

    def _delete(self, path: str) -> None:
        sc = self.spark.sparkContext
        p = sc._jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(sc._jsc.hadoopConfiguration()).delete(p, True)


# ---------------------------------------------------------------- text buffers


def text_buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of all texts in one array, and where each begins; a null text is empty."""
    arr = pc.fill_null(column, b"" if pa.types.is_binary(column.type) else "")
    if isinstance(arr, pa.ChunkedArray):
        arr = arr.combine_chunks()
    arr = arr.cast(pa.large_binary())
    offsets = np.frombuffer(arr.buffers()[1], dtype=np.int64)[arr.offset : arr.offset + len(arr) + 1] if len(arr) else np.zeros(1, np.int64)
    raw = arr.buffers()[2]
    data = np.frombuffer(raw, dtype=np.uint8) if raw is not None else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def chunks(data: np.ndarray, offsets: np.ndarray, most: int = CHUNK_BYTES):
    """(first row, bytes, offsets) of runs of whole texts of about `most` bytes."""
    n, i = len(offsets) - 1, 0
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + most, side="right")) - 1)
        j = min(j, n)
        yield i, data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]
        i = j


# ---------------------------------------------------------------- hashes

_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
_INVERSE = np.uint64(pow(int(_BASE), -1, 1 << 64))
_powers = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def _power_table(n: int) -> tuple[np.ndarray, np.ndarray]:
    """BASE**i and its inverse modulo 2**64, for i < n at least."""
    if len(_powers[0]) < n:
        size = 1 << max(12, int(n - 1).bit_length())
        for k, base in enumerate((_BASE, _INVERSE)):
            steps = np.full(size, base, np.uint64)
            steps[0] = 1
            _powers[k] = np.multiply.accumulate(steps)
    return _powers[0], _powers[1]


def mix(h: np.ndarray) -> np.ndarray:
    """Spread a 64-bit value over all bits (a public finaliser of the xor-shift-multiply kind)."""
    h = h ^ (h >> np.uint64(33))
    h = h * np.uint64(0xFF51AFD7ED558CCD)
    h = h ^ (h >> np.uint64(33))
    h = h * np.uint64(0xC4CEB9FE1A85EC53)
    return h ^ (h >> np.uint64(33))


def prefix_sums(data: np.ndarray) -> np.ndarray:
    """sums[i]: the polynomial of the first i bytes."""
    power, _ = _power_table(len(data) + 1)
    sums = np.empty(len(data) + 1, np.uint64)
    sums[0] = 0
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * power[: len(data)], out=sums[1:])
    return sums


def span_hashes(sums: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Hash of bytes[start:end], the same wherever those bytes stand."""
    _, inverse = _power_table(len(sums))
    return mix((sums[end] - sums[start]) * inverse[start] + (end - start).astype(np.uint64))


def slide_hashes(sums: np.ndarray, k: int) -> np.ndarray:
    """span_hashes of every k consecutive bytes."""
    n = len(sums) - k
    _, inverse = _power_table(len(sums))
    return mix((sums[k:] - sums[:n]) * inverse[:n] + np.uint64(k))


def word_bounds(data: np.ndarray, offsets: np.ndarray, gap: np.ndarray = SPACE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start, end and text number of every maximal run of bytes that `gap` does not mark; by default [^\\x20\\x09-\\x0D]+."""
    n = len(data)
    if not n:
        z = np.zeros(0, np.int64)
        return z, z, z
    inside = ~gap[data]
    first = np.zeros(n + 1, bool)
    first[offsets] = True
    begin = inside.copy()
    begin[1:] &= ~inside[:-1] | first[1:n]
    last = inside.copy()
    last[:-1] &= ~inside[1:] | first[1:n]
    start, end = np.flatnonzero(begin), np.flatnonzero(last) + 1
    return start, end, np.searchsorted(offsets, start, side="right") - 1


def word_hashes(data: np.ndarray, offsets: np.ndarray, gap: np.ndarray = SPACE) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hash (A-Z lower-cased) and text number of every word."""
    low = LOWER[data]
    start, end, owner = word_bounds(low, offsets, gap)
    return span_hashes(prefix_sums(low), start, end), owner


def shingle_hashes(data: np.ndarray, offsets: np.ndarray, k: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Hash and text number of every k-word shingle; fewer words than k: the whole sequence as one; no word: none."""
    words, owner = word_hashes(data, offsets)
    n_texts = len(offsets) - 1
    count = np.bincount(owner, minlength=n_texts).astype(np.int64)
    base = np.uint64(0xD6E8FEB86659FD93)
    out = np.zeros(max(0, len(words) - k + 1), np.uint64)
    for j in range(k):
        out = out * base + words[j : j + len(out)]
    full = owner[: len(out)] == owner[k - 1 :] if len(out) else np.zeros(0, bool)
    h, who = mix(out[full] + np.uint64(k)), owner[: len(out)][full]
    short = np.flatnonzero((count > 0) & (count < k))
    if len(short):
        at = np.concatenate([[0], np.cumsum(count)])
        hs = np.zeros(len(short), np.uint64)
        for i, t in enumerate(short):
            acc = 0
            for w in words[at[t] : at[t + 1]]:
                acc = (acc * int(base) + int(w)) & 0xFFFFFFFFFFFFFFFF
            hs[i] = acc
        h = np.concatenate([h, mix(hs + count[short].astype(np.uint64))])
        who = np.concatenate([who, short])
    return h, who
