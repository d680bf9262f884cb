"""Bit filters of bounded size: membership of 64-bit keys without a miss, built piece by piece on the executors."""

from __future__ import annotations

import uuid
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bits of a filter (2**27 bits are 16 MB) and its pieces.
FILTER_BITS, FILTER_PIECES = 27, 1024
#: Bits for each key that a filter should have, and bits of the largest filter (2**30 bits are 128 MB).
KEY_BITS, MOST_BITS = 8, 30


def _slots(key: np.ndarray, per_piece: int):
    for shift in (14, 37):
        yield ((key >> np.uint64(shift)) % np.uint64(per_piece)).astype(np.int64)


def piece_of(key: np.ndarray, pieces: int = FILTER_PIECES) -> np.ndarray:
    return key.view(np.int64) % pieces


def set_bits(key: np.ndarray, per_piece: int) -> np.ndarray:
    """One piece of a filter with the bits of its keys."""
    field = np.zeros(per_piece // 8, np.uint8)
    for slot in _slots(key, per_piece):
        np.bitwise_or.at(field, slot >> 3, (1 << (slot & 7)).astype(np.uint8))
    return field


def bits_for(keys: int, least: int = FILTER_BITS, most: int = MOST_BITS) -> int:
    """Bits of a filter that lets under a twentieth of foreign keys pass, up to the largest filter."""
    return max(least, min(most, (max(1, keys) * KEY_BITS - 1).bit_length()))


def build_filter(keys: DataFrame, bits: int = FILTER_BITS, pieces: int = FILTER_PIECES, rounds: int = 1, head: bytes = b"") -> np.ndarray:
    """Two bits for each value of keys.key; every piece of the filter is made by one task from its own keys.

    With several rounds the driver takes in that part of a large filter at a time; keys is then read as often.
    The bytes of head stand before the filter.
    """
    per_piece = (1 << bits) // pieces

    def piece(table: pa.Table) -> pa.Table:
        field = set_bits(table.column("key").to_numpy().view(np.uint64), per_piece)
        return pa.table({"piece": pa.array([table.column("piece")[0].as_py()], pa.int32()), "field": pa.array([field.tobytes()], pa.binary())})

    named = keys.select("key", F.pmod(F.col("key"), F.lit(pieces)).cast("int").alias("piece"))
    out = np.zeros(len(head) + (1 << (bits - 3)), np.uint8)
    out[: len(head)] = np.frombuffer(head, np.uint8)
    field = out[len(head) :]
    for i in range(rounds):
        part = named if rounds == 1 else named.where(F.col("piece") % rounds == i)
        for row in part.groupBy("piece").applyInArrow(piece, "piece int, field binary").collect():
            field[row[0] * (per_piece // 8) : (row[0] + 1) * (per_piece // 8)] = np.frombuffer(row[1], np.uint8)
    return out


def in_filter(field: np.ndarray, key: np.ndarray, pieces: int = FILTER_PIECES) -> np.ndarray:
    per_piece = len(field) * 8 // pieces
    base = piece_of(key, pieces) * (per_piece // 8)
    hit = np.ones(len(key), bool)
    for slot in _slots(key, per_piece):
        hit &= (field[base + (slot >> 3)] >> (slot & 7).astype(np.uint8)) & 1 == 1
    return hit


class SharedFilter:
    """A broadcast filter of which an executor has one copy: its Python workers map Spark's file of it."""

    def __init__(self, spark: SparkSession, build: Callable[[bytes], np.ndarray]):
        self.head = uuid.uuid4().bytes  # tells where in the file the filter begins
        whole = build(self.head)
        self.size = len(whole) - len(self.head)
        self.sent = spark.sparkContext.broadcast(whole)

    def field(self) -> np.ndarray:
        if path := getattr(self.sent, "_path", None):
            with open(path, "rb") as f:
                at = f.read(4096).find(self.head)
            if at >= 0:
                return np.asarray(np.memmap(path, np.uint8, "r", at + len(self.head), (self.size,)))
        return self.sent.value[len(self.head) :]  # an encrypted broadcast has no such file
