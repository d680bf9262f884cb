"""Functions that SQL lacks, over Arrow batches: block hashes of long payloads, a pickle codec, and line splitting."""

from __future__ import annotations

import hashlib
import pickle

import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Bytes of one block.
BLOCK = 4096


@F.pandas_udf(T.ArrayType(T.StringType()))
def block_hashes(payload: pd.Series) -> pd.Series:
    """md5 of every block of a payload's bytes; an empty payload has none, a null one is null."""
    def one(p):
        raw = p.encode()
        return [hashlib.md5(raw[i : i + BLOCK]).hexdigest() for i in range(0, len(raw), BLOCK)]

    return payload.map(one, na_action="ignore")


@F.pandas_udf(T.BinaryType())
def pickle_encode(payload: pd.Series) -> pd.Series:
    """The pickle codec: bytes that depend on the value alone, as change detection needs."""
    return payload.map(lambda p: pickle.dumps(p, protocol=5), na_action="ignore")


@F.pandas_udf(T.StringType())
def pickle_decode(blob: pd.Series) -> pd.Series:
    return blob.map(pickle.loads, na_action="ignore")


@F.udtf(returnType=T.StructType([T.StructField("line_no", T.IntegerType()), T.StructField("length", T.IntegerType())]))
class LineLengths:
    """One row for each line of a text."""

    def eval(self, text: str):
        for i, line in enumerate((text or "").split("\n")):
            yield i, len(line)
