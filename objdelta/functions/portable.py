"""Values that Spark and DuckDB compute alike: draws, canonical text, fingerprints, and the planner's integer arithmetic.

Every helper comes as a Spark Column and as SQL text, so that queries and oracles share one definition.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Overhead of one parcel in bytes, and the depth limit of the planner.
C = 1200
MAX_DEPTH = 3
PPM = 1_000_000
#: Bytes that a node costs besides its payload.
NODE_BYTES = 60


def draw(key: Column, step: Column) -> Column:
    """0 ... 2**24-1, fixed by (key, step)."""
    return F.conv(F.substring(F.md5(F.concat(key, F.lit("|"), step.cast("string"))), 1, 6), 16, 10).cast("long")


def draw_sql(key: str, step: str) -> str:
    return f"('0x' || substr(md5({key} || '|' || cast({step} as varchar)), 1, 6))::bigint"


def mutates(key: Column, step: Column, rate_ppm: int) -> Column:
    return draw(key, step) * PPM < F.lit(rate_ppm * (1 << 24))


def mutates_sql(key: str, step: str, rate_ppm: int) -> str:
    return f"{draw_sql(key, step)} * {PPM} < {rate_ppm * (1 << 24)}"


def cents(c: Column) -> Column:
    return F.round(c * 100).cast("long")


def stamp(c: Column) -> Column:
    return F.date_format(c, "yyyy-MM-dd HH:mm:ss.SSSSSS")


def probe_size(payload: Column) -> Column:
    """Size without serializing: payload bytes and a constant."""
    return (F.octet_length(payload) + NODE_BYTES).cast("long")


def delta_keep(s_parcel: Column, l_parcel: Column, s: Column, l: Column) -> Column:
    """Cost in byte * ppm that a node adds when it joins a parcel."""
    return s_parcel * l + s * (l_parcel + l)


def delta_split(s: Column, l: Column, c: int = C) -> Column:
    """Cost in byte * ppm of a parcel of its own."""
    return F.lit(c * PPM) + s * l


def escape(c: Column) -> Column:
    """Separators escaped and NULL marked, so that joined text is injective."""
    return F.coalesce(F.replace(F.replace(c.cast("string"), F.lit("\\"), F.lit("\\\\")), F.lit("|"), F.lit("\\|")), F.lit("\\N"))


def fingerprint(parts: Column) -> Column:
    """128 bits of an array of strings, whatever its order."""
    return F.md5(F.concat_ws(";", F.array_sort(parts)))


def collision_probability(n: float, capacity: float, bits: int = 128) -> float:
    return n * capacity / 2.0**bits
