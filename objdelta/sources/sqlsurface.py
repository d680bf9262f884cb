"""SQL surface: the planner's arithmetic as SQL functions, and a store's metadata as views."""

from __future__ import annotations

from pyspark.sql import SparkSession

from ..functions.portable import C, NODE_BYTES, PPM

FUNCTIONS = {
    "objdelta_delta_keep": ("s_parcel BIGINT, l_parcel BIGINT, s BIGINT, l BIGINT", "BIGINT", "s_parcel * l + s * (l_parcel + l)"),
    "objdelta_delta_split": ("s BIGINT, l BIGINT", "BIGINT", f"{C * PPM} + s * l"),
    "objdelta_probe_size": ("payload STRING", "BIGINT", f"octet_length(payload) + {NODE_BYTES}"),
    "objdelta_to_global": ("v BIGINT, pages ARRAY<BIGINT>, page BIGINT", "BIGINT", "CASE WHEN v < 2147483648 THEN pages[CAST(v DIV page AS INT)] + pmod(v, page) ELSE v - 2147483648 END"),
}


def register(spark: SparkSession, store=None) -> None:
    """Create the functions; with a store, also views objdelta_trace and objdelta_states."""
    for name, (args, out, body) in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {out} RETURN {body}")
    if store is not None:
        store.trace().createOrReplaceTempView("objdelta_trace")
        rows = [(s, x["parent"], sorted(x["entries"])) for s, x in sorted(store.states.items())]
        spark.createDataFrame(rows, "state_id int, parent_id int, names array<string>").createOrReplaceTempView("objdelta_states")
