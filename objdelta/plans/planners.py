"""Planners: which nodes share a parcel.

KEEP joins the parent's parcel, OPEN starts one and goes on below, SEAL starts one for the whole subtree. The greedy
rule in integers is: KEEP iff S * l + s * L < c * 10**6, S and L being size and churn (ppm) of the current parcel.
For leaves under a list (a star), three forms give the same parcels: a fold in Catalyst for lists of bounded length,
a streamed fold that holds one parcel's sums, and a closed form over runs of equal leaves.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.portable import C, MAX_DEPTH, NODE_BYTES, PPM, draw

KEEP, OPEN, SEAL = 0, 1, 2


def list_size(grp):
    """Size of a list node."""
    return (F.octet_length(F.concat(F.lit("list:"), grp)) + NODE_BYTES).cast("long")


LIST_SIZE_SQL = f"(octet_length(encode('list:' || grp)) + {NODE_BYTES})::bigint"


def decide(parcel_size: int, parcel_churn: int, size: int, churn: int, depth: int, c: int = C, max_depth: int = MAX_DEPTH) -> int:
    """The greedy rule for one node; a tie splits."""
    if parcel_size * churn + size * parcel_churn < c * PPM:
        return KEEP
    return OPEN if depth < max_depth else SEAL


def star_fold(leaves: DataFrame, c: int = C) -> DataFrame:
    """grp -> (s, l, n_keep, n_open) by a fold over the list's leaves in key order; leaves: grp, node_key, size, churn."""
    items = F.array_sort(F.collect_list(F.struct("node_key", "size", "churn")))
    big = lambda x: x.cast("decimal(38,0)")  # noqa: E731  products outgrow 64 bits on large parcels

    def step(acc, x):
        keep = big(acc["s"]) * x["churn"] + big(acc["l"]) * x["size"] < F.lit(c * PPM)
        return F.struct(
            F.when(keep, acc["s"] + x["size"]).otherwise(acc["s"]).alias("s"), F.when(keep, acc["l"] + x["churn"]).otherwise(acc["l"]).alias("l"),
            (acc["k"] + F.when(keep, 1).otherwise(0)).alias("k"), (acc["o"] + F.when(keep, 0).otherwise(1)).alias("o"),
        )

    zero = F.lit(0).cast("long")
    acc = F.aggregate("items", F.struct(list_size(F.col("grp")).alias("s"), zero.alias("l"), zero.alias("k"), zero.alias("o")), step)
    return leaves.groupBy("grp").agg(items.alias("items")).select("grp", acc.alias("a")).select("grp", F.col("a.k").alias("n_keep"), F.col("a.o").alias("n_open"), F.col("a.s").alias("parcel_bytes"), F.col("a.l").alias("parcel_churn_ppm"))


def star_members(leaves: DataFrame, c: int = C, memo: DataFrame | None = None) -> DataFrame:
    """leaves with action and parcel_key, by a streamed fold: memory is one parcel's sums, whatever the list's length.

    With memo (node_key, action) a node keeps its first action.
    """
    rows = leaves if memo is None else leaves.join(memo.select("node_key", F.col("action").alias("prior")), "node_key", "left")
    rows = rows if memo is not None else rows.withColumn("prior", F.lit(None).cast("int"))
    keyed = rows.select("grp", "node_key", "size", "churn", "prior")

    def fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        grp = None
        s = l = 0
        for batch in batches:
            out = []
            for g, size, churn, prior in zip(*(batch.column(i).to_pylist() for i in (0, 2, 3, 4)), strict=True):
                if g != grp:
                    grp, s, l = g, len(f"list:{g}".encode()) + NODE_BYTES, 0
                action = prior if prior is not None else decide(s, l, size, churn, 0, c)
                if action == KEEP:
                    s, l = s + size, l + churn
                out.append(action)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(out, pa.int32())], ["grp", "node_key", "action"])

    acted = keyed.repartition("grp").sortWithinPartitions("grp", "node_key").mapInArrow(fold, "grp string, node_key string, action int")
    parcel = F.when(F.col("action") == KEEP, F.concat(F.lit("list:"), "grp")).otherwise(F.col("node_key"))
    return acted.withColumn("parcel_key", parcel)


def star_cutoff(leaves: DataFrame, c: int = C) -> DataFrame:
    """The closed form: maximal runs of equal (size, churn) in key order, then one short fold over runs.

    Of a run of j equal leaves that meets a parcel (S, L), with d = c - S*l - s*L, the first min(j, ceil(d / 2sl)) stay
    (all, if s*l = 0 and d > 0; none, if d <= 0).
    """
    w = Window.partitionBy("grp").orderBy("node_key")
    new = F.when((F.lag("size").over(w) == F.col("size")) & (F.lag("churn").over(w) == F.col("churn")), 0).otherwise(1)
    runs = leaves.withColumn("new", new).withColumn("run", F.sum("new").over(w)).groupBy("grp", "run").agg(F.first("size").alias("size"), F.first("churn").alias("churn"), F.count(F.lit(1)).alias("j"))
    big = lambda x: x.cast("decimal(38,0)")

    def step(acc, x):
        d = F.lit(c * PPM).cast("decimal(38,0)") - big(acc["s"]) * x["churn"] - big(acc["l"]) * x["size"]
        twice = (2 * x["size"] * x["churn"]).cast("decimal(38,0)")
        most = F.when(d <= 0, F.lit(0).cast("long")).when(twice == 0, x["j"]).otherwise(F.least(x["j"], F.ceil(d / F.when(twice == 0, 1).otherwise(twice)).cast("long")))
        return F.struct((acc["s"] + most * x["size"]).alias("s"), (acc["l"] + most * x["churn"]).alias("l"), (acc["k"] + most).alias("k"), (acc["o"] + x["j"] - most).alias("o"))

    zero = F.lit(0).cast("long")
    acc = F.aggregate("items", F.struct(list_size(F.col("grp")).alias("s"), zero.alias("l"), zero.alias("k"), zero.alias("o")), step)
    return runs.groupBy("grp").agg(F.array_sort(F.collect_list(F.struct("run", "size", "churn", "j"))).alias("items")).select("grp", acc.alias("a")).select("grp", F.col("a.k").alias("n_keep"), F.col("a.o").alias("n_open"), F.col("a.s").alias("parcel_bytes"), F.col("a.l").alias("parcel_churn_ppm"))


def star_fold_sql(leaves: str, c: int = C) -> str:
    """The fold in DuckDB; also returns the kept keys."""
    return f"""
(select grp, r.k as n_keep, r.o as n_open, r.s as parcel_bytes, r.l as parcel_churn_ppm, r.kept as kept from (
  select grp, list_reduce(list_prepend({{'s': {LIST_SIZE_SQL}, 'l': 0::bigint, 'k': 0::bigint, 'o': 0::bigint, 'x': 0::bigint, 'y': 0::bigint, 'key': '', 'kept': []::varchar[]}},
      list({{'s': 0::bigint, 'l': 0::bigint, 'k': 0::bigint, 'o': 0::bigint, 'x': size::bigint, 'y': churn::bigint, 'key': node_key, 'kept': []::varchar[]}} order by node_key)),
    lambda a, i: case when a.s * i.y + i.x * a.l < {c * PPM}
      then {{'s': a.s + i.x, 'l': a.l + i.y, 'k': a.k + 1, 'o': a.o, 'x': 0::bigint, 'y': 0::bigint, 'key': '', 'kept': list_append(a.kept, i.key)}}
      else {{'s': a.s, 'l': a.l, 'k': a.k, 'o': a.o + 1, 'x': 0::bigint, 'y': 0::bigint, 'key': '', 'kept': a.kept}} end) as r
  from {leaves} group by grp))"""


# ---------------------------------------------------------------- other planners on stars


def policy(name: str):
    """parcel_key column of a fixed policy for leaves (var, grp, node_key, size)."""
    own, whole, lst = F.col("node_key"), F.lit("root"), F.concat(F.lit("list:"), "grp")
    return {
        "keep_all": whole,
        "split_all": own,
        "random": F.when(draw(F.col("node_key"), F.lit(99)) % 3 == KEEP, lst).otherwise(own),
        "kind": F.when(F.col("size") > 4096, own).otherwise(lst),
    }[name]


POLICY_SQL = {
    "keep_all": "'root'",
    "split_all": "node_key",
    "random": "case when ('0x' || substr(md5(node_key || '|99'), 1, 6))::bigint % 3 = 0 then 'list:' || grp else node_key end",
    "kind": "case when size > 4096 then node_key else 'list:' || grp end",
}


# ---------------------------------------------------------------- sums of parcels on stars


def _folded(sizes: np.ndarray, churns: np.ndarray, s: int, l: int, limit: int) -> tuple[np.ndarray, int, int]:
    """Which leaves of one list stay in its parcel (s, l), which is returned as it is after them."""
    keep, at, n = np.zeros(len(sizes), bool), 0, len(sizes)
    while at < n:
        # Parcels fill up and then take almost nothing: the next leaf that stays is looked up in growing pieces.
        width = 1
        while at < n:
            hit = s * churns[at : at + width] + sizes[at : at + width] * l < limit
            first = int(hit.argmax())
            if hit[first]:
                at += first
                break
            at, width = at + width, min(2 * width, 4096)
        if at < n:
            keep[at] = True
            s, l, at = s + int(sizes[at]), l + int(churns[at]), at + 1
    return keep, s, l


def star_sums(leaves: DataFrame, greedy: list[str], fixed: dict[str, str] | None = None, joined: bool = False, c: int = C) -> DataFrame:
    """(planner, grp, own, var, mask, parcels, n, bytes): the leaves under a list, summed by parcel and by the steps at which they change.

    leaves: grp, node_key, var, size, mask (bit t - 1 if it changes at step t), a churn column for each name in greedy, and for each name
    in fixed a boolean column that says which leaves are parcels of their own. A list's other leaves are one parcel. Leaves are exchanged
    once, by list; one task streams a list in key order and holds one parcel's sums for each planner. Rows that share a key share a parcel
    (with the list, if one of them stays there), and with joined each counts as often as rows share the key.
    """
    names = [*greedy, *(fixed or {})]
    columns = ["grp", "node_key", "var", "size", "mask", *greedy, *(fixed or {}).values()]
    limit = c * PPM

    def one(g: str, key, var, size, mask, cols, state):
        """Sums of consecutive leaves of one list; no key is cut."""
        new = np.ones(len(size), bool)
        new[1:] = key[1:] != key[:-1]
        run = np.cumsum(new) - 1
        times = np.bincount(run)[run] if joined else np.ones(len(size), np.int64)
        for i, p in enumerate(names):
            if i < len(greedy):
                keep, *state[i] = _folded(size, cols[i], *state[i], limit)
                own = ~(np.bincount(run, keep)[run] > 0)
            else:
                own = cols[i].astype(bool)
            # Of the rows that share a key and are parcels of their own, the first counts as the parcel.
            mine = np.flatnonzero(own)
            lead = np.zeros(len(size), bool)
            lead[mine[np.unique(run[mine], return_index=True)[1]]] = True
            cell, at = np.unique(var << 33 | mask << 1 | own, return_inverse=True)
            order = np.argsort(at, kind="stable")
            first = np.searchsorted(at[order], np.arange(len(cell)))
            sums_ = (np.add.reduceat(w[order], first).tolist() for w in (lead.astype(np.int64), times, times * size))
            for x, *w in zip(cell.tolist(), *sums_, strict=True):
                yield p, g, bool(x & 1), x >> 33, x >> 1 & 0xFFFFFFFF, *w

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        grp, state, held = None, [], None
        for batch in _and_none(batches):
            rows = []
            t = held if batch is None else pa.Table.from_batches([batch]) if held is None else pa.concat_tables([held, pa.Table.from_batches([batch])]).combine_chunks()
            held = None
            if t is None or not t.num_rows:
                continue
            g, k = t.column(0).to_numpy(zero_copy_only=False), t.column(1).to_numpy(zero_copy_only=False)
            edge = np.ones(len(g), bool)
            edge[1:] = (g[1:] != g[:-1]) | (k[1:] != k[:-1])
            done = len(g) if batch is None else int(np.flatnonzero(edge)[-1])  # the last key may go on in the next batch
            held = t.slice(done) if done < len(g) else None
            rest = [t.column(i).to_numpy(zero_copy_only=False)[:done].astype(np.int64) for i in range(2, t.num_columns)]
            cuts = [0, *(np.flatnonzero(g[1:done] != g[: done - 1]) + 1).tolist(), done] if done else [0]
            for a, b in zip(cuts, cuts[1:], strict=False):
                if g[a] != grp:
                    grp, state = g[a], [(len(f"list:{g[a]}".encode()) + NODE_BYTES, 0) for _ in greedy]
                var, size, mask, *cols = (x[a:b] for x in rest)
                rows.extend(one(grp, k[a:b], var, size, mask, cols, state))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(list(x), f.type) for x, f in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)

    schema = pa.schema([("planner", pa.string()), ("grp", pa.string()), ("own", pa.bool_()), ("var", pa.int64()), ("mask", pa.int64()), ("parcels", pa.int64()), ("n", pa.int64()), ("bytes", pa.int64())])
    return leaves.select(*columns).repartition("grp").sortWithinPartitions("grp", "node_key").mapInArrow(sums, "planner string, grp string, own boolean, var long, mask long, parcels long, n long, bytes long")


def _and_none(items):
    yield from items
    yield None


def parcel_states(sums: DataFrame, steps: int) -> DataFrame:
    """(planner, step, grp, own, var, parcels, n, bytes, dirty) of the parcels summed by star_sums: a row for each list, and one for all own parcels of a list that change alike."""
    x = sums.withColumn("step", F.explode(F.sequence(F.lit(0), F.lit(steps - 1))))
    changed = (F.col("step") == 0) | (F.expr("(mask >> greatest(step - 1, 0)) & 1") == 1)
    x = x.withColumn("changed", changed).withColumn("bytes", F.col("bytes") + 2 * F.col("n") * F.expr("bit_count(mask & ((1L << step) - 1))"))
    cell = ["planner", "step", "grp", F.when(F.col("own"), F.col("mask")).alias("mask"), "own"]
    return x.groupBy(*cell).agg(F.min("var").alias("var"), F.greatest(F.sum("parcels"), F.lit(1)).alias("parcels"), F.sum("n").alias("n"), F.sum("bytes").alias("bytes"), F.bool_or("changed").alias("dirty"))


# ---------------------------------------------------------------- deep fold


def tree_fold(preorder: DataFrame, c: int = C, max_depth: int = MAX_DEPTH, memo: bool = False) -> DataFrame:
    """Greedy over trees in depth-first order: (component, path, level, node_key, size, churn[, prior]) -> action, parcel_key, depth.

    Components are independent; one task streams the rows of a component in path order and holds a stack.
    """
    rows = preorder if memo else preorder.withColumn("prior", F.lit(None).cast("int"))

    def fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        component, stack = None, []
        for batch in batches:
            keys, acts, parcels, depths = [], [], [], []
            for comp, level, key, size, churn, prior in zip(*(batch.column(i).to_pylist() for i in range(6)), strict=True):
                if comp != component:
                    component, stack = comp, []
                del stack[level:]
                if not stack:
                    parcel, action = [key, size, churn, 0, False], OPEN
                else:
                    parcel = stack[-1]
                    action = KEEP if parcel[4] else prior if prior is not None else decide(parcel[1], parcel[2], size, churn, parcel[3], c, max_depth)
                    if action == KEEP:
                        parcel[1] += size
                        parcel[2] += churn
                    else:
                        parcel = [key, size, churn, parcel[3] + 1, action == SEAL]
                stack.append(parcel)
                keys.append(key)
                acts.append(action)
                parcels.append(parcel[0])
                depths.append(parcel[3])
            yield pa.RecordBatch.from_arrays([pa.array(keys, pa.string()), pa.array(acts, pa.int32()), pa.array(parcels, pa.string()), pa.array(depths, pa.int32())], ["node_key", "action", "parcel_key", "depth"])

    ordered = rows.select("component", "level", "node_key", "size", "churn", "prior", "path").repartition("component").sortWithinPartitions("component", "path").drop("path")
    return ordered.mapInArrow(fold, "node_key string, action int, parcel_key string, depth int")


def expand_seal(decisions: list[tuple[str, str | None, int]]) -> list[tuple[str, int]]:
    """(node, parent, action) in preorder -> SEAL written as OPEN with KEEP for every descendant."""
    sealed: set[str] = set()
    out = []
    for node, parent, action in decisions:
        if parent in sealed:
            sealed.add(node)
            out.append((node, KEEP))
        elif action == SEAL:
            sealed.add(node)
            out.append((node, OPEN))
        else:
            out.append((node, action))
    return out


# ---------------------------------------------------------------- cost


def parcel_costs(members: DataFrame, c: int = C) -> DataFrame:
    """parcel_key -> n, s, l, cost in byte * ppm (c + S * L)."""
    per = members.groupBy("parcel_key").agg(F.count(F.lit(1)).alias("n"), F.sum("size").alias("s"), F.sum("churn").alias("l"))
    return per.withColumn("cost", F.lit(c * PPM).cast("decimal(38,0)") + F.col("s").cast("decimal(38,0)") * F.col("l"))


def parcelling_cost(members: DataFrame, c: int = C) -> DataFrame:
    """(n_parcels, cost): cost in bytes, rounded to 6."""
    return parcel_costs(members, c).agg(F.count(F.lit(1)).alias("n_parcels"), F.round(F.sum("cost").cast("double") / PPM, 6).alias("cost"))
