"""The delta store: states of a namespace of tables, saved by parcels whose bytes are new.

A namespace is a dict of named DataFrames. Rows are leaves of a list tree: variable -> lists -> rows. save() plans
parcels only for touched variables (those accessed, new, or linked to such), keeps the memo of decisions, writes parcels
with fingerprints that no variable of any state has, records the owner of every other parcel's bytes, and carries
untouched variables over from the parent state. load() reads the folders of those owners and no others. With declared
keys a row keeps its identity when its content changes, hence its list, its parcel and its decision. The manifest is
written last, so a state exists only if all its parcels do; parcels are named by their content, so a repeated write is
harmless.
"""

from __future__ import annotations

import json
import time
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.portable import C, NODE_BYTES, escape
from ..plans import planners
from .change import detect_changes
from .workspace import delete

JSON_OPTIONS = {"timestampNTZFormat": "yyyy-MM-dd'T'HH:mm:ss.SSSSSS", "timestampFormat": "yyyy-MM-dd'T'HH:mm:ss.SSSSSSXXX"}
#: Rows of one extent: the physical bound of a parcel, whatever the planner keeps together.
EXTENT_ROWS = 50_000
INDEX = "fp string, parcel_key string, owner string"
BLOBS = "fp string, parcel_key string, n_nodes long, raw_len int, sum long, blob binary, fp_prefix string"


class MissingReference(Exception):
    """A parcel that a state refers to is not stored."""


class CorruptParcel(Exception):
    """A stored parcel's bytes don't match its length or checksum."""


class StorageLimit(Exception):
    """The run reached its storage cap."""


def connected(names: set[str], links: list[tuple[str, str]]) -> set[str]:
    """Names that links reach from these; a namespace's names and links are few."""
    out, more = set(names), True
    while more:
        near = {y for a, b in links for x, y in ((a, b), (b, a)) if x in out} - out
        out, more = out | near, bool(near)
    return out


class Store:
    def __init__(self, spark: SparkSession, path: str, session: str = "default", cd: bool = True, scope: bool = True, churn_ppm: int = 50_000, c: int = C, rows_per_list: int = 64, codec: str = "plain", limit_bytes: int | None = None, verify: bool = True, memo: bool = True):
        self.spark, self.path, self.session = spark, path.rstrip("/"), session
        self.cd, self.scope, self.churn, self.c, self.rows_per_list, self.codec, self.limit, self.verify, self.use_memo = cd, scope, churn_ppm, c, rows_per_list, codec, limit_bytes, verify, memo
        self.states: dict[int, dict] = {}
        self.indexed: list[str] = []
        self.written = 0

    # ------------------------------------------------------------ save

    def save(self, namespace: dict[str, DataFrame], accessed: set[str] | None = None, keys: dict[str, list[str]] | None = None, links: set[tuple[str, str]] | None = None) -> int:
        """Save the namespace after an execution that accessed these names (None: all); returns the state id.

        keys: columns that identify a variable's rows (else their content does). links: pairs of names that share
        objects now (None: as in the parent state); what was connected to an accessed name before or is now may have
        changed with it.
        """
        began = time.time()
        parent = max(self.states, default=None)
        before = self.states[parent]["entries"] if parent is not None else {}
        state = len(self.states)
        if self.limit is not None and self.written > self.limit:
            raise StorageLimit(f"{self.written} bytes stored; the limit is {self.limit}")
        old = [tuple(x) for x in self.states[parent]["links"]] if parent is not None else []
        links = old if links is None else sorted(links)
        wanted = connected({*accessed} | (namespace.keys() - before.keys()), [*old, *links]) if accessed is not None and self.scope else namespace.keys()
        touched = {n for n in namespace if n in wanted}
        entries = {n: before[n] for n in namespace if n not in touched}
        counts, seconds, known = {}, {}, len(self.indexed)
        try:
            for name in sorted(touched):
                entries[name], counts[name], seconds[name] = self._save_variable(state, name, namespace[name], before.get(name), (keys or {}).get(name))
        except BaseException:
            del self.indexed[known:]  # a state that is not committed owns nothing
            raise
        self.states[state] = {"parent": parent, "links": links, "entries": entries, "counts": counts, "steps": seconds, "seconds": time.time() - began}
        self._write_manifest(state)
        return state

    def _save_variable(self, state: int, name: str, df: DataFrame, prior: dict | None, keys: list[str] | None) -> tuple[dict, dict, dict]:
        clock = [time.time()]
        lists = prior["lists"] if prior else max(1, -(-df.count() // self.rows_per_list))
        payload = F.to_json(F.struct(*[F.col(f"`{c}`") for c in df.columns]), {**JSON_OPTIONS, "ignoreNullFields": "false"})
        # Identity is the declared key, or else the content; a counter among equal rows makes repeated rows all count.
        identity = F.md5(F.concat_ws("|", *(escape(F.col(f"`{c}`")) for c in keys))) if keys else F.md5(payload)
        rows = df.select(payload.alias("payload"), identity.alias("node_key")).groupBy("node_key", "payload").agg(F.count(F.lit(1)).alias("copies"))
        leaves = rows.select("payload", "copies", "node_key", (F.octet_length("payload") + NODE_BYTES).cast("long").alias("size"), F.lit(self.churn).cast("long").alias("churn"))
        leaves = leaves.withColumn("grp", F.pmod(F.xxhash64("node_key"), F.lit(lists)).cast("string"))
        memo = self._read(f"decisions/{name}/{prior['decided']}") if prior and self.use_memo else None
        acted = planners.star_members(leaves, self.c, memo)
        base = f"{self.path}/{self.session}"
        acted.groupBy("node_key").agg(F.min("action").alias("action"), F.min("parcel_key").alias("parcel_key")).write.parquet(f"{base}/decisions/{name}/{state}")
        members = self._read(f"decisions/{name}/{state}").select("node_key", "parcel_key").join(leaves, "node_key")
        clock.append(time.time())
        text = F.concat(F.lpad(F.col("copies").cast("string"), 9, "0"), F.lit(":"), "payload")
        parcels = members.withColumn("ext", F.pmod(F.xxhash64(F.lit(3), "node_key"), F.lit(max(1, self.rows_per_list // EXTENT_ROWS)))).groupBy("parcel_key", "ext").agg(F.array_sort(F.collect_list(text)).alias("items"), F.count(F.lit(1)).alias("n_nodes"))
        blob = F.to_json("items")
        parcels = parcels.select(F.concat_ws("/", F.lit(name), "parcel_key", F.col("ext").cast("string")).alias("parcel_key"), "n_nodes", blob.alias("blob")).withColumn("fp", F.md5("blob")).withColumn("raw_len", F.octet_length("blob")).withColumn("sum", F.crc32(F.col("blob").cast("binary")))
        staged = self._stage(parcels, f"staging/{name}/{state}")
        clock.append(time.time())
        if self.cd:
            new, aliases = detect_changes(staged, self._index())
            to_write = self._stage(new.select(*staged.columns), f"staging/{name}/{state}-new")
        else:
            to_write, aliases = staged, staged.select("parcel_key", "fp", F.col("fp").alias("alias_of"))
        here = F.lit(f"{name}/save={state}")
        body = to_write.select("fp", "parcel_key", "n_nodes", "raw_len", "sum", F.col("blob").cast("binary").alias("blob"), F.substring("fp", 1, 1).alias("fp_prefix"))
        body.write.option("compression", {"plain": "zstd", "lz": "lz4_raw"}.get(self.codec, "zstd")).partitionBy("fp_prefix").parquet(f"{base}/blobs/{name}/save={state}")
        written = self._blobs([f"{name}/save={state}"])
        written.select("fp", "parcel_key", here.alias("owner")).write.parquet(f"{base}/index/{name}/{state}")
        self.indexed.append(f"{base}/index/{name}/{state}")
        owners = self._index().select("fp", "owner") if self.cd else written.select("fp", here.alias("owner")).distinct()
        aliases.select("parcel_key", "fp").join(owners, "fp").select("parcel_key", "fp", "owner").write.parquet(f"{base}/parcels/{name}/{state}")
        new = written.agg(F.count(F.lit(1)), F.coalesce(F.sum("raw_len"), F.lit(0)), F.coalesce(F.sum("n_nodes"), F.lit(0))).first()
        total = staged.count()
        owned = sorted(r[0] for r in self._read(f"parcels/{name}/{state}").select("owner").distinct().collect())  # one for each save at most
        for part in (f"{state}", f"{state}-new"):
            delete(self.spark, f"{base}/staging/{name}/{part}")
        self.written += int(new[1]) + self.c * int(new[0])
        clock.append(time.time())
        seconds = dict(zip(("plan", "serialize", "detect_and_write"), (y - x for x, y in zip(clock, clock[1:])), strict=True))
        return {"lists": lists, "decided": state, "parcels": state, "owners": owned, "schema": df.schema.json()}, {"parcels": total, "written": int(new[0]), "bytes": int(new[1])}, seconds

    def _stage(self, df: DataFrame, name: str) -> DataFrame:
        df.write.parquet(f"{self.path}/{self.session}/{name}")
        return self.spark.read.schema(df.schema).parquet(f"{self.path}/{self.session}/{name}")

    def _read(self, name: str) -> DataFrame:
        return self.spark.read.parquet(f"{self.path}/{self.session}/{name}")

    def _blobs(self, owners: list[str]) -> DataFrame:
        """Parcels in some saves' folders, of which any may have written none."""
        root = f"{self.path}/{self.session}/blobs"
        return self.spark.read.schema(BLOBS).option("basePath", root).parquet(*[f"{root}/{o}" for o in owners] or [root])

    def _index(self) -> DataFrame:
        """Fingerprints known so far, of all variables, each with one owner."""
        if not self.indexed:
            return self.spark.createDataFrame([], INDEX)
        known = self.spark.read.schema(INDEX).parquet(*self.indexed)
        return known.groupBy("fp").agg(F.min(F.struct("owner", "parcel_key")).alias("first")).select("fp", "first.parcel_key", "first.owner")

    def _write_manifest(self, state: int) -> None:
        line = json.dumps({"state": state, **self.states[state]})
        base = f"{self.path}/{self.session}/states"
        name = f"{base}/.{state}-{uuid.uuid4().hex}"
        self.spark.createDataFrame([(line,)], "value string").coalesce(1).write.text(name)
        jvm, sc = self.spark.sparkContext._jvm, self.spark.sparkContext
        path = jvm.org.apache.hadoop.fs.Path
        fs = path(base).getFileSystem(sc._jsc.hadoopConfiguration())
        if not fs.rename(path(name), path(f"{base}/state={state}")):
            raise OSError(f"state {state} could not be committed")

    @classmethod
    def open(cls, spark: SparkSession, path: str, session: str = "default", **options) -> Store:
        """The store as its committed manifests describe it."""
        store = cls(spark, path, session, **options)
        for row in spark.read.text(f"{store.path}/{session}/states/state=*").select("value").collect():
            found = json.loads(row[0])
            state = found.pop("state")
            store.states[state] = found
            store.indexed += [f"{store.path}/{session}/index/{n}/{state}" for n in found["counts"]]
        return store

    # ------------------------------------------------------------ load

    def load(self, names: set[str] | None, state: int) -> dict[str, DataFrame]:
        """The named variables (None: all) as they were after that state."""
        if state not in self.states:
            raise KeyError(f"unknown state {state}")
        entries = self.states[state]["entries"]
        missing = (names or set()) - entries.keys()
        if missing:
            raise KeyError(f"state {state} has no {sorted(missing)}")
        return {n: self._load_variable(n, entries[n]) for n in sorted(names if names is not None else entries)}

    def load_many(self, requests: list[tuple[set[str] | None, int]]) -> list[dict[str, DataFrame]]:
        return [self.load(n, s) for n, s in requests]

    def _load_variable(self, name: str, entry: dict) -> DataFrame:
        wanted = self._read(f"parcels/{name}/{entry['parcels']}").select("fp").distinct()
        blobs = self._blobs(entry["owners"])
        # A save writes a fingerprint once, unless detection is off: then equal bytes of one owner count once.
        blobs = blobs.select("fp", "raw_len", "sum", F.col("blob").cast("string").alias("blob"))
        found = wanted.join(blobs if self.cd else blobs.dropDuplicates(["fp"]), "fp", "left")
        if self.verify:
            bad = found.select(F.count_if(F.col("blob").isNull()), F.count_if(F.col("blob").isNotNull() & ((F.octet_length("blob") != F.col("raw_len")) | (F.crc32(F.col("blob").cast("binary")) != F.col("sum"))))).first()
            if bad[0]:
                raise MissingReference(f"{bad[0]} parcels of {name} are not stored")
            if bad[1]:
                raise CorruptParcel(f"{bad[1]} parcels of {name} are damaged")
        schema = T.StructType.fromJson(json.loads(entry["schema"]))
        item = found.select(F.explode(F.from_json("blob", "array<string>")).alias("item"))
        row = item.select(F.substring("item", 1, 9).cast("int").alias("copies"), F.from_json(F.expr("substring(item, 11)"), schema, JSON_OPTIONS).alias("row"))
        return row.select("row", F.explode(F.sequence(F.lit(1), F.col("copies")))).select("row.*")

    # ------------------------------------------------------------ upkeep

    def trace(self) -> DataFrame:
        """(state, name, parcels, written, bytes) of every save."""
        rows = [(s, n, c["parcels"], c["written"], c["bytes"]) for s, x in sorted(self.states.items()) for n, c in sorted(x["counts"].items())]
        return self.spark.createDataFrame(rows, "state int, name string, parcels long, written long, bytes long")

    def diff(self, a: int, b: int) -> DataFrame:
        """(name, n_only_a, n_only_b, n_common): parcels of two states, by fingerprint."""
        x, y = self.states[a]["entries"], self.states[b]["entries"]
        out = None
        for n in sorted(x.keys() | y.keys()):
            empty = self.spark.createDataFrame([], "fp string")
            p = self._read(f"parcels/{n}/{x[n]['parcels']}").select("fp").distinct() if n in x else empty
            q = self._read(f"parcels/{n}/{y[n]['parcels']}").select("fp").distinct() if n in y else empty
            r = p.withColumn("a", F.lit(1)).join(q.withColumn("b", F.lit(1)), "fp", "full").agg(F.lit(n).alias("name"), F.count_if(F.col("b").isNull()).alias("n_only_a"), F.count_if(F.col("a").isNull()).alias("n_only_b"), F.count_if(F.col("a").isNotNull() & F.col("b").isNotNull()).alias("n_common"))
            out = r if out is None else out.unionByName(r)
        return out

    def recover(self, state: int, executions: list) -> dict[str, DataFrame]:
        """Load an older state and run later executions (functions of a namespace) again."""
        namespace = self.load(None, state)
        for run in executions:
            namespace = run(namespace)
        return namespace

    def vacuum(self) -> int:
        """Delete folders of blobs that no state refers to, such as those of a save that broke off; returns how many."""
        used = {o for s in self.states.values() for e in s["entries"].values() for o in e["owners"]}
        sc = self.spark.sparkContext
        path = sc._jvm.org.apache.hadoop.fs.Path
        root = path(f"{self.path}/{self.session}/blobs")
        fs = root.getFileSystem(sc._jsc.hadoopConfiguration())
        gone = 0
        for v in fs.listStatus(root) if fs.exists(root) else []:
            for b in fs.listStatus(v.getPath()):
                if f"{v.getPath().getName()}/{b.getPath().getName()}" not in used:
                    fs.delete(b.getPath(), True)
                    gone += 1
        return gone
