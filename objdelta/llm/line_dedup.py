"""Line dedup over levelled sorted runs of line hashes, with DataFrame functions only.

Each batch of documents is reduced to (line hash, first document); a merge anti-join against the runs leaves the
hashes that are new, which become a run of level 0. When a level holds FANOUT runs, they are merged into one sorted
run of the next level. Batches go up by doc_id, so the runs hold the smallest document of every line.

Defined cases: null or empty text is one empty line; keys under `min_chars` code points are never dropped; rows
without doc_id keep all lines; equal rows are treated alike; an empty table gives an empty result; further columns
of the input are carried by `apply` in a struct, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import SPACE_CHARS, Workspace, ascii_lower, read_table

FANOUT = 2
HASHES = ["__h1", "__h2"]


class RunStore:
    """Sorted runs (hash, first_doc) by level, in the shared folder."""

    def __init__(self, work: Workspace, fanout: int = FANOUT):
        self.work, self.fanout, self.levels, self.made = work, fanout, {}, 0

    def runs(self) -> list[DataFrame]:
        return [df for level in sorted(self.levels) for df in self.levels[level]]

    def add(self, keys: DataFrame) -> DataFrame:
        """Anti-join the batch's keys against every run; the rest becomes a run. Returns that run."""
        for run in self.runs():
            keys = keys.join(run.select(*HASHES), HASHES, "left_anti")
        run = self._write(keys)
        self._place(run, 0)
        return run

    def first(self) -> DataFrame:
        """Every line hash with the smallest document that holds it."""
        out, *rest = self.runs()
        for df in rest:
            out = out.unionByName(df)
        return out

    def _write(self, df: DataFrame) -> DataFrame:
        self.made += 1
        return self.work.table(df.sortWithinPartitions(*HASHES), f"run-{self.made}")

    def _place(self, run: DataFrame, level: int) -> None:
        self.levels.setdefault(level, []).append(run)
        if len(self.levels[level]) >= self.fanout:
            merged, *rest = self.levels.pop(level)
            for df in rest:
                merged = merged.unionByName(df)
            self._place(self._write(merged.repartition(*HASHES)), level + 1)


def line_table(docs: DataFrame, min_chars: int) -> DataFrame:
    """One row for each line long enough to count: (doc, text hash, position, key hash)."""
    text = F.coalesce(F.col("text"), F.lit(""))
    key = ascii_lower(F.btrim(F.col("line"), F.lit(SPACE_CHARS)))
    return (
        docs.where(F.col("doc_id").isNotNull())
        .select(F.col("doc_id").alias("__doc"), F.xxhash64(text).alias("__text"), F.posexplode(F.split(text, "\n", -1)).alias("__pos", "line"))
        .select("__doc", "__text", "__pos", key.alias("key"))
        .where(F.length("key") >= min_chars)
        .select("__doc", "__text", "__pos", F.xxhash64("key").alias("__h1"), F.xxhash64(F.lit(20_011), "key").alias("__h2"))
    )


def apply(spark: SparkSession, docs: DataFrame, min_chars: int = 10, batches: int = 3) -> DataFrame:
    """(row, lines, dropped, kept): a row of docs with all its columns, its lines before, how many go, and the text after."""
    work = Workspace(spark, "lines")
    lines = work.table(line_table(docs, min_chars), "lines")
    cuts = lines.agg(F.percentile_approx("__doc", [i / batches for i in range(1, batches)], 1000)).first()[0] or []
    store, low = RunStore(work), None
    for high in [*sorted(set(cuts)), None]:
        part = lines
        part = part.where(F.col("__doc") > low) if low is not None else part
        part = part.where(F.col("__doc") <= high) if high is not None else part
        store.add(part.groupBy(*HASHES).agg(F.min("__doc").alias("__first")))
        low = high
    flags = (
        lines.join(store.first(), HASHES)
        .select("__doc", "__text", "__pos", (F.col("__doc") > F.col("__first")).alias("__out"))
        .where("__out")
        .groupBy("__doc", "__text")
        .agg(F.sort_array(F.collect_set("__pos")).alias("__out"))
    )
    # Columns of the input travel inside one struct, so their names never meet the ones used here.
    rows = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("row"), F.col("doc_id").alias("id"), F.xxhash64(F.coalesce(F.col("text"), F.lit(""))).alias("t"))
    split = F.split("full", "\n", -1)
    # Kept lines are the slices between dropped positions: linear in the lines, whatever their number.
    bounds = F.concat(F.array(F.lit(-1)), F.col("__out"), F.array(F.size("split")))
    slices = F.flatten(F.transform(F.sequence(F.lit(1), F.size("__out") + 1), lambda i: F.slice(F.col("split"), F.element_at("bounds", i) + 2, F.element_at("bounds", i + 1) - F.element_at("bounds", i) - 1)))
    joined = rows.join(flags, (F.col("id") == F.col("__doc")) & (F.col("t") == F.col("__text")), "left")
    return (
        joined.withColumn("full", F.coalesce("row.text", F.lit(""))).withColumn("split", split)
        .withColumn("bounds", F.when(F.col("__out").isNotNull(), bounds))
        .select(
            "row", F.size("split").cast("long").alias("lines"), F.coalesce(F.size("__out"), F.lit(0)).cast("long").alias("dropped"),
            F.when(F.col("__out").isNull(), F.col("full")).otherwise(F.array_join(slices, "\n")).alias("kept"),
        )
    )


def digest(spark: SparkSession, docs: DataFrame, **options) -> DataFrame:
    """One row per document: counts of lines and the hash of what stays."""
    return apply(spark, docs.select("doc_id", "text"), **options).select(
        "row.doc_id", F.col("lines").alias("n_lines"), F.col("dropped").alias("n_dropped"), F.sha2(F.col("kept").cast("binary"), 256).alias("kept_sha256")
    )


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: the same documents with repeated lines taken out; n_chars follows the text."""
    new = {"text": F.col("kept"), "n_chars": F.length("kept").cast("long")}
    of = lambda c: F.col(f"row.`{c}`")
    return apply(spark, docs).select(*((F.when(F.col("dropped") > 0, new[c]).otherwise(of(c)) if c in new else of(c)).alias(c) for c in docs.columns))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digest(spark, read_table(spark, sf_dir, "documents"))


ORACLE = r"""
with lines as (
  select doc_id, i as pos, string_split(coalesce(text, ''), chr(10))[i] as line
  from (select doc_id, text, unnest(range(1, len(string_split(coalesce(text, ''), chr(10))) + 1)) as i from documents)
), keyed as (
  select *, translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)),
                      'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as key from lines
), firsts as (select key, min(doc_id) as f from keyed where length(key) >= 10 group by key),
marked as (select k.*, f.f is not null and k.doc_id > f.f as out from keyed k left join firsts f on k.key = f.key)
select doc_id, count(*)::bigint as n_lines, count(*) filter (where out)::bigint as n_dropped,
       sha256(coalesce(string_agg(line, chr(10) order by pos) filter (where not out), '')) as kept_sha256
from marked group by doc_id
"""
