"""Similarity join of documents by the Jaccard index of their k-word shingles, through a token-group matrix.

Exact: every pair with 100 * intersection >= percent * union is connected in the result.

1. Documents with equal shingle sets are one class (compared by digest), of which one goes on.
2. Shingles are ordered: those that few documents hold come first (all are counted; levels of the counts are kept in
   fixed-size filters), within a level by hash. Two documents that reach the threshold share at least `common`
   shingles among the first n - ceil(percent * n / 100) + common of each, so only those beginnings are kept, and of
   them only shingles that two documents hold.
3. In each of a few rounds every shingle has a leader among the documents that hold it: first the most central one,
   whose shingles most others share, later one drawn by hash from another group. A document is verified against the
   leaders of its rarest shingles and those of at least `common` of its shingles, unless their parities already differ
   in too many bits; so a round's pairs are linear in the documents, however large a group is. What is connected is a
   group: a partition of similar documents. Shingles of one group alone are done with.
4. The token-group matrix holds each group's union of beginnings. A document's overlap with a foreign group's union
   bounds its overlap with every member (by parities as well, if one member alone holds the shingle); only groups that
   reach the bound are opened, and members that reach it too are verified on whole texts. Verified links leave each task as a spanning forest.

Defined cases: a document without words has an empty set and links with nothing; fewer words than k are one shingle;
rows that share a doc_id are one node; rows without doc_id link with nothing (component null); an empty table gives
an empty result; further columns are ignored.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .bitfilter import build_filter, in_filter, piece_of, set_bits
from .common import CHUNK_BYTES, Workspace, chunks, mix, read_table, shingle_hashes, text_buffers
from .components import components, forest

K, PERCENT, COMMON, ROUNDS = 5, 75, 4, 3
#: A shingle is of level i if at least LEVELS[i] documents hold it; the filters' sizes in bits.
LEVELS = (2, 4, 16, 64, 256, 2048)
LEVEL_BITS = (27, 27, 25, 24, 24, 24)
#: Pieces of the filters, at least; a piece has about PIECE_SHINGLES shingles at most. Text dealt to the pieces at once.
PIECES, PIECE_SHINGLES, DEAL_BYTES = 1024, 4 << 20, 4 << 20
#: Words of a document's parities, which bound how many shingles two documents differ in.
PARITY = 4
#: Leaders of a document's rarest shingles that it is verified against in any case.
RAREST = 2
_SIG = [f"s{i}" for i in range(PARITY)]


def shingle_sets(data: np.ndarray, offsets: np.ndarray, k: int):
    """Distinct shingles of all texts, sorted by text and hash, and where each text's begin."""
    h, who = shingle_hashes(data, offsets, k)
    order = np.lexsort((h, who))
    h, who = h[order], who[order]
    new = np.ones(len(h), bool)
    new[1:] = (h[1:] != h[:-1]) | (who[1:] != who[:-1])
    h, who = h[new], who[new]
    return h, np.concatenate([[0], np.cumsum(np.bincount(who, minlength=len(offsets) - 1))]).astype(np.int64)


def parities(h: np.ndarray, who: np.ndarray, n_texts: int) -> np.ndarray:
    """PARITY words of 64 bits for each text: bit b is the parity of its shingles that hash to b. Two texts' shingle sets
    differ in at least as many shingles as their parities differ in bits."""
    bits = 64 * PARITY
    odd = np.bincount(who * bits + ((h >> np.uint64(40)) % np.uint64(bits)).astype(np.int64), minlength=n_texts * bits) & 1
    return np.packbits(odd.astype(np.uint8).reshape(n_texts, bits), axis=1).view(np.int64)


def beginning(n: np.ndarray, percent: int = PERCENT, common: int = COMMON) -> np.ndarray:
    """Shingles that a document of n shows."""
    return np.minimum(n, n - -(-percent * n // 100) + common)


def _source(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc"), F.coalesce(F.col("text"), F.lit("")).alias("text"))


def describe(docs: DataFrame, k: int = K) -> DataFrame:
    """(doc, n, d1, d2): size and digest of every document's set."""

    def run(batches):
        for batch in batches:
            data, offsets = text_buffers(batch.column(1))
            for first, part, offs in chunks(data, offsets):
                h, at = shingle_sets(part, offs, k)
                sums = [np.concatenate([np.zeros(1, np.uint64), np.cumsum(mix(h * np.uint64(m)))]) for m in (1, 0x9E3779B97F4A7C15)]
                d1, d2 = ((s[at[1:]] - s[at[:-1]]).view(np.int64) for s in sums)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(first, len(offs) - 1), pa.array(np.diff(at)), pa.array(d1), pa.array(d2)], ["doc", "n", "d1", "d2"])

    return _source(docs).mapInArrow(run, "doc long, n long, d1 long, d2 long")


def _doc_key(ids: np.ndarray) -> np.ndarray:
    return mix(ids.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15))


def _doc_filter(ids: DataFrame, bits: int = 24) -> np.ndarray:
    def run(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array(_doc_key(batch.column(0).to_numpy()).view(np.int64))], ["key"])

    return build_filter(ids.mapInArrow(run, "key long"), bits)


def _numbers(column) -> tuple[np.ndarray, np.ndarray]:
    """(values, valid) of a nullable long column."""
    return column.fill_null(0).to_numpy(), column.is_valid().to_numpy(zero_copy_only=False)


def level_filters(docs: DataFrame, reps, pieces: int, k: int) -> list[np.ndarray]:
    """For each of LEVELS a bit filter of the shingles that so many documents hold.

    Every run of texts sends its shingles to the filters' pieces as one blob each, equal ones counted; a piece is
    counted whole by one task, which sets its bits. So rows are few, and no table of counts is kept.
    """

    def deal(batches):
        for batch in batches:
            ids, valid = _numbers(batch.column(0))
            data, offsets = text_buffers(batch.column(1))
            keep = valid & in_filter(reps.value, _doc_key(ids))
            for begin, run, bounds in chunks(data, offsets, DEAL_BYTES):
                found = []
                for first, part, offs in chunks(run, bounds):
                    h, at = shingle_sets(part, offs, k)
                    first += begin
                    found.append(h[np.repeat(keep[first : first + len(at) - 1], np.diff(at))])
                t, c = np.unique(np.concatenate(found), return_counts=True)
                where = piece_of(t, pieces)
                order = np.argsort(where, kind="stable")
                t, c, edges = t[order], np.minimum(c[order], 65535).astype(np.uint16), np.searchsorted(where[order], np.arange(pieces + 1))
                some = np.flatnonzero(np.diff(edges))
                yield pa.RecordBatch.from_arrays(
                    [pa.array(some.astype(np.int32)), *(pa.array([x[edges[i] : edges[i + 1]].tobytes() for i in some.tolist()], pa.binary()) for x in (t, c))], ["piece", "t", "c"]
                )

    def count(table: pa.Table) -> pa.Table:
        t, c = (np.concatenate([np.frombuffer(x.as_buffer(), kind) for x in table.column(name)]) for name, kind in (("t", np.uint64), ("c", np.uint16)))
        order = np.argsort(t)
        t, c = t[order], c[order].astype(np.int64)
        new = np.ones(len(t), bool)
        new[1:] = t[1:] != t[:-1]
        at = np.flatnonzero(new)
        t, total = t[at], np.add.reduceat(c, at)
        fields = [set_bits(t[total >= least], (1 << bits) // pieces).tobytes() for least, bits in zip(LEVELS, LEVEL_BITS, strict=True)]
        return pa.table([pa.array([table.column("piece")[0].as_py()], pa.int32()), pa.array([fields], pa.list_(pa.binary()))], names=["piece", "fields"])

    out = [np.zeros(1 << (bits - 3), np.uint8) for bits in LEVEL_BITS]
    dealt = _source(docs).mapInArrow(deal, "piece int, t binary, c binary")
    for piece, fields in dealt.groupBy("piece").applyInArrow(count, "piece int, fields array<binary>").collect():  # of fixed size, whatever the input
        for whole, field in zip(out, fields, strict=True):
            whole[piece * len(field) : (piece + 1) * len(field)] = np.frombuffer(field, np.uint8)
    return out


def _beginnings(docs: DataFrame, reps, levels, pieces: int, k: int, percent: int, common: int) -> DataFrame:
    """(t, doc, n, top, pos, mid, text): the shingles in the documents' beginnings that others hold too, and where they stand.

    top is the largest partner that a document can have: its overlap with any is at most n less the shingles that it
    alone holds, and the threshold asks for an overlap of percent / (100 + percent) of both sizes together. mid is the
    mean level of all its shingles, in thousandths: how central it is. Its text and its
    parities come with the first of its rows.
    """
    schema = "t long, doc long, n long, top long, pos long, mid long, text string, " + ", ".join(f"{c} long" for c in _SIG)

    def run(batches):
        for batch in batches:
            ids, valid = _numbers(batch.column(0))
            data, offsets = text_buffers(batch.column(1))
            keep = valid & in_filter(reps.value, _doc_key(ids))
            for first, part, offs in chunks(data, offsets):
                h, at = shingle_sets(part, offs, k)
                n = np.diff(at)
                p = np.where(keep[first : first + len(n)], beginning(n, percent, common), 0)
                who = np.repeat(np.arange(len(n)), n)
                level = np.zeros(len(h), np.int64)
                some = np.arange(len(h))
                for f in levels.value:  # every level's shingles are among those of the level below
                    some = some[in_filter(f, h[some], pieces)]
                    level[some] += 1
                alone = np.bincount(who[level == 0], minlength=len(n))
                top = (n - alone) * (100 + percent) // percent - n
                p = np.where(top * 100 >= percent * n, p, 0)
                order = np.lexsort((h, level, who))
                pos = np.empty(len(h), np.int64)
                pos[order] = np.arange(len(h)) - at[who]
                take = (pos < p[who]) & (level > 0)
                mid = 1000 * np.bincount(who, weights=level, minlength=len(n)).astype(np.int64) // np.maximum(n, 1)
                of = who[take]
                columns = (h[take].view(np.int64), ids[first + of], n[of], top[of], pos[take], mid[of])
                once = np.ones(len(of), bool)
                once[1:] = of[1:] != of[:-1]
                text = batch.column(1).take(pa.array(first + of, mask=~once))
                sig = parities(h, who, len(n))
                marks = [pa.array(sig[of, i], mask=~once) for i in range(PARITY)]
                yield pa.RecordBatch.from_arrays([*(pa.array(c) for c in columns), text, *marks], ["t", "doc", "n", "top", "pos", "mid", "text", *_SIG])

    return _source(docs).mapInArrow(run, schema)


def _linked(batch: pa.RecordBatch, k: int, percent: int) -> tuple[np.ndarray, np.ndarray]:
    """Of rows (a, b, x, y), the pairs (a, b) whose texts x and y reach the threshold."""
    keep = np.zeros(batch.num_rows, bool)
    (x, p), (y, q) = (shingle_sets(*text_buffers(batch.column(c)), k) for c in (2, 3))
    for i in range(batch.num_rows):
        a, b = x[p[i] : p[i + 1]], y[q[i] : q[i + 1]]
        same = len(np.intersect1d(a, b, assume_unique=True))
        keep[i] = same > 0 and 100 * same >= percent * (len(a) + len(b) - same)
    return tuple(batch.column(c).to_numpy()[keep] for c in (0, 1))


def verify(texts: DataFrame, pairs: DataFrame, k: int = K, percent: int = PERCENT) -> DataFrame:
    """Links (a, b) that connect what the pairs connect that reach the threshold, on the whole texts (doc, text): for
    each batch a spanning forest, at most one row for each document in it."""
    both = pairs.join(texts.select(F.col("doc").alias("a"), F.col("text").alias("x")), "a").join(texts.select(F.col("doc").alias("b"), F.col("text").alias("y")), "b").select("a", "b", "x", "y")

    def compare(batches):
        for batch in batches:
            ends = np.cumsum(sum(np.diff(text_buffers(batch.column(c))[1]) for c in (2, 3)))
            found, i = [], 0
            while i < batch.num_rows:  # so many rows at a time as have CHUNK_BYTES of text, one at least
                j = max(i + 1, int(np.searchsorted(ends, (ends[i - 1] if i else 0) + CHUNK_BYTES, side="right")))
                found.append(_linked(batch.slice(i, j - i), k, percent))
                i = j
            if found:
                a, b = forest(*(np.concatenate(x) for x in zip(*found, strict=True)))
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], ["a", "b"])

    return both.mapInArrow(compare, "a long, b long")


def join(spark: SparkSession, docs: DataFrame, k: int = K, percent: int = PERCENT, common: int = COMMON, rounds: int = ROUNDS) -> DataFrame:
    """doc_id, n_shingles, component_id for every row of docs."""
    work = Workspace(spark, "jaccard")
    sizes = work.table(describe(docs, k), "sizes")
    real = sizes.where(F.col("doc").isNotNull() & (F.col("n") > 0))
    classes = work.table(real.groupBy("n", "d1", "d2").agg(F.min("doc").alias("rep")), "classes")
    reps = spark.sparkContext.broadcast(_doc_filter(classes.select("rep")))
    # Rows that share a doc_id but not their words are one node: their classes are linked.
    shared = real.groupBy("doc").agg(F.min(F.struct("n", "d1", "d2")).alias("x"), F.max(F.struct("n", "d1", "d2")).alias("y")).where("x <> y").select("doc")
    several = real.join(shared, "doc").join(classes, ["n", "d1", "d2"]).where("doc <> rep").select(F.col("doc").alias("a"), F.col("rep").alias("b")).distinct()
    edges = [work.table(several, "several")]

    total = sizes.agg(F.sum("n")).first()[0] or 0
    pieces = max(PIECES, 1 << (total // PIECE_SHINGLES).bit_length())
    levels = spark.sparkContext.broadcast(level_filters(docs, reps, pieces, k))
    work.release()
    posts = work.table(_beginnings(docs, reps, levels, pieces, k, percent, common), "posts")
    texts = posts.where("text is not null").select("doc", "text")
    marks = posts.where("text is not null").groupBy("doc").agg(*(F.when(F.count(F.lit(1)) == 1, F.first(c)).alias(c) for c in _SIG))

    # A pair's own overlap decides how far into both beginnings its first `common` shared shingles can stand.
    overlap = lambda x, y: F.ceil((x + y) * percent / (100 + percent))
    reach = lambda x, y: x - overlap(x, y) + common
    least = lambda x: F.least(F.lit(common), F.ceil(x * percent / 100))  # noqa: E731  a smaller document may share fewer
    n, m = F.col("n"), F.col("m")
    near = (F.least(n, m) * 100 >= F.greatest(n, m) * percent) & (n <= F.col("m_top")) & (m <= F.col("top")) & (F.col("pos") < reach(n, m)) & (F.col("m_pos") < reach(m, n))
    theirs = [f"u{c}" for c in _SIG]
    differ = lambda size: F.coalesce(sum(F.bit_count(F.col(c).bitwiseXOR(F.col(u))) for c, u in zip(_SIG, theirs, strict=True)), F.lit(0)) <= n + size - 2 * overlap(n, size)
    open_rows = posts.drop("text", *_SIG).withColumn("g", F.col("doc"))
    for r in range(rounds):
        order = (-F.col("mid")) if r == 0 else F.xxhash64(F.lit(r), "g")
        lead = open_rows.groupBy("t").agg(F.min(F.struct(order.alias("h"), "g", F.xxhash64(F.lit(r), "doc").alias("i"), "doc", "n", "top", "pos")).alias("lead"))
        lead = lead.select("t", F.col("lead.doc").alias("lead"), F.col("lead.n").alias("m"), F.col("lead.top").alias("m_top"), F.col("lead.pos").alias("m_pos"), F.col("lead.g").alias("other"))
        led_by = open_rows.join(lead, "t").where((F.col("g") != F.col("other")) & near).groupBy("doc", "lead", "n", "m").agg(F.count(F.lit(1)).alias("c"), F.min("pos").alias("p"))
        bound = led_by.join(marks, "doc").join(marks.select(F.col("doc").alias("lead"), *(F.col(c).alias(u) for c, u in zip(_SIG, theirs, strict=True))), "lead").where(differ(m))
        rarest = F.row_number().over(Window.partitionBy("doc").orderBy("p", "lead"))
        star = bound.withColumn("i", rarest).where((F.col("c") >= least(F.greatest("n", "m"))) | (F.col("i") <= RAREST))
        star = work.table(star.select(F.col("doc").alias("a"), F.col("lead").alias("b")), f"star-{r}")
        edges.append(work.table(verify(texts, star, k, percent), f"led-{r}"))
        if not edges[-1].limit(1).count():
            break
        groups = components(work, _all(edges), f"groups-{r}")
        grouped = open_rows.drop("g").join(groups.withColumnRenamed("node", "doc"), "doc", "left").select("t", "doc", "n", "top", "pos", "mid", F.coalesce("component", "doc").alias("g"))
        if r == rounds - 1:
            open_rows = grouped
            break
        grouped = work.table(grouped, f"grouped-{r}")
        foreign = grouped.groupBy("t").agg(F.min("g").alias("g0"), F.max("g").alias("g1")).where("g0 < g1").select("t")
        open_rows = work.table(grouped.join(foreign, "t"), f"foreign-{r}")
        work.drop(f"grouped-{r}")
        work.release()

    # The token-group matrix of what is left. Of the h shingles that a document shares with a group, a partner in it
    # holds `common` at least, hence one of any h - common + 1: the members are looked up by those that the fewest hold.
    open_rows = work.table(open_rows.join(marks, "doc"), "open")
    alone = F.min("doc") == F.max("doc")  # one member alone holds it: its parities bound the overlap
    unions = open_rows.groupBy("t", "g").agg(F.min("n").alias("low"), F.max("n").alias("high"), F.max("top").alias("most"), F.min("pos").alias("m_pos"), F.count(F.lit(1)).alias("held"), *(F.when(alone, F.first(c)).alias(u) for c, u in zip(_SIG, theirs, strict=True))).withColumnRenamed("g", "other")
    fits = (F.col("low") * percent <= F.col("n") * 100) & (F.col("high") * 100 >= F.col("n") * percent) & (F.col("low") <= F.col("top")) & (F.col("n") <= F.col("most"))
    fits &= (F.col("pos") < reach(n, F.col("low"))) & (F.col("m_pos") < reach(F.col("high"), n))
    fits &= differ(F.col("low"))
    hits = open_rows.join(unions, "t").where((F.col("other") < F.col("g")) & fits).select("t", "doc", "n", "top", "pos", "other", "held", *_SIG)
    bound = Window.partitionBy("doc", "other")
    rare = hits.withColumn("h", F.count(F.lit(1)).over(bound)).withColumn("i", F.row_number().over(bound.orderBy("held", "t"))).where(F.col("i") <= F.col("h") - least(n) + 1)
    member = open_rows.select("t", F.col("doc").alias("b"), F.col("n").alias("m"), F.col("top").alias("m_top"), F.col("pos").alias("m_pos"), F.col("g").alias("other"), *(F.col(c).alias(u) for c, u in zip(_SIG, theirs, strict=True)))
    pairs = rare.join(member, ["t", "other"]).where(near & differ(m)).select(F.col("doc").alias("a"), "b").distinct()
    opened = work.table(pairs, "pairs")
    edges.append(work.table(verify(texts, opened, k, percent), "opened"))
    work.release()

    # A class has the component of its representative, the smallest document in it.
    reached = components(work, _all(edges), "all").select(F.col("node").alias("rep"), "component")
    named = sizes.join(classes, ["n", "d1", "d2"], "left").join(reached, "rep", "left")
    alone = F.col("n") == 0
    return named.select(F.col("doc").alias("doc_id"), F.col("n").alias("n_shingles"), F.when(alone | F.col("doc").isNull(), F.col("doc")).otherwise(F.coalesce("component", "rep")).alias("component_id"))


def _all(edges: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, edges)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return join(spark, read_table(spark, sf_dir, "documents"))


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str, keep_empty: bool = True) -> DataFrame:
    """Pipeline stage: of each group one row stays, that of the smallest id; same columns.

    Rows that repeat that id are one document, of which the row with the smallest text hash stays. Documents without
    words link with nothing: they stay, or with keep_empty=False (earlier stages may have emptied them) they all go.
    Rows without doc_id link with nothing and stay alike.
    """
    work = Workspace(spark, "near")
    out = work.table(join(spark, docs), "groups").where("doc_id is not null")
    per = out.groupBy(F.col("doc_id").alias("key")).agg(F.max(F.col("doc_id") != F.col("component_id")).alias("gone"), F.count(F.lit(1)).alias("rows"))
    marks = work.table(per.where("gone or rows > 1"), "marks")
    docs = docs if keep_empty else docs.where(F.coalesce(F.col("text"), F.lit("")).rlike(r"[^\x20\x09-\x0D]"))
    # A filter without misses tells which rows may be marked; only those are exchanged with the marks.
    marked = spark.sparkContext.broadcast(_doc_filter(marks.select("key")))
    at = docs.columns.index("doc_id")

    def side(may: bool):
        def run(batches):
            for batch in batches:
                ids, valid = _numbers(batch.column(at).cast(pa.int64()))
                yield batch.filter(pa.array((valid & in_filter(marked.value, _doc_key(ids))) == may))

        return docs.mapInArrow(run, docs.schema)

    row = side(True).select(F.col("doc_id").cast("long").alias("key"), F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("row"), F.xxhash64("text").alias("h"))
    left = row.join(marks, "key", "left")
    rest = left.where("gone is null").select("row.*")
    first = left.where("not gone").groupBy("key").agg(F.min_by("row", "h").alias("row")).select("row.*")
    return side(False).unionByName(rest).unionByName(first)
