"""Training-data operators against brute force on small fixtures with the odd cases."""

import collections
import hashlib
import math
import random
import re
import zlib

import numpy as np
import pytest

from objdelta.llm import decontaminate, jaccard_join, line_dedup, packing, pitman_yor, quality, suffix_dedup, toxicity, url_filter

WORD = r"[^\x20\x09-\x0D]+"


def lower(t):
    return re.sub("[A-Z]", lambda m: m.group().lower(), t or "")


def frame(spark, docs, extra=True):
    rows = [(d, t, "x", "y", 1) for d, t in docs]
    return spark.createDataFrame(rows, "doc_id long, text string, th string, __pos string, n long") if extra else spark.createDataFrame(docs, "doc_id long, text string")


@pytest.fixture(scope="module")
def docs():
    r = random.Random(11)
    words = ["w%d" % i for i in range(50)] + ["É", "ñu", "Über", "the", "of"]
    base = [[r.choice(words) for _ in range(r.choice([2, 4, 5, 6, 30, 90]))] for _ in range(40)]
    out = []
    for i in range(160):
        b = list(r.choice(base))
        for _ in range(r.choice([0, 0, 1, 2, 6])):
            b[r.randrange(len(b))] = r.choice(words)
        out.append((3 * i + 2, "".join(w + r.choice([" ", " ", " ", "\n", "\t"]) for w in b)))
    out += [(9001, None), (9002, ""), (9003, " \n\t"), (9004, "same line here\nsame line here\nother"), (9005, "  SAME line here \nshort\n"), (9006, "a" * 3000), (9007, "ab" * 1500), (9008, "solo"), (9009, out[5][1]), (9010, out[5][1] * 3)]
    return out


# ---------------------------------------------------------------- 1


def test_url_filter(spark):
    urls = ["http://a.example.net/en/1", "http://example.net/de/", "https://EXAMPLE.com/de/x?y#z", "http://sub.org/fr/1", "http://org/fr/", "http://xorg/fr/", "nothing", None, "://", "http://h?/en/", "http://net", "ftp://net/", "http://a.net/x://b.org/fr/", "http://" + "a" * 5000 + ".com/" + "p/" * 3000]
    df = spark.createDataFrame([(i, u, "z") for i, u in enumerate(urls)] * 2, "page_id long, url string, host string")
    got = {r.page_id: r for r in url_filter.judge(df).collect()}

    def parts(u):
        if u is None or "://" not in u:
            return "", ""
        rest = u.split("://", 1)[1]
        m = re.match(r"([^/?#]*)([^?#]*)", rest, re.S)
        return lower(m[1]), m[2]

    for i, u in enumerate(urls):
        h, p = parts(u)
        fits = [(len(a + b), a + b, v) for a, b, v in url_filter.RULES if (h == a or h.endswith("." + a)) and p.startswith(b)]
        rule = max(fits)[1:] if fits else (None, None)
        assert (got[i].host, got[i].path, got[i].rule) == (h, p, rule[0])
        assert got[i].verdict == (rule[1] or got[i].verdict) and got[i].verdict in ("allow", "block")
    labelled = spark.createDataFrame([(f"http://bad{i}.com/spam", 1) for i in range(30)] + [(f"http://good{i}.com/wiki", 0) for i in range(30)] + [(None, 1), ("x", None)], "url string, label int")
    asked = spark.createDataFrame([(1, "http://bad99.com/spam"), (2, "http://good99.com/wiki")], "page_id long, url string")
    assert [r.verdict for r in url_filter.judge(asked, labelled).orderBy("page_id").collect()] == ["block", "allow"]
    assert url_filter.judge(df.limit(0)).count() == 0


# ---------------------------------------------------------------- 2


def test_decontamination(spark):
    r = random.Random(5)
    text = lambda n: " ".join(r.choice("abcdefghij") + str(r.randint(0, 99)) for _ in range(n))
    items = [(i, text(r.choice([3, 12, 40]))) for i in range(12)] + [(99, None), (98, "")]
    plain = [(i, text(60)) for i in range(20)]
    leaked = []
    for i, (n, t) in enumerate(items[:12]):
        w = t.split()
        half = len(w) // 2
        moved = " ".join(w[half:] + ["zzz"] + w[:half]) if len(w) >= 12 else t
        leaked.append((100 + i, f"{text(20)} {moved.upper()}. {text(5)}", n))
    partial = (500, text(10) + " " + " ".join(items[2][1].split()[: len(items[2][1].split()) // 3]))
    docs = plain + [(d, t) for d, t, _ in leaked] + [partial, (600, None), (601, ""), (100, leaked[0][1])]
    bench = spark.createDataFrame(items, "item_id long, text string")
    df = frame(spark, docs)
    small = {(x.doc_id, x.item_id): x for x in decontaminate.leaks(spark, df, bench).collect()}
    assert set(small) == {(d, n) for d, _, n in leaked}
    assert all(x.coverage == 1 for x in small.values())
    assert max(x.n_tiles for x in small.values()) == 2
    large = {(x.doc_id, x.item_id) for x in decontaminate.leaks(spark, df, bench, max_tokens=1).collect()}
    assert large == set(small)
    for limit in (1, 10**6):
        kept = decontaminate.clean(spark, df, bench, max_tokens=limit)
        assert kept.columns == df.columns and sorted(x.doc_id for x in kept.collect()) == sorted([d for d, _ in plain] + [500, 600, 601])
    assert decontaminate.leaks(spark, df, bench.limit(0)).count() == 0


def test_decontamination_keeps_rows_apart_on_both_paths(spark):
    """Null and shared ids with different texts: the seed join must give what the broadcast index gives."""
    r = random.Random(6)
    text = lambda n: " ".join(r.choice("abcdefghij") + str(r.randint(0, 99)) for _ in range(n))
    items = [(1, text(12)), (None, text(12)), (3, text(12)), (3, text(12)), (4, "lone"), (5, None)]
    leak = [f"{text(8)} {t} {text(8)}" if t else text(8) for _, t in items]
    docs = [(None, leak[0]), (None, text(30)), (7, leak[1]), (7, text(30)), (7, leak[2]), (8, leak[3]), (8, leak[3]), (None, leak[4]), (9, text(30)), (9, None), (None, None), (None, "")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    df = frame(spark, docs)
    want = [(None, 1), (7, None), (7, 3), (8, 3), (None, 4)]
    bad = set(leak)
    for limit in (1, 10**6):
        got = decontaminate.leaks(spark, df, bench, max_tokens=limit).collect()
        assert collections.Counter((x.doc_id, x.item_id) for x in got) == collections.Counter(want)
        kept = decontaminate.clean(spark, df, bench, max_tokens=limit)
        assert kept.schema == df.schema
        assert collections.Counter((x.doc_id, x.text) for x in kept.collect()) == collections.Counter(x for x in docs if x[1] not in bad)


def test_tiling_takes_the_longest_first():
    a = np.arange(10, dtype=np.uint64)
    doc = np.concatenate([a[5:], a[:8]])
    pairs = [(i, int(doc[i])) for i in range(len(doc) - 1) if doc[i + 1] == doc[i] + 1]
    assert decontaminate.tile(doc, a, pairs, 2) == (2, 10)


# ---------------------------------------------------------------- 4, 10


def test_toxicity(spark):
    r = random.Random(2)
    clean = [(i, " ".join(f"{r.choice('bcdfg')}a{r.choice('lmnp')}e{r.randint(0, 999)}x" for _ in range(40)) + ".") for i in range(300)]
    bad = [(1000 + i, clean[i][1] + f" you zorvek{r.choice('abcde')} and zorvek{r.choice('xyz')} again.") for i in range(150)]
    odd = [(5000, None), (5001, ""), (5002, "you are an idiot"), (5003, "x" * 50_000), (5004, "you zorvekq zorvekw!")]
    labels = spark.createDataFrame([(d, 0, 1) for d, _ in clean] + [(d, 1, 1) for d, _ in bad] + [(5000, None, None)], "doc_id long, toxic int, quality int")
    got = {x.doc_id: x for x in toxicity.score(spark, frame(spark, clean + bad + odd), labels).collect()}
    assert len(got) == 455
    held = [x for x in got.values() if x.held_out and x.doc_id < 5000]
    assert all(x.held_out == (zlib.crc32(str(d).encode()) % 3 == 1) for d, x in got.items())
    assert sum(x.predicted == (x.doc_id >= 1000) for x in held) / len(held) > 0.97
    assert got[5004].predicted == 1 and got[5000].predicted == got[5001].predicted == got[5003].predicted == 0
    none = toxicity.score(spark, frame(spark, odd), labels.limit(0)).collect()
    assert [x.doc_id for x in none if x.score > 0.5] == [5002]


def test_grammar_weighs_the_clause():
    g = toxicity.Grammar()
    score = {t: g.score(t) for t in ("you idiot", "idiot", "he is not an idiot", "she said idiot", "i kill you", "nice", "")}
    assert score["you idiot"] > score["idiot"] > score["she said idiot"] > score["he is not an idiot"] > score["nice"] == score[""]
    assert g.kinds("Not now. You idiot!") == {"aimed": 1.0}
    assert g.kinds("bidiot nonidiot") == {}


def test_quality(spark):
    r = random.Random(3)
    good = [(i, "\n".join(" ".join("word%d" % r.randint(0, 999) for _ in range(r.randint(5, 15))) + "." for _ in range(r.randint(1, 6)))) for i in range(200)]
    junk = [(1000 + i, "\n".join(" | ".join(str(r.randint(0, 99999)) for _ in range(9)) for _ in range(r.randint(1, 6)))) for i in range(120)]
    odd = [(5000, None), (5001, ""), (5002, "\n\n\n"), (5003, "y" * 60_000)]
    labels = spark.createDataFrame([(d, 1) for d, _ in good] + [(d, 0) for d, _ in junk] + [(5000, None)], "doc_id long, quality int")
    got = {x.doc_id: x for x in quality.score(spark, frame(spark, good + junk + odd), labels).collect()}
    held = [x for x in got.values() if x.held_out and x.doc_id < 5000]
    assert len(got) == 324 and held and sum(x.predicted == (x.doc_id < 1000) for x in held) / len(held) > 0.97
    assert all(0 <= x.score <= 1 for x in got.values())
    assert {x.score for x in quality.score(spark, frame(spark, odd), labels.limit(0)).collect()} == {0.5}


def test_forward_backward_equals_enumeration():
    r = np.random.default_rng(1)
    counts = np.array([4, 1, 3])
    unary, trans = r.normal(size=8), r.normal(size=(2, 2))
    got, pairs = quality.marginals(unary, trans, counts, True)
    want, total, at = [], np.zeros((2, 2)), 0
    for n in counts:
        z, p, q = 0.0, np.zeros(n), np.zeros((2, 2))
        for m in range(2**n):
            y = [(m >> i) & 1 for i in range(n)]
            w = math.exp(sum(unary[at + i] * y[i] for i in range(n)) + sum(trans[y[i], y[i + 1]] for i in range(n - 1)))
            z += w
            p += w * np.array(y)
            for i in range(n - 1):
                q[y[i], y[i + 1]] += w
        want += list(p / z)
        total += q / z
        at += n
    assert np.allclose(got, want) and np.allclose(pairs, total)


# ---------------------------------------------------------------- 5


def test_pitman_yor(spark, docs):
    got = {x.doc_id: x for x in pitman_yor.score(spark, frame(spark, docs)).collect()}
    toks = {d: [*re.findall(WORD, lower(t)), None] for d, t in docs}
    held = {d: zlib.crc32(str(d).encode()) % 5 == 1 for d in toks}
    c = collections.Counter(w for d, ws in toks.items() if not held[d] for w in ws)
    n, v = sum(c.values()), len(c)
    assert set(got) == set(toks)
    for d, ws in toks.items():
        x = got[d]
        assert (x.held_out, x.n_tokens, x.n_known, x.train_tokens) == (held[d], len(ws), sum(c[w] > 0 for w in ws), n)
        assert abs(x.base_score - sum(math.log10((c[w] + 0.5) / (n + 0.5 * (v + 1))) for w in ws)) < 1e-6
        assert x.score <= 0
    assert sum(x.score for x in got.values() if x.held_out) > sum(x.base_score for x in got.values() if x.held_out)
    alone = pitman_yor.score(spark, frame(spark, [(1, "a b"), (2, None)]).where("doc_id < 0"))
    assert alone.count() == 0


def test_pitman_yor_contexts_are_words(spark):
    """With one table for each pair the scores have a closed form over true word pairs, of far more contexts than any class of hashes."""
    r = random.Random(8)
    docs = [(i, " ".join(r.choice(["the", "of", f"a{r.randrange(6000)}", f"a{r.randrange(60)}"]) for _ in range(r.randrange(60)))) for i in range(400)] + [(9001, None), (9002, "")]
    held = {d: zlib.crc32(str(d).encode()) % 5 == 1 for d, _ in docs}
    pairs = {d: list(zip([None, *(ws := (t or "").split())], [*ws, ""], strict=True)) for d, t in docs}
    c = collections.Counter(p for d, ps in pairs.items() if not held[d] for p in ps)
    inside, tables, parent = collections.Counter(), collections.Counter(u for u, _ in c), collections.Counter(w for _, w in c)
    for (u, _), n in c.items():
        inside[u] += n
    share = lambda x: sum(v == 1 for v in x.values()) / (sum(v == 1 for v in x.values()) + 2 * sum(v == 2 for v in x.values()))
    d2, d1 = (min(0.95, max(0.05, share(x))) for x in (c, parent))
    assert len(inside) > 1500

    def p(u, w):
        above = (parent[w] - d1 if parent[w] else 1 + d1 * len(parent)) / (1 + len(c))
        return (c[u, w] - d2 * (c[u, w] > 0) + (1 + d2 * tables[u]) * above) / (1 + inside[u])

    got = {x.doc_id: x.score for x in pitman_yor.score(spark, frame(spark, [*docs, (None, "the of")]), sweeps=0).collect()}
    assert set(got) == set(held)
    for d, ps in pairs.items():
        assert abs(got[d] - sum(math.log10(p(*x)) for x in ps)) < 1e-6


def test_predictive_sums_to_one():
    r = np.random.default_rng(5)
    contexts, words = 4, np.arange(6, dtype=np.uint64)
    w, u = (x.ravel() for x in np.meshgrid(np.arange(6), np.arange(contexts), indexing="ij"))
    c = r.integers(1, 80, len(w))
    lens = np.full(6, contexts)
    b = pitman_yor.Bucket(0, pitman_yor.pack((words, lens.astype(np.uint8), u.astype(np.uint16), c.astype(np.uint32))), contexts)
    t = pitman_yor.Totals(contexts)
    t.customers, t.n, t.v, t.d1, t.d2 = np.bincount(u, weights=c), int(c.sum()), 6, 0.4, 0.6
    for s in range(4):
        if s:
            b.sweep(t)
        t.tables.append(np.bincount(b.u, weights=b.seats[-1]).astype(float))
        t.all_tables.append(float(b.parent[-1].sum()))
    for ctx in range(contexts):
        p = b.predictive(np.array([0, 1, 2, 3, 4, 5, 0]), np.array([True] * 6 + [False]), np.full(7, ctx), t)
        assert abs(p.sum() - 1) < 1e-9 and (p > 0).all()
    assert all((x >= 1).all() and (x <= b.c).all() for x in b.seats)


def test_table_counts_follow_their_conditional():
    d, odds, c = 0.5, 0.7, 6
    s = pitman_yor.log_stirling(d)
    p = np.exp(s[c, 1 : c + 1] + np.arange(1, c + 1) * math.log(odds))
    drawn = pitman_yor.draw_tables(np.full(40_000, c), np.full(40_000, odds), s, np.random.default_rng(1))
    assert np.allclose(np.bincount(drawn, minlength=c + 1)[1:] / 40_000, p / p.sum(), atol=0.01)


# ---------------------------------------------------------------- 6


def shingles(t):
    w = re.findall(WORD, lower(t))
    return frozenset(tuple(w[i : i + 5]) for i in range(len(w) - 4)) if len(w) >= 5 else frozenset([tuple(w)] if w else [])


def test_jaccard_join(spark, docs):
    sets = {d: shingles(t) for d, t in docs}
    low = {d: d for d in sets}
    ids = sorted(sets)
    links = [(a, b) for i, a in enumerate(ids) for b in ids[i + 1 :] if sets[a] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b])]
    for _ in ids:
        for a, b in links:
            low[a] = low[b] = min(low[a], low[b])
    df = frame(spark, [*docs, (None, docs[3][1])])
    got = jaccard_join.join(spark, df).collect()
    assert {x.doc_id: (x.n_shingles, x.component_id) for x in got if x.doc_id is not None} == {d: (len(sets[d]), low[d]) for d in ids}
    assert len(links) > 20 and len(got) == len(docs) + 1
    kept = jaccard_join.stage(spark, df, "")
    assert kept.columns == df.columns
    assert sorted(x.doc_id for x in kept.collect() if x.doc_id is not None) == sorted({low[d] for d in ids})


def test_jaccard_stage_repeats_and_empties(spark):
    long = " ".join(f"w{i}" for i in range(40))
    rows = [(1, long, "a"), (1, long, "a"), (1, long + " x", "b"), (2, long, "c"), (7, "", "d"), (8, " \n", "e"), (None, long, "f"), (None, None, "g")]
    df = spark.createDataFrame(rows, "doc_id long, text string, mark0 string")
    kept = [(r.doc_id, r.mark0) for r in jaccard_join.stage(spark, df, "").collect()]
    assert sorted(d for d, _ in kept if d) == [1, 7, 8] and {m for d, m in kept if d is None} == {"f", "g"}
    bare = jaccard_join.stage(spark, df, "", keep_empty=False)
    assert sorted((r.doc_id or 0) for r in bare.collect()) == [0, 1] and bare.columns == df.columns
    assert jaccard_join.stage(spark, df.limit(0), "").count() == 0


def test_jaccard_large_group_of_near_copies(spark):
    """Copies of one text with two words changed each: one group, and few rows on the way to it."""
    r = random.Random(5)
    base = [f"v{i}" for i in range(120)]
    docs = []
    for i in range(300):
        t = list(base)
        for _ in range(r.choice([1, 2, 3])):
            t[r.randrange(120)] = f"u{r.randrange(40)}"
        docs.append((i, " ".join(t)))
    sets = [shingles(t) for _, t in docs]
    low = list(range(300))
    while True:
        new = [min(low[j] for j in range(300) if i == j or 100 * len(sets[i] & sets[j]) >= 75 * len(sets[i] | sets[j])) for i in range(300)]
        if new == low:
            break
        low = new
    got = {r.doc_id: r.component_id for r in jaccard_join.join(spark, frame(spark, docs)).collect()}
    assert got == dict(enumerate(low))


# ---------------------------------------------------------------- 7


def test_line_dedup(spark, docs):
    df = frame(spark, docs)
    key = lambda x: lower(x.strip(" \t\n\x0b\x0c\r"))
    first = {}
    for d, t in docs:
        for x in (t or "").split("\n"):
            if len(key(x)) >= 10:
                first[key(x)] = min(first.get(key(x), d), d)
    got = {x.doc_id: x for x in line_dedup.digest(spark, df).collect()}
    for d, t in docs:
        lines = (t or "").split("\n")
        kept = [x for x in lines if first.get(key(x), d) >= d]
        assert (got[d].n_lines, got[d].n_dropped, got[d].kept_sha256) == (len(lines), len(lines) - len(kept), hashlib.sha256("\n".join(kept).encode()).hexdigest())
    out = line_dedup.stage(spark, df.withColumnRenamed("n", "n_chars"), "")
    assert out.columns == ["doc_id", "text", "th", "__pos", "n_chars"] and out.count() == len(docs)
    assert line_dedup.digest(spark, df.limit(0)).count() == 0


def test_line_dedup_clashing_columns(spark):
    names = ["__doc", "__text", "__t", "__split", "__bounds", "__out", "row", "kept", "lines", "dropped", "full"]
    df = spark.createDataFrame([(i, "one long line\nx\nanother long line", *["v"] * len(names)) for i in (1, 2, None)], "doc_id long, text string, " + ", ".join(f"{n} string" for n in names))
    out = line_dedup.stage(spark, df, "")
    assert out.columns == df.columns
    assert {(r.doc_id, r.text, r.kept) for r in out.collect()} == {(1, df.first().text, "v"), (2, "x", "v"), (None, df.first().text, "v")}


def test_run_store_compacts(spark):
    from objdelta.llm.common import Workspace

    store = line_dedup.RunStore(Workspace(spark, "t"), fanout=2)
    for i in range(5):
        store.add(spark.createDataFrame([(h, h, i) for h in range(i, i + 3)], "__h1 long, __h2 long, __first long"))
    assert {r[0]: r[2] for r in store.first().collect()} == {0: 0, 1: 0, 2: 0, 3: 1, 4: 2, 5: 3, 6: 4}
    assert {k: len(v) for k, v in store.levels.items() if v} == {2: 1, 0: 1}


# ---------------------------------------------------------------- 8


def test_packing(spark, docs):
    from tokenizers import Tokenizer

    long = [(20_000 + i, " ".join(t or "" for _, t in docs) * 2) for i in range(3)]
    all_docs = docs + long + [(None, "null id")]
    full = Tokenizer.from_file(packing.tokenizer_path())
    rows = packing.pack(spark, frame(spark, all_docs)).collect()
    by_doc, by_seq = collections.defaultdict(list), collections.defaultdict(list)
    for x in rows:
        by_doc[x.doc_id].append(x)
        by_seq[x.sequence_id].append(x)
    for d, t in all_docs:
        ids = np.array(full.encode(t or "", add_special_tokens=False).ids + [2], "<u4")
        at = 0
        for x in sorted(by_doc[d], key=lambda x: x.start):
            assert x.start == at and x.doc_tokens == len(ids) and x.ids_crc32 == zlib.crc32(ids[at : at + x.length].tobytes())
            at += x.length
        assert at == len(ids)
    for pieces in by_seq.values():
        at = 0
        for x in sorted(pieces, key=lambda x: x.offset):
            assert x.offset == at
            at += x.length
        assert at <= 4096
    assert sum(x.length for x in rows) / (4096 * len(by_seq)) > 0.5
    assert packing.pack(spark, frame(spark, docs).limit(0)).count() == 0


def test_encoder_equals_the_whole_tokenizer():
    from tokenizers import Tokenizer

    e, full = packing.Encoder(packing.tokenizer_path()), Tokenizer.from_file(packing.tokenizer_path())
    for t in ["It's  a.b ab.. É.,x’ ÀB. İx ﬁ \t tab nb <|endoftext|>x foo, Bar. .,", "l'été d'ß éx. CAFÉ, naïve!", "don't I'll we've.", "ＡＢ Σας ΣΑΣ. 你好, ok", ", . .. a, , b.", "", "x" * 300, "12 3a4 a1,"]:
        for _ in range(2):
            assert np.frombuffer(e.ids(t), "<u4").tolist() == full.encode(t, add_special_tokens=False).ids


# ---------------------------------------------------------------- 9


def brute_suffix(docs, width=50):
    seen, out = {}, collections.defaultdict(list)
    for d, t in docs:
        b = (t or "").encode()
        for i in range(len(b) - width + 1):
            if d is not None:
                seen[b[i : i + width]] = min(seen.get(b[i : i + width], d), d)
    for d, t in docs:
        b = (t or "").encode()
        gone = bytearray(len(b))
        for i in range(len(b) - width + 1):
            if d is not None and seen[b[i : i + width]] < d:
                gone[i : i + width] = b"\1" * width
        kept = bytes(x for x, y in zip(b, gone, strict=True) if not y)
        out[d].append((len(b), sum(gone), sum(gone[i] and (i == 0 or not gone[i - 1]) for i in range(len(gone))), hashlib.sha256(kept).hexdigest()))
    return {d: sorted(v) for d, v in out.items()}


def test_suffix_dedup_rejects_widths_beyond_a_run(spark, docs):
    for width, gram in ((136, 16), (10, 16), (50, 0)):
        with pytest.raises(ValueError, match="width"):
            suffix_dedup.remove(spark, frame(spark, docs), width=width, gram=gram)


def test_suffix_dedup(spark, docs):
    r = random.Random(3)
    pool = ["".join(r.choice("ab cdé") for _ in range(r.randint(40, 160))) for _ in range(20)]
    mixed = [(30_000 + 3 * i, "".join(r.choice(pool)[r.randint(0, 20) :] if r.random() < 0.6 else "".join(r.choice("abcdefgh \n") for _ in range(r.randint(5, 90))) for _ in range(r.randint(0, 7)))) for i in range(80)]
    all_docs = docs + mixed + [(None, docs[5][1] * 4), (7, mixed[4][1] * 2), (7, mixed[5][1])]
    want = brute_suffix(all_docs)
    got = collections.defaultdict(list)
    for x in suffix_dedup.remove(spark, frame(spark, all_docs)).drop("kept").collect():
        got[x.doc_id].append((x.n_bytes, x.n_removed, x.n_spans, x.kept_sha256))
    assert {d: sorted(v) for d, v in got.items()} == want
    assert suffix_dedup.remove(spark, frame(spark, docs).limit(0)).count() == 0


def test_loser_tree_merges_front_coded_runs():
    r = random.Random(9)
    words = ["".join(r.choice("ab") for _ in range(r.randint(1, 12))).encode() for _ in range(300)]
    runs = [suffix_dedup.encode_run([(w, (b"", i, 0, 0, 1)) for w in words[i::7]]) for i in range(7)]
    out = list(suffix_dedup.LoserTree([suffix_dedup.decode_run(b) for b in runs]))
    assert [x[1] for x in out] == sorted(words)
    for (_, a, _), (known, b, _) in zip(out, out[1:], strict=False):
        common = 0
        while common < min(len(a), len(b)) and a[common] == b[common]:
            common += 1
        assert known == common


def test_pitman_yor_scores_do_not_depend_on_dealing(spark, docs, monkeypatch):
    df = frame(spark, docs)
    one = {r.doc_id: r.score for r in pitman_yor.score(spark, df.coalesce(1)).collect()}
    monkeypatch.setattr(pitman_yor, "BUCKET_BYTES", 500)
    monkeypatch.setattr(pitman_yor, "SEGMENT_BYTES", 700)
    other = {r.doc_id: r.score for r in pitman_yor.score(spark, df.repartition(7)).collect()}
    assert one.keys() == other.keys() and all(abs(one[d] - other[d]) < 1e-6 for d in one)


def test_poisson_moments():
    r = np.random.default_rng(3)
    for mean in (0.2, 3.0, 40.0, 900.0):
        x = pitman_yor.poisson(np.full(50_000, mean), r.random(50_000), r.random(50_000))
        assert abs(x.mean() - mean) < 0.05 * mean and abs(x.var() - mean) < 0.05 * mean


def test_tiles_against_brute_force():
    """Longest free match first, ties by place in the document, then in the item, until none of k tokens is left."""

    def brute(doc, item, k):
        used_doc, used_item, tiles = set(), set(), []
        while True:
            best = (0, 0, 0)
            for i in range(len(doc)):
                for j in range(len(item)):
                    n = 0
                    while i + n < len(doc) and j + n < len(item) and doc[i + n] == item[j + n] and i + n not in used_doc and j + n not in used_item:
                        n += 1
                    best = min(best, (-n, i, j))
            n, i, j = -best[0], *best[1:]
            if n < k:
                return len(tiles), sum(tiles)
            tiles.append(n)
            used_doc |= set(range(i, i + n))
            used_item |= set(range(j, j + n))

    r = random.Random(4)
    for _ in range(150):
        k = r.choice([2, 3])
        item = [r.randrange(4) for _ in range(r.randrange(k, 12))]
        cut = r.randrange(len(item))
        doc = [r.randrange(4) for _ in range(r.randrange(8))] + item[cut:] + [r.randrange(4) for _ in range(r.randrange(4))] + item[:cut]
        pairs = [(i, j) for i in range(len(doc) - k + 1) for j in range(len(item) - k + 1) if doc[i : i + k] == item[j : j + k]]
        if pairs:
            assert decontaminate.tile(np.array(doc), np.array(item), pairs, k) == brute(doc, item, k)


def test_classifiers_on_empty_tables_null_ids_and_repeats(spark):
    docs = spark.createDataFrame([(1, "you idiot"), (1, "you idiot"), (None, "a fine day"), (4, None), (5, "")], "doc_id long, text string")
    labels = spark.createDataFrame([(1, 1, 1), (4, 0, 0), (None, 1, 1), (5, None, None)], "doc_id long, quality int, toxic int")
    for op in (toxicity, quality):
        got = op.score(spark, docs, labels).collect()
        assert sorted((r.doc_id or 0) for r in got) == [0, 1, 1, 4, 5]
        assert all(0 <= r.score <= 1 and r.held_out in (True, False) and r.predicted in (0, 1) for r in got)
        assert len({r.score for r in got if r.doc_id == 1}) == 1 and not next(r for r in got if r.doc_id is None).held_out
        assert op.score(spark, docs.limit(0), labels).count() == 0 and op.score(spark, docs, labels.limit(0)).count() == 5
