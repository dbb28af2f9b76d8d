"""Whole-text operators against brute force, with nulls, empty tables, repeats and clashing columns."""

import hashlib
import random

import numpy as np
import pyarrow as pa
import pytest

pytest.importorskip("kgflow.llm")

from kgflow.llm import ann, bpe, decontam, license, lines, neardup, packs, registry, substring, toxicity, urlfilter, words

VOCAB = [f"w{i}" for i in range(60)]


def corpus(seed=1, n=60):
    """(id, text): random texts, copies, near copies, shared passages, nulls, empties, one long text, repeated rows."""
    r = random.Random(seed)
    say = lambda k: " ".join(r.choice(VOCAB) for _ in range(k))
    passage, rows = say(40), []
    for i in range(n):
        rows.append((i, say(r.randint(1, 80)).replace(" w3", "\nW3").replace(" w5", "  \t w5")))
    for i in range(n, n + 10):
        rows.append((i, f"{say(5)} {passage} {say(r.randint(0, 9))}"))
    rows += [(n + 10, rows[3][1]), (n + 11, rows[3][1]), (n + 12, None), (n + 13, ""), (n + 14, "  \n "), (n + 15, say(4000)), (n + 16, "one two"), (n + 17, "one two")]
    long = rows[n + 15][1].split()
    rows.append((n + 18, " ".join(long[:2000] + ["changed"] + long[2001:])))
    rows += [(n + 19, None), (5, rows[5][1])]
    return rows


def frame(spark, rows):
    return spark.createDataFrame([(i, t, "x", 1, 2) for i, t in rows], "doc_id long, text string, id string, key int, bucket int").repartition(5)


def test_words_and_windows():
    texts = ["a b  c", None, "", " d\te\x0bf ", "é ü x", "tail"]
    got = []
    for c in words.chunks(pa.array(texts), most=8):
        got += [[c.word(i).decode() for i in range(c.first[t], c.first[t + 1])] for t in range(c.hi - c.lo)]
    assert got == [(t or "").encode().split() and [w.decode() for w in (t or "").encode().split()] for t in texts]
    h = {}
    for c in words.chunks(pa.array(["a b c d", "x a b c", "c b a"])):
        key, own, pos = words.windows(c, 3)
        h |= {(int(o), int(p)): int(k) for k, o, p in zip(key, own, pos, strict=True)}
    assert h[0, 0] == h[1, 1] and len(set(h.values())) == 4


def test_packs_round_trip_and_spark_hash(spark):
    x = np.array([0, 1, -5, 2**62, -(2**63)], np.int64)
    a, b = packs.unpack(packs.pack(x, np.arange(5)))
    assert (a.view(np.int64) == x).all() and b.tolist() == list(range(5))
    from pyspark.sql import functions as F

    want = [r[0] for r in spark.createDataFrame([(int(v),) for v in x], "v long").select(F.xxhash64("v")).collect()]
    assert packs.xxhash64(x).tolist() == want


def brute_substring(rows, k=13):
    least = {}
    toks = [(i, (t or "").encode().split()) for i, t in rows]
    for i, w in toks:
        for p in range(len(w) - k + 1):
            g = tuple(w[p : p + k])
            least[g] = min(least.get(g, i), i)
    out = []
    for i, w in toks:
        gone = set()
        for p in range(len(w) - k + 1):
            if least[tuple(w[p : p + k])] < i:
                gone |= set(range(p, p + k))
        kept = b" ".join(x for j, x in enumerate(w) if j not in gone)
        out.append((i, len(w), len(gone), kept.decode()))
    return sorted(out)


@pytest.mark.parametrize("block", [1 << 20, 64])
def test_substring(spark, monkeypatch, block):
    monkeypatch.setattr(packs, "BLOCK", block)
    rows = corpus()
    docs = frame(spark, rows)
    out = substring.deduplicate(docs).collect()
    assert sorted((r.doc_id, r.n_words, r.n_removed, r.kept_text) for r in out) == brute_substring(rows)
    text = {}
    for i, t in rows:
        text.setdefault(i, []).append((t or "").split())
    n = 0
    for r in out:
        for x in r.spans:  # the words of a path stand at its source coordinates
            assert x.source_doc < r.doc_id
            assert any(a[x.start : x.start + x.length] == b[x.source_start : x.source_start + x.length] for a in text[r.doc_id] for b in text[x.source_doc])
            n += 1
        ends = sorted((x.source_doc, x.source_start - x.start, x.start, x.length) for x in r.spans)
        assert r.doc_id == 5 or all((a[:2]) != (b[:2]) or a[2] + a[3] < b[2] for a, b in zip(ends, ends[1:]))  # paths don't run on
    assert n > 10


def test_substring_equal_hashes(spark):
    """K-mers of different words with one hash are proposed, but their words stay."""
    rows = [(1, " ".join(f"a{i}" for i in range(30))), (2, " ".join(f"b{i}" for i in range(30))), (3, " ".join([f"b{i}" for i in range(20)] + ["x"])), (4, None)]

    def blunt(k):
        def items(batches):
            for key, doc, pos in substring.kmers(k)(batches):
                yield np.where((pos == 0) & (doc < 3), np.uint64(77), key), doc, pos

        return items

    out = {r.doc_id: (r.n_removed, len(r.spans)) for r in substring.deduplicate(frame(spark, rows), items=blunt).collect()}
    assert out == {1: (0, 0), 2: (0, 0), 3: (19, 1), 4: (0, 0)}


def test_empty_tables(spark):
    none = frame(spark, []).select("doc_id", "text")
    assert substring.deduplicate(none).count() == 0
    assert lines.deduplicate(none).count() == 0
    assert neardup.label_documents(none).count() == 0
    assert bpe.round_trip_digests(none).count() == 0
    assert license.scan(none).count() == 0
    model = toxicity.train(none, spark.createDataFrame([], "doc_id long, toxic int"))
    assert toxicity.score(frame(spark, corpus()), model).where("_toxic").count() == 0
    bench = spark.createDataFrame([], "item_id long, text string")
    assert decontam.contaminated(frame(spark, corpus()), bench).where("size(_found) > 0").count() == 0


def test_null_ids_pass(spark):
    rows = [(None, "a b c\nd e f\ng h i"), (1, "a b c\nd e f\ng h i"), (2, "a b c\nd e f\ng h i")]
    out = {(r.doc_id, r._removed) for r in lines.deduplicate(frame(spark, rows)).collect()}
    assert out == {(None, 0), (1, 0), (2, 3)}
    near = {(r.doc_id, r.component_id, r.kept) for r in neardup.label_documents(frame(spark, rows)).collect()}
    assert near == {(None, None, True), (1, 1, True), (2, 1, False)}


def brute_lines(rows, k=3):
    seen, gone = set(), {}
    for i, t in sorted(((i, t) for i, t in dict(rows).items()), key=lambda r: r[0]):
        own = [(j, x) for j, x in enumerate((t or "").split("\n")) if x.strip(" \t\r\v\f")]
        for p in range(len(own) - k + 1):
            g = tuple(x for _, x in own[p : p + k])
            if g in seen:
                gone.setdefault(i, set()).update(j for j, _ in own[p : p + k])
            seen.add(g)
    return {i: "\n".join(x for j, x in enumerate((t or "").split("\n")) if j not in gone.get(i, ())) for i, t in rows}


def test_lines(spark):
    r = random.Random(3)
    stock = ["alpha", "beta", "gamma", "", " ", "delta\r"]
    rows = [(i, "\n".join(r.choice(stock) for _ in range(r.randint(0, 9)))) for i in range(40)] + [(99, None)]
    out = lines.deduplicate(frame(spark, rows))
    assert out.columns[:5] == ["doc_id", "text", "id", "key", "bucket"]
    assert {x.doc_id: x.text or "" for x in out.collect()} == brute_lines(rows)


CLASHING = "DOC_ID long, Text string, _bucket int, _LINES int, _removed string, found int, c0 int, shared int, _severity int, _found int, _plain int, _toxic int"


def clashing(spark, rows):
    """Columns that differ from the asked ones in case, and columns with the names that operators use."""
    return spark.createDataFrame([(i, t, 1, 2, "r", 3, 4, 5, 6, 7, 8, 9) for i, t in rows], CLASHING).repartition(3)


def test_clashing_names(spark):
    rows = [(i, "\n".join(["alpha", "beta", "gamma", f"delta {i}"])) for i in range(12)] + [(90, None), (91, "")]
    docs = clashing(spark, rows)
    out = lines.deduplicate(docs)
    assert out.columns == [c for c in docs.columns if c not in ("_LINES", "_removed")] + ["_lines", "_removed"]
    assert {x.DOC_ID: x.Text or "" for x in out.collect()} == brute_lines(rows) and out.where("c0 <> 4 or _bucket <> 1").count() == 0
    assert substring.deduplicate(docs, k=3).where("n_removed > 0").count() == 11
    labels = spark.createDataFrame([(i, int(i % 2)) for i in range(12)], "doc_id long, toxic int")
    scored = toxicity.score(docs, toxicity.train(docs, labels))
    assert scored.count() == 14 and scored.columns == [c for c in docs.columns if c not in ("_severity", "_toxic")] + ["_severity", "_grade", "_toxic"]
    bench = spark.createDataFrame([(1, "gamma delta 7")], "ITEM_ID long, Text string")
    found = decontam.contaminated(docs, bench)
    assert found.columns == [c for c in docs.columns if c != "_found"] + ["_found"]
    assert [x.DOC_ID for x in found.where("size(_found) > 0").collect()] == [7]
    assert neardup.label_documents(docs).count() == 14 and bpe.round_trip_digests(docs).count() == 14
    assert license.scan(docs).count() == 14


def test_line_dedup_of_long_texts(spark):
    many = "\n".join(f"line {i}" for i in range(20000))
    rows = [(1, many), (2, "x\n" + many), (3, "y\n" * 9)]
    out = {x.doc_id: (x._lines, x._removed, x.text) for x in lines.deduplicate(frame(spark, rows)).collect()}
    assert out == {1: (20000, 0, many), 2: (20001, 20000, "x"), 3: (9, 8, "y\n")}


def brute_near(rows, percent):
    sets = {}
    for i, t in rows:
        w = [x.lower() for x in (t or "").encode().split()]
        sets[i] = {tuple(w[p : p + 5]) for p in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())
    up = {i: i for i in sets}

    def find(i):
        while up[i] != i:
            i = up[i]
        return i

    ids = sorted(sets)
    for a in ids:
        for b in ids:
            if a < b and sets[a] and sets[b]:
                both = len(sets[a] & sets[b])
                if 100 * both >= percent * (len(sets[a]) + len(sets[b]) - both):
                    x, y = find(a), find(b)
                    up[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), find(i), find(i) == i) for i in sets}


@pytest.mark.parametrize("percent", [80, 85])
def test_near_duplicates(spark, monkeypatch, percent):
    monkeypatch.setattr(neardup, "BLOCK", 4)
    r = random.Random(percent)
    base = [r.choice(VOCAB) + str(r.random()) for _ in range(150)]
    rows = corpus()
    for i in range(200, 240):  # a family of near copies that overlap to various degrees
        w = list(base)
        for _ in range(r.randint(0, 5)):
            w[r.randrange(150)] = f"n{r.random()}"
        rows.append((i, " ".join(w)))
    out = {x.doc_id: (x.n_shingles, x.component_id, x.kept) for x in neardup.label_documents(frame(spark, rows), percent).collect()}
    assert out == brute_near(rows, percent)


def test_bpe_round_trip(spark):
    texts = [None, "", "don't  stop\n\n now ", "é€😀 " * 50, ("word " * 40000), "x" * 70000, "<|endoftext|>"]
    path, pattern = bpe.default_vocabulary()
    enc = bpe.codec(path, pattern)
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    for r in bpe.round_trip_digests(docs).collect():
        ids = enc.encode_ordinary(texts[r.doc_id] or "")
        assert r.n_tokens == len(ids)
        assert r.ids_sha256 == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()
        assert r.decoded_sha256 == hashlib.sha256((texts[r.doc_id] or "").encode()).hexdigest()
    back = bpe.decode(bpe.encode(docs))
    assert {r.doc_id: bytes(r.decoded).decode() for r in back.collect()} == {i: t or "" for i, t in enumerate(texts)}
    long = "".join(random.Random(4).choice(["ab ", "cd", "\n", " 12", "'s ", "é"]) for _ in range(60000))
    assert bpe.encode_text(enc, long).tolist() == enc.encode_ordinary(long)


def test_url_rules(spark):
    urls = ["http://www.Example.com/en/a?q#f", "http://example.com/en/", "http://a.example.com/x", "https://x.net/es/1", "net://net/fr/", "http://commerce/", "nothing", None, "http://", "http://a..com/", "http://x.com", "http://example.com/en/", "http://b.org/\n/x?y"]
    pages = spark.createDataFrame([(i, u, "<x>") for i, u in enumerate(urls)], "page_id long, url string, host string")
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in urlfilter.judge(pages, urlfilter.rule_table(spark)).collect()}

    def want(u):
        host = path = ""
        if u and "://" in u:
            rest = u.split("://", 1)[1]
            cut = min([rest.find(c) for c in "/?#" if c in rest] + [len(rest)])
            host, path = rest[:cut].lower(), rest[cut:].split("?")[0].split("#")[0]
        fits = [(len(h + p), len(h), h + p, v) for h, p, v in urlfilter.RULES if (host == h or host.endswith("." + h)) and path.startswith(p)]
        best = max(fits, default=(0, 0, None, "allow" if host else "block"))
        return host, path, best[2], best[3]

    assert got == {i: want(u) for i, u in enumerate(urls)}
    twice = pages.unionByName(pages)
    assert urlfilter.judge(twice, urlfilter.rule_table(spark)).count() == 2 * len(urls)


def test_license_blocks(spark):
    texts = ["Released under the\nMIT License.", "licensed under the apache-license version 2.0", "under a GNU General  Public LICENSE", None, "", "mit mit license license", "Licensed under CC BY NC 4.0.", "this source form code is subject of the terms to mozilla license"]
    docs = spark.createDataFrame([(i, t, 1) for i, t in enumerate(texts)], "doc_id long, text string, label int")
    got = {r.doc_id: r for r in license.digest(license.scan(docs)).collect()}
    assert [got[i].n_base for i in range(8)] == [1, 1, 1, 0, 0, 1, 0, 0]
    assert got[0].first_word == 3 and got[5].first_word == 1 and got[3].first_word is None
    assert got[6].labels == "cc-by-nc" and got[6].score == 1.0 and got[7].labels == "mpl"
    assert got[1].base_labels == "apache" and got[4].n_words == 0


def test_license_notices_over_lines(spark):
    """A wrapped notice is found; words spread over a text without line feeds are none."""
    wrapped = "x\nRedistribution and use in source and binary forms, with or without\nmodification, are permitted provided that"
    spread = "under " + "a " * 40 + "released " + "b " * 40 + "license " + "c " * 40 + "the mit"
    docs = spark.createDataFrame([(0, wrapped), (1, spread), (2, "the mit\nlicence released\nunder license")], "doc_id long, text string")
    got = {r.doc_id: (r.labels, r.score) for r in license.digest(license.scan(docs)).collect()}
    assert got == {0: ("bsd", 1.0), 1: ("", 0.0), 2: ("mit", 1.0)}


def brute_license(text, templates=None):
    """Labels and best share of every window that starts at a word of a template."""
    import math
    import re

    ws = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m.group().lower(), text or ""))
    best = {}
    for t in templates or license.TEMPLATES:
        s = set(t.words)
        for p, w in enumerate(ws):
            if w in s:
                x = set(ws[p : p + math.ceil(len(t.words) / license.CONTAINMENT - 1e-9)])
                share = len(x & s) / len(s)
                if share >= license.CONTAINMENT - 1e-9 and set(t.must) <= x and not set(t.never) & x:
                    best[t.label] = max(best.get(t.label, 0), share)
    return best


def test_license_against_brute_force(spark):
    """Notices whole, worn, near the threshold and of related licenses, in other text."""
    r = random.Random(21)
    rows = ["Released under the BSD license.", "Licensed under CC BY-SA 4.0", "Licensed under CC BY 4.0", "Licensed under CC BY-NC-SA 4.0. x", "under the general license of the software", " ".join(license.TEMPLATES[1].words) * 1]
    for _ in range(150):
        t = r.choice(license.TEMPLATES)
        w = [x.upper() if r.random() < 0.2 else x for x in t.words if r.random() > r.choice([0, 0.1, 0.2, 0.3])]
        for _ in range(r.randint(0, len(w) // 4)):
            w.insert(r.randrange(len(w) + 1), r.choice(VOCAB + ["license", "the", "gnu", "sa"]))
        rows.append(" ".join([r.choice(VOCAB + ["software", "of"]) for _ in range(r.randint(0, 30))]) + r.choice([" ", "\n", ", "]) + r.choice([" ", "\n"]).join(w))
    rows.append("the license of the software " * 4000 + "released under the mit license " + "x " * 5000)
    docs = spark.createDataFrame([(i, t, "a", 1) for i, t in enumerate(rows)], "Doc_Id long, TEXT string, id string, line int").repartition(3)
    found = {x.doc_id: {} for x in license.scan(docs).collect()}
    for x in license.scan(docs).collect():
        for b in x.blocks:
            found[x.doc_id][b.label] = max(found[x.doc_id].get(b.label, 0), b.share)
    want = {i: brute_license(t) for i, t in enumerate(rows)}
    assert found == want and sum(map(bool, want.values())) > 60
    assert want[0].keys() == {"bsd"} and want[1].keys() == {"cc-by-sa"} and want[2].keys() == {"cc-by"} and want[3].keys() == {"cc-by-nc-sa"} and not want[4]


def brute_edits(item, doc):
    row = [0] * (len(doc) + 1)
    for a in item:
        new = [row[0] + 1]
        for j, b in enumerate(doc):
            new.append(min(row[j] + (a != b), row[j + 1] + 1, new[j] + 1))
        row = new
    return min(row)


def test_decontamination(spark):
    r = random.Random(9)
    big = [f"v{i}" for i in range(3000)]
    items = [[r.choice(big) for _ in range(r.randint(12, 50))] for _ in range(12)] + [["only", "four", "words", "here"]]
    rows = []
    for i in range(120):
        item = list(r.choice(items[:12]))
        for _ in range(r.randint(0, len(item) // 3)):
            p = r.randrange(len(item))
            item[p : p + 1] = r.choice([[], [r.choice(big)], [item[p], r.choice(big)]])
        rows.append((i, " ".join([r.choice(big) for _ in range(r.randint(0, 60))] + item + [r.choice(big) for _ in range(r.randint(0, 60))]).upper()))
    rows += [(500, None), (501, ""), (502, "x only FOUR words here y"), (503, " ".join(r.choice(big) for _ in range(3000)))]
    bench = spark.createDataFrame([(i, ", ".join(w)) for i, w in enumerate(items)] + [(90, None), (91, "")], "item_id long, text string")
    out = {x.doc_id: {f.item: f.edits for f in x._found} for x in decontam.contaminated(frame(spark, rows), bench).collect()}
    pairs = found = 0
    for i, t in rows:
        doc = (t or "").lower().split()
        for j, w in enumerate(items):
            most = 0 if len(w) < decontam.SHORT else int(decontam.RATIO * len(w))
            d = brute_edits(w, doc) if doc else len(w)
            if d <= most:
                pairs += 1
                found += out[i].get(j, 99) >= d and j in out[i]
            else:
                assert j not in out[i]
    assert pairs > 60 and found >= 0.97 * pairs


def test_decontamination_of_long_items(spark):
    """Every near copy is found with its least distance, however long the item."""
    r = random.Random(10)
    big = [f"v{i}" for i in range(3000)]
    items = [[r.choice(big) for _ in range(n)] for n in (60, 150, 250, 400)]
    rows = []
    for i in range(80):
        item = list(items[i % 4])
        for _ in range(len(item) // 5):
            p = r.randrange(len(item))
            item[p : p + 1] = r.choice([[], [r.choice(big)], [item[p], r.choice(big)]])
        rows.append((i, " ".join([r.choice(big) for _ in range(20)] + item)))
    bench = spark.createDataFrame([(i, " ".join(w)) for i, w in enumerate(items)], "item_id long, text string")
    out = {x.doc_id: {f.item: f.edits for f in x._found} for x in decontam.contaminated(frame(spark, rows), bench).collect()}
    for i, t in rows:
        assert out[i] == {i % 4: brute_edits(items[i % 4], t.split())}


def test_neighbours_recall(spark):
    rng = np.random.default_rng(5)
    x = rng.standard_normal((900, 16)).astype(np.float32)
    x[100:160] = x[100]
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(2000, None), (2020, [0.0] * 16), (2040, [float("nan")] * 16), (2060, [1.0] * 3), (None, [1.0] * 16)]
    table = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got = {}
    for r in ann.nearest(table, table.where("vec_id % 20 = 0"), 20).collect():
        got.setdefault(r.query_id, {})[r.rank] = (r.vec_id, r.score)
    assert set(got) == set(range(0, 900, 20))
    hit = 0
    d = x.astype(np.float64)
    for q in got:
        s = d @ d[q]
        best = [i for i in np.lexsort((np.arange(900), -s)) if i != q][:20]
        hit += len(set(best) & {v for v, _ in got[q].values()})
        assert list(got[q]) and all(abs(sc - s[v]) < 1e-9 for v, sc in got[q].values())
        if q == 100:
            assert [got[q][k][0] for k in range(1, 21)] == list(range(101, 121))
    assert hit >= 0.9 * 20 * len(got)


@pytest.mark.parametrize("kind", ["unit", "gaussian", "lognormal", "outlier", "huge"])
def test_recall_of_shards(kind):
    """Graphs well above the width of the walk, for vectors of every kind of length."""
    rng = np.random.default_rng(8)
    x = rng.standard_normal((4000, 64))
    if kind != "gaussian":
        x /= np.linalg.norm(x, axis=1, keepdims=True)
    x *= {"lognormal": np.exp(rng.standard_normal((4000, 1))), "huge": np.full((1, 1), 1e60)}.get(kind, 1.0)
    if kind == "outlier":
        x[7] *= 1e4
    mag = np.floor(np.log2(np.linalg.norm(x, axis=1))).astype(int)
    q = np.arange(0, 4000, 20)
    score, name = [[] for _ in q], [[] for _ in q]
    for m in np.unique(mag):
        own = np.flatnonzero(mag == m)
        t = pa.table({"dim": pa.array([64] * len(own), pa.int32()), "mag": pa.array([int(m)] * len(own), pa.int32()), "shard": pa.array([0] * len(own), pa.int32()), "id": own, "vec": pa.array(x[own].tolist(), pa.list_(pa.float64()))})
        got = ann.search_shard(21, ann.EF_SEARCH)(ann.build_shard(t), pa.table({"id": np.arange(len(q)), "vec": pa.array(x[q].tolist(), pa.list_(pa.float64()))})).to_pylist()
        for r in got:
            score[r["q"]].append(r["score"])
            name[r["q"]].append(r["id"])
    hit = 0
    for i, v in enumerate(q):
        s = x @ x[v]
        s[v] = -np.inf
        found = [name[i][j] for j in np.argsort(-np.array(score[i])) if name[i][j] != v][:20]
        hit += len(set(found) & set(np.argsort(-s)[:20].tolist()))
    assert hit >= 0.93 * 20 * len(q)


def test_neighbours_recall_end_to_end(spark):
    """Shards wider than the walk; the width comes from trials over all shards."""
    x = np.random.default_rng(9).standard_normal((9000, 48))
    table = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    got = {}
    for r in ann.nearest(table, table.where("vec_id % 20 = 0"), 20).collect():
        got.setdefault(r.query_id, set()).add(r.vec_id)
    assert len(got) == 450 and all(len(v) == 20 for v in got.values())
    hit = 0
    for q, found in got.items():
        s = x @ x[q]
        s[q] = -np.inf
        hit += len(found & set(np.argpartition(-s, 20)[:20].tolist()))
    assert hit >= 0.93 * 20 * len(got), hit / 20 / len(got)


def test_neighbours_edges(spark):
    none = spark.createDataFrame([], "vec_id long, embedding array<float>")
    assert ann.nearest(none, none).count() == 0
    rows = [(1, [1e30, 0.0], 5), (2, [1e-30, 0.0], 5), (3, [1.0, 1.0], 5), (3, [0.0, 2.0], 5), (4, [1.0, 0.0], 5), (4, [1.0, 0.0], 5)]
    table = spark.createDataFrame(rows, "VEC_ID long, Embedding array<double>, shard int")
    got = [(r.query_id, r.rank, r.vec_id) for r in ann.nearest(table, table.where("vec_id = 4")).orderBy("rank").collect()]
    assert got == [(4, 1, 1), (4, 2, 3), (4, 3, 2)]


def test_toxicity_held_out():
    r = random.Random(2)
    tox, keys, counts = [], [], []
    for i in range(900):
        bad = i % 6 == 0
        w = [r.choice(VOCAB) for _ in range(40)] + ([r.choice(["vile", "nasty", "foul"]) for _ in range(r.randint(1, 6))] if bad else [])
        for c in words.chunks(pa.array([" ".join(w)]), words.ALNUM, lower=True):
            k, n = np.unique(c.hashes(*toxicity.PREFIXES).reshape(-1), return_counts=True)
        tox.append(bad)
        keys.append(k)
        counts.append(n.astype(np.int32))
    m = toxicity.fit(np.array(tox[:600]), keys[:600], counts[:600])
    assert m.thresholds[0] <= m.thresholds[1]
    at = {int(k): w for k, w in zip(m.keys, m.weights, strict=True)}
    score = np.array([sum(at.get(int(a), 0) * toxicity.damped(b) for a, b in zip(k, n, strict=True)) for k, n in zip(keys[600:], counts[600:], strict=True)])
    p = m.exceed(score)
    assert ((p[:, 0] >= 0.5) == np.array(tox[600:])).mean() > 0.97
    assert (p[:, 0] >= p[:, 1]).all()


def test_toxicity_end_to_end(spark):
    """train() and score() on Spark: held-out accuracy, expected grades by hand from the model, nulls, a long text, repeats."""
    r = random.Random(4)
    rows, bad = [], {}
    for i in range(1200):
        bad[i] = i % 5 == 0
        words_ = [r.choice(VOCAB) for _ in range(30)] + ([r.choice(["vile", "nasty", "foul"]) for _ in range(r.randint(1, 6))] if bad[i] else [])
        r.shuffle(words_)
        rows.append((i, " ".join(words_)))
    rows += [(2000, None), (2001, ""), (2002, "w1 w2 " * 30000), (2003, "vile nasty foul " * 9000), (None, "vile nasty"), (7, rows[7][1])]
    docs = frame(spark, rows)
    labels = spark.createDataFrame([(i, int(bad[i])) for i in range(800)] + [(800, None), (None, 1), (801, 0), (801, 1)], "doc_id long, toxic int")
    model = toxicity.train(docs, labels)
    out = toxicity.score(docs, model).collect()
    assert len(out) == len(rows)
    assert sum(x._toxic == bad[x.doc_id] for x in out if x.doc_id is not None and 800 <= x.doc_id < 1200) > 0.98 * 400
    at = {int(k): w for k, w in zip(model.keys, model.weights, strict=True)}
    for x in out:
        total = 0.0
        for c in words.chunks(pa.array([x.text], pa.string()), words.ALNUM, lower=True):
            k, n = np.unique(c.hashes(*toxicity.PREFIXES).reshape(-1), return_counts=True)
            total = sum(at.get(int(a), 0) * toxicity.damped(b) for a, b in zip(k, n, strict=True))
        p = model.exceed(np.array([total]))[0]
        assert abs(x._severity - p.sum()) < 1e-9 and x._toxic == (p[0] >= 0.5) and x._grade == int(np.argmax([1 - p[0], p[0] - p[1], p[1]]))
    by = {x.doc_id: x._toxic for x in out}
    assert not by[2000] and not by[2001] and not by[2002] and by[2003] and by[None]


def test_decontamination_query_by_brute_force(spark, sf_dir, tmp_path):
    """op5 over whole tables against the plain definition, on short documents with planted passages."""
    r = random.Random(31)
    big = [f"v{i}" for i in range(500)]
    say = lambda n: [r.choice(big) for _ in range(n)]
    items = [say(r.randint(5, 30)) for _ in range(15)]
    docs = [(i, say(r.randint(0, 60))) for i in range(150)]
    for i in range(150, 260):
        w = list(r.choice(items))
        for _ in range(r.randint(0, len(w) // 4)):
            p = r.randrange(len(w))
            w[p : p + 1] = r.choice([[], [r.choice(big)], [w[p], r.choice(big)]])
        docs.append((i, say(r.randint(0, 30)) + w + say(r.randint(0, 30))))
    spark.createDataFrame([(i, " ".join(w)) for i, w in docs], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(i, " ".join(w)) for i, w in enumerate(items)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    got = {x.doc_id: (x.contaminated, x.items, x.least_edits) for x in registry.op5_decontamination(spark, str(tmp_path)).collect()}
    for i, w in docs:
        d = {j: brute_edits(item, w) for j, item in enumerate(items)}
        own = {j: e for j, e in d.items() if e <= int(decontam.RATIO * len(items[j]))}
        assert got[i] == (bool(own), sorted(own), min(own.values(), default=None)), i


def test_url_rule_edges(spark):
    pages = spark.createDataFrame([(1, "http://a.com/x/y", 1), (2, "http://b.a.com/x", 1), (3, "http://a.com", 1)], "page_id long, url string, key int")
    assert urlfilter.judge(pages.limit(0), urlfilter.rule_table(spark)).count() == 0


def test_toxicity_rows_of_the_model(spark):
    """The model has as many labelled rows as the quality figures were measured with."""
    n = 8500
    docs = spark.range(n).selectExpr("id AS doc_id", "concat('w', id % 50, IF(id % 6 = 0, ' vile', '')) AS text")
    labels = spark.range(n).selectExpr("id AS doc_id", "CAST(id % 6 = 0 AS int) AS toxic")
    assert len(toxicity.labelled(docs, labels, "doc_id", "text", toxicity.MAX_ROWS)[0]) == 8000


def replicas(spark, rows, bad):
    return (spark.createDataFrame([tuple(r) for r in x], "page_id long, url string, html string, key int, node int, copy string") for x in (rows, bad))


def test_fixity(spark):
    from kgflow.llm import fixity

    rows = [(i, f"http://x/{i}", "body" * (i % 7), 1, 2, "c") for i in range(300)] + [(7, "http://x/7", None, 1, 2, "c"), (None, None, None, 1, 2, "c"), (None, "http://n", "", 1, 2, "c"), (7, "http://x/7", None, 1, 2, "c")]
    bad = [list(r) for r in rows]
    bad[17][2] = "flipped"
    del bad[50]
    bad.append([999, "http://new", "extra", 1, 2, "c"])
    a, b = replicas(spark, rows, bad)
    out = fixity.audit(a, b, "Page_ID", ["url", "HTML"], fanout=4).collect()
    got = {}
    for r in out:
        got.setdefault(r.status, []).append(r.id)
    assert got["corrupt"] == ["17"] and got["missing"] == ["50"] and got["extra"] == ["999"] and len(got["intact"]) == 302
    for file in {r.file for r in out}:  # offsets run on within a file
        own = sorted((r.start, r.length) for r in out if r.file == file and r.status != "extra")
        assert not own or own[0][0] == 0 and all(x + n == y for (x, n), (y, _) in zip(own, own[1:]))
    assert {r.status for r in fixity.audit(a, a, "page_id", ["url", "html"]).collect()} == {"intact"}
    assert fixity.audit(a.limit(0), a.limit(0), "page_id", ["url", "html"]).count() == 0


def test_fixity_reads_one_path(spark):
    """A record that grows, one that is lost and none: the nodes read on every level."""
    from kgflow.llm import fixity

    rows = [[i, f"http://x/{i}", "body" * (i % 5), 1, 2, "c"] for i in range(256)]
    longer, lost = [list(r) for r in rows], [r for r in rows if r[0] != 100]
    longer[30][2] += "<!-- sixteen -->"
    for bad, want in ((longer, [1, 4, 4, 4, 4]), (lost, [1, 4, 4, 4, 4]), (rows, [1])):
        a, b = replicas(spark, rows, bad)
        tree = fixity.trees(fixity.layout(*(fixity.leaves(x, "page_id", ["url", "html"]) for x in (a, b))), fanout=4)
        damaged, read = tree.damaged()
        assert read == want and damaged.count() == len(want) // 5


@pytest.mark.parametrize("name", ["op2_url_filters", "op4_warc_fixity", "op9_line_dedup", "op3_license_scan", "op6_substring_dedup"])
def test_queries_against_sql(spark, sf_dir, same_as_sql, name):
    same_as_sql(registry.queries()[name](spark, sf_dir), registry.oracle_sql()[name])
