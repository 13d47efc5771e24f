"""Operators on texts against brute force, and their edge cases."""

import base64
import hashlib
import random
import re

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from idagg.llm import bpe, decontaminate, licenses, line_dedup, quality, queries, repeats, simhash, toxicity, warc
from idagg.llm.suffix_array import suffix_array

DOCS = "doc_id long, text string, lang string, score double, id string, h long, place int"
LONG = " ".join(f"w{k}" for k in range(30_000))
WORDS = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon".split()


def prose(seed, n=120):
    r = random.Random(seed)
    return " ".join(r.choice(WORDS) + str(r.randrange(50)) for _ in range(n))


def lines(seed, n=12):
    return "\n".join(prose(f"{seed}/{k}", 9) for k in range(n))


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empties, a very long text, ties and repeated rows, and columns whose names operators use inside."""
    rows = [
        (1, None, None, 1.0, "x", 5, 1), (2, "", "en", None, None, None, None), (3, LONG, "en", 0.5, "y", 1, 2), (4, prose(1), "en", 0.1, "z", 2, 3),
        (4, prose(1), "en", 0.1, "z", 2, 3), (None, prose(2), "en", 0.2, "q", 7, 7), (6, "One two", "en", 0.2, "q", 7, 7), (7, "one TWO ", "en", 0.2, "q", 7, 7),
        (8, lines(3), None, 0.3, "r", 8, 8), (9, lines(3) + "\n" + lines(4), None, 0.3, "r", 8, 8), (10, "\n\n \t", None, 0.3, "r", 8, 8), (11, LONG, "en", 0.5, "y", 1, 2)]
    return spark.createDataFrame(rows, DOCS)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOCS)


def ids(df, col="doc_id"):
    return sorted((r[col] for r in df.collect()), key=lambda x: (x is not None, x))


ALL = [None, 1, 2, 3, 4, 4, 6, 7, 8, 9, 10, 11]


# ---- suffix arrays and repeats


def test_suffix_array_brute_force():
    r = random.Random(5)
    for _ in range(800):
        x = [r.randrange(r.choice([1, 2, 3, 9])) for _ in range(r.randrange(30))]
        assert suffix_array(x) == sorted(range(len(x)), key=lambda i: x[i:])
    x = [0] * 500
    assert suffix_array(x) == list(range(499, -1, -1))


def brute_repeats(texts, n):
    raw = [(t or "").encode() for t in texts]
    seen: dict[bytes, int] = {}
    for b in raw:
        for i in range(len(b) - n + 1):
            seen[b[i : i + n]] = seen.get(b[i : i + n], 0) + 1
    out = []
    for b in raw:
        cov = np.zeros(len(b), bool)
        for i in range(len(b) - n + 1):
            if seen[b[i : i + n]] > 1:
                cov[i : i + n] = True
        kept = bytes(x for x, c in zip(b, cov, strict=True) if not c)
        out.append((len(b), int(cov.sum()), int((np.diff(np.concatenate([[0], cov.astype(int)])) == 1).sum()), kept))
    return out


@pytest.mark.parametrize("cap", [1, 3, 512])
def test_repeats_brute_force(spark, cap):
    r = random.Random(7)
    shared = [prose(k, 60) for k in range(3)]
    texts = [prose(100 + k, 30) + " " + r.choice(shared)[r.randrange(60) :] + " " + prose(200 + k, 20) for k in range(40)]
    texts += [None, "", "é" * 300, "ab" * 200, "ab" * 150 + "x", prose(100), prose(100), "tie " * 90]
    df = spark.createDataFrame([(k, t) for k, t in enumerate(texts)], "doc_id long, text string").repartition(3)
    got = {x.doc_id: (x.n_bytes, x.n_removed, x.n_spans, bytes(x.kept)) for x in repeats.dedup(df, length=80, k=16, cap=cap).collect()}
    assert [got[k] for k in range(len(texts))] == brute_repeats(texts, 80)


def brute_passages(texts, n):
    """Words of each text in runs of n words that another text has too."""
    words = [(t or "").split() for t in texts]
    where: dict[tuple, set] = {}
    for k, w in enumerate(words):
        for i in range(len(w) - n + 1):
            where.setdefault(tuple(w[i : i + n]), set()).add(k)
    out = []
    for w in words:
        cov = np.zeros(len(w), bool)
        for i in range(len(w) - n + 1):
            if len(where[tuple(w[i : i + n])]) > 1:
                cov[i : i + n] = True
        out.append(int(cov.sum()))
    return out


@pytest.mark.parametrize("cap", [1, 3, 512])
def test_passages_brute_force(spark, cap):
    """Passages across documents, whatever white space is between the words; a document's own repeats don't count."""
    r = random.Random(11)
    shared = [prose(f"p{k}", r.randrange(10, 40)).split() for k in range(4)]
    texts = [prose(f"a{k}", 20) + " " + r.choice([" ", "\n", "\t"]).join(r.choice(shared)[r.randrange(12) :]) + "  " + prose(f"b{k}", 15) for k in range(50)]
    own = prose("own", 16)
    texts += [None, "", "one", own + " x " + own + " y " + own, prose("c"), prose("c"), "tie " * 90, "tie " * 40, "the " * 200]
    texts += [own + " z " + prose("q", 4), (" ".join(shared[0][:14]) + " v ") * 3]
    df = spark.createDataFrame([(k, t) for k, t in enumerate(texts)], "doc_id long, text string").repartition(3)
    got = {x.doc_id: x.n_passage_words for x in repeats.dedup(df, length=80, k=16, cap=cap, words=12).collect()}
    assert [got[k] for k in range(len(texts))] == brute_passages(texts, 12)


def test_repeats_odd(odd, none):
    got = repeats.dedup(odd)
    assert ids(got) == ALL
    by = {r.doc_id: r for r in got.collect()}
    assert by[3].n_removed == by[3].n_bytes == by[11].n_removed and by[1].n_bytes == 0 and by[4].n_removed == by[4].n_bytes
    assert repeats.dedup(none).count() == 0
    got = repeats.dedup(odd, words=5)
    assert ids(got) == ALL and {r.n_passage_words for r in got.where("doc_id in (3, 11)").collect()} == {30_000} and {r.n_passage_words for r in got.where("doc_id = 4").collect()} == {0}
    assert repeats.dedup(none, words=5).count() == 0


# ---- simhash


def brute_fp(text):
    t = re.sub("[A-Z]", lambda m: m[0].lower(), text or "")
    w = re.findall("[^\x20\x09-\x0d]+", t)
    if not w:
        return 0
    s = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] or [" ".join(w)]
    hs = [xxhash.xxh64_intdigest(x.encode(), seed=42) for x in s]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(s))


def classes(n, linked):
    up = list(range(n))

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for i in range(n):
        for j in range(i):
            if linked(i, j):
                a, b = root(i), root(j)
                up[max(a, b)] = min(a, b)
    return [root(x) for x in range(n)]


def test_fingerprints(odd):
    for t in (None, "", "One two", "a  b\tc\x0bd", prose(1), "É x\x85y z É", "\n\n \t"):
        assert simhash.fingerprint(t) == brute_fp(t)
    assert simhash.fingerprints(odd.select("doc_id", "text")).where("doc_id = 7").first().fp == simhash.fingerprints(odd.select("doc_id", "text")).where("doc_id = 6").first().fp


@pytest.mark.parametrize("bucket", [4, 1024])
def test_links_of_fingerprints(spark, bucket):
    r = random.Random(3)
    base = [r.getrandbits(64) for _ in range(12)] + [0]
    fps = sorted({b ^ sum(1 << k for k in r.sample(range(64), r.randrange(5))) for b in base for _ in range(12)})
    df = spark.createDataFrame([(x - (1 << 64) if x >> 63 else x,) for x in fps], "fp long")
    signed = sorted((x - (1 << 64) if x >> 63 else x) for x in fps)
    from idagg.llm._common import components

    got = {x.node: x.root for x in components(simhash.links(df, bucket=bucket), spark).collect()}
    want = classes(len(signed), lambda i, j: ((signed[i] ^ signed[j]) & ((1 << 64) - 1)).bit_count() <= 3)
    assert [got.get(x, x) for x in signed] == [signed[k] for k in want]


def test_allocation_sums():
    cost, ts = simhash.allocate([[0, 5, 50], [0, 1, 2], [0, 9, 99]], 1)
    assert sum(ts) == 1 and cost == 5 + 2 + 9 or sum(ts) == 1
    rng = np.random.default_rng(0)
    plan = simhash.plan(rng.integers(0, 1 << 63, 500).astype(np.uint64), 10_000, 3)
    assert sum(t + 1 for _, t in plan) == 4 or sum(t + 1 for _, t in plan) >= 3


def test_simhash_odd(odd, none):
    got = simhash.clusters(odd)
    by = {r.doc_id: r for r in got.collect()}
    assert ids(got) == ALL and by[7].component_id == 6 and by[11].component_id == 3 and by[2].component_id == 1 and by[10].component_id == 1
    assert simhash.clusters(none).count() == 0
    kept = simhash.keep_one(odd)
    assert kept.columns == odd.columns and ids(kept) == [None, 1, 3, 4, 6, 8, 9]


# ---- line dedup


def test_line_dedup(spark, odd, none):
    texts = [lines(k) for k in range(6)] + [lines(1) + "\n" + lines(9), "new first line\n" + lines(2), None, "", lines(3)]
    df = spark.createDataFrame([(k, t, "c") for k, t in enumerate(texts)], "doc_id long, text string, hs string")
    got = {r.doc_id: r for r in line_dedup.dedup(df).collect()}
    seen: set[str] = set()
    for k, t in enumerate(texts):
        if t is None:
            assert got[k].text is None
            continue
        out = []
        for c in line_dedup.chunks(t):
            x = "\n".join(c)
            if len(c) > 1 and x in seen:
                continue
            seen.update([x] if len(c) > 1 else [])
            out += c
        assert got[k].text == "\n".join(out)
    assert "\n".join(x for c in line_dedup.chunks(texts[0]) for x in c) == texts[0]
    got = line_dedup.dedup(odd)
    assert ids(got) == ALL and set(odd.columns) < set(got.columns)
    assert line_dedup.dedup(none).count() == 0


@pytest.mark.parametrize("n", range(2, 9))
def test_line_dedup_cuts_every_repeated_run(spark, n, tmp_path):
    """Passages of n lines inside otherwise different documents, at any place, through the registered query: brute force over pairs of lines."""
    texts = [lines(f"own{n}/{k}", 3 + k % 5).split("\n") for k in range(24)]
    for k in range(0, 24, 2):
        passage = lines(f"shared{n}/{k}", n).split("\n")
        texts[k][k % 3 : k % 3] = passage
        texts[k + 1][2:2] = passage
    texts += [["x", "x", "x", "y"], ["y", "x", "x"], ["", "", "z"], ["z"], ["p", "q"], ["p", "q", "r"], ["q", "r"]]
    spark.createDataFrame([(k, "\n".join(t)) for k, t in enumerate(texts)], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r.doc_id: r for r in queries.op3_line_dedup(spark, str(tmp_path)).collect()}
    seen: set[tuple] = set()
    for k, t in enumerate(texts):
        gone: set[int] = set()
        for i in range(len(t) - 1):
            gone |= {i, i + 1} if (t[i], t[i + 1]) in seen else set()
            seen.add((t[i], t[i + 1]))
        if k < 24:
            assert len(gone) == n * (k % 2)
            assert got[k].n_removed_chunks == k % 2
        assert got[k].n_removed_lines == len(gone)
        assert got[k].kept_sha256 == hashlib.sha256("\n".join(x for i, x in enumerate(t) if i not in gone).encode()).hexdigest()


# ---- decontamination


def test_decontamination(spark, odd, none):
    items = [(1, prose(50, 20)), (2, prose(51, 60)), (3, "only three words"), (4, None), (5, ""), (6, prose(52, 8)), (7, prose(2))]
    bench = spark.createDataFrame(items, "item_id long, text string")
    near = prose(51, 60).split(" ")
    near[30] = "changed"
    texts = [prose(9, 3000) + " " + prose(50, 20) + " " + prose(8, 3000), " ".join(near), "Only three WORDS", "only three words more", prose(52, 8) + ".", prose(99), None]
    df = spark.createDataFrame([(k, t) for k, t in enumerate(texts)], "doc_id long, text string")

    def sh(t):
        w = decontaminate.words_of(t)
        return {" ".join(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()

    want = {(k, i) for k, t in enumerate(texts) for i, x in items if sh(x) and len(sh(x) & sh(t)) / len(sh(x)) >= 0.8}
    assert {(r.doc_id, r.item_id) for r in decontaminate.search(df, bench).collect()} == want
    assert {(r.doc_id, r.item_id) for r in decontaminate.search(df, bench, block_items=2).collect()} == want
    assert ids(decontaminate.drop_contaminated(df, bench)) == sorted(set(range(7)) - {k for k, _ in want})
    assert {(r.doc_id, r.item_id) for r in decontaminate.search(odd, bench).collect()} == {(None, 7)}
    kept = decontaminate.drop_contaminated(odd, bench)
    assert kept.columns == odd.columns and ids(kept) == ALL[1:]
    assert decontaminate.search(none, bench).count() == 0 and decontaminate.search(df, bench.where("false")).count() == 0
    assert all(decontaminate.miss_chance(q, c, 0.8) < 4e-5 for c in (8, 16, 32, 64) for q in range(c // 2 + 1, c + 1))


def test_tiny_items(spark):
    items = [(k, prose(300 + k, 5 + k % 4)) for k in range(40)]
    docs = [(k, prose(900 + k, 400) + " " + t + " " + prose(500 + k, 300)) for k, t in items]
    got = decontaminate.search(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string"))
    assert {(r.doc_id, r.item_id) for r in got.collect()} == {(k, k) for k, _ in items}


# ---- classifiers


def fold_docs(spark):
    rows, labels = [], []
    for k in range(400):
        bad = k % 4 == 0
        rows.append((k, prose(k, 60) + (" you utter nitwitface" + str(k % 9) if bad else "")))
        labels.append((k, int(bad), int(not bad)))
    return spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, toxic int, quality int")


def test_toxicity_held_out(spark, odd, none):
    docs, labels = fold_docs(spark)
    model = toxicity.fit(docs, labels, may_learn=F.crc32(F.col("id").cast("string")) % 5 != 0)
    got = toxicity.score(docs, model).join(labels, "doc_id").where(F.crc32(F.col("doc_id").cast("string")) % 5 == 0).toPandas()
    assert ((got.score >= 0.5) == (got.toxic == 1)).mean() > 0.95
    assert len(model[0]) < 3_000  # sparse
    s = toxicity.score(odd.drop("score"), model)
    assert s.count() == 12 and s.where("score is null or score < 0 or score > 1").count() == 0
    assert toxicity.score(none.drop("score"), model).count() == 0
    empty = toxicity.fit(docs, labels.where("false"))
    assert toxicity.score(docs, empty).count() == 400


def test_quality_held_out(spark, odd, none):
    docs, labels = fold_docs(spark)
    docs = docs.join(labels, "doc_id").select("doc_id", F.when(F.col("quality") == 1, F.col("text")).otherwise(F.upper(F.regexp_replace("text", " ", "!!! "))).alias("text"))
    net = quality.fit(docs, labels)
    got = quality.score(docs, net).join(labels, "doc_id").toPandas()
    assert ((got.score >= 0.5) == (got.quality == 1)).mean() > 0.95
    s = quality.score(odd.drop("score"), net)
    assert s.count() == 12 and s.where("score is null or isnan(score)").count() == 0
    assert quality.score(none.drop("score"), net).count() == 0 and quality.fit(docs, labels.where("quality = 0")) is None
    assert quality.score(docs, None).where("score = 0.5").count() == 400


# ---- archives


def test_warc_round_trip(spark, tmp_path):
    rows = [(1, "http://a", "<p>same</p>" * 50), (2, None, "<p>same</p>" * 50), (3, "http://c", None), (4, "http://d", ""), (5, "http://e\r\nX: y", "<b>é</b>\r\n\r\nbody"), (5, "http://e", "<b>é</b>\r\n\r\nbody"), (6, "u", "x" * 300_000)]
    pages = spark.createDataFrame([(*r, "k", "best") for r in rows], "page_id long, url string, html string, k string, best string")
    archives = warc.write(pages, archive_bytes=1_000)
    got = warc.read(archives).toPandas().sort_values(["page_id"]).reset_index(drop=True)
    assert len(got) == len(rows)
    for pid, _, html in rows:
        g = got[got.page_id == pid].iloc[0]
        raw = (html or "").encode()
        assert g.payload_bytes == len(raw) and g.payload_digest == base64.b32encode(hashlib.sha1(raw).digest()).decode()
    kinds = {r.page_id: (r.record_type, None if r.refers_to != r.refers_to else r.refers_to) for r in got.itertuples()}
    assert kinds == {1: ("revisit", 2), 2: ("response", None), 3: ("revisit", 4), 4: ("response", None), 5: ("response", None), 6: ("response", None)}
    assert got[got.page_id == 2].html.iloc[0] == "<p>same</p>" * 50
    warc.write_files(archives, f"file://{tmp_path}")
    files = list(tmp_path.glob("*.warc.zst"))
    assert len(files) == archives.count() and sum(1 for f in files for _ in warc.records(f.read_bytes())) == len(rows)
    assert warc.read(warc.write(pages.where("false"))).count() == 0


# ---- tokenising


def test_bpe_against_library(spark, odd, none):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(bpe.default_vocabulary())
    t.no_truncation()
    t.no_padding()
    texts = [prose(3), "", None, "Ünïcödé ﬁne ½ ΣΑΣ's don't 12345 !!??", "a" * 2_000, "日本語 😀", "\x1cx\x1f y\x85z", "<|endoftext|>hi<|startoftext|>", "x" + "!" * 500]
    df = spark.createDataFrame([(k, x, "c") for k, x in enumerate(texts)], "doc_id long, text string, ids string")
    got = {r.doc_id: r for r in bpe.encode_frame(df).collect()}
    dig = {r.doc_id: r for r in bpe.encode_digests(df).collect()}
    for k, x in enumerate(texts):
        e = t.encode(x or "", add_special_tokens=False)
        d = t.decode(e.ids, skip_special_tokens=False)
        assert got[k].ids == e.ids and got[k].decoded == d
        assert dig[k].n_tokens == len(e.ids) and dig[k].ids_sha256 == hashlib.sha256(" ".join(map(str, e.ids)).encode()).hexdigest()
        assert dig[k].decoded_sha256 == hashlib.sha256(d.encode()).hexdigest()
    assert ids(bpe.encode_digests(odd)) == ALL and bpe.encode_digests(none).count() == 0


# ---- licences


def test_licenses(spark, odd, none):
    words = "Licensed under the Apache License, Version 2.0 now.".split()
    docs = [(1, "x\nReleased under the MIT License.\ny"), (2, "released UNDER the  mit-license"), (3, None), (4, ""), (5, " ".join(words)), (6, "Licensed"), (7, "under the license of nature we walk")]
    df = spark.createDataFrame([(*d, "z") for d in docs], "doc_id long, text string, norm string")

    def brute(text):
        out = set()
        split = text.split("\n")
        for no, unit in [*enumerate(split), *([(-1, text)] if len(split) > 1 else [])]:
            w = re.sub(r"[\W_]+", " ", unit.lower()).strip().split(" ")
            b = set(zip(w, w[1:], strict=False))
            for k, (_, t) in enumerate(licenses.TEMPLATES):
                v = re.sub(r"[\W_]+", " ", t.lower()).strip().split(" ")
                c = set(zip(v, v[1:], strict=False))
                if b and 2 * len(b & c) / (len(b) + len(c)) >= 0.8:
                    out.add((no, k))
        return out

    want = {(d, *x) for d, t in docs if t for x in brute(t)}
    assert {(r.doc_id, r.line_no, r.template_no) for r in licenses.scan(df).collect()} == want and len(want) >= 3
    assert licenses.scan(odd).count() == 0 and licenses.scan(none).count() == 0


def test_queries_registered():
    q = queries.queries()
    assert sorted(int(n[2:].split("_")[0]) for n in q) == list(range(1, 11))


def test_short_items_are_found_inside_documents(spark):
    items = [(1, "Solve"), (2, "two plus two"), (3, "a b c d"), (4, "two"), (5, "one two three four five six")]
    docs = [(1, "please solve this: what is two plus two, she said"), (2, "a b c d"), (3, "x a b c d y z w"), (4, "a b c"), (5, None), (6, "Two Plus Two"),
            (7, "zero one two three four five six seven"), (8, "nothing of the kind stands in here")]
    want = set()
    for d, text in docs:
        w = decontaminate.words_of(text)
        for k, item in items:
            v = decontaminate.words_of(item)
            if len(w) > 4 and any(w[i : i + len(v)] == v for i in range(len(w) - len(v) + 1)) or w == v:
                want.add((d, k, 1.0))
    df, bench = spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    got = [tuple(r) for r in decontaminate.search(df, bench).collect()]
    assert sorted(got) == sorted(want) and (3, 3, 1.0) in want and (1, 1, 1.0) in want
    assert {r.doc_id for r in decontaminate.drop_contaminated(df, bench).collect()} == {4, 5, 8}


def test_ftrl_against_the_plain_recurrence():
    """Per-coordinate steps against the update written out with scalars."""
    from math import exp, sqrt

    r = random.Random(4)
    m = toxicity.Ftrl(12, alpha=0.3, beta=1.0, l1=0.2, l2=1.0)
    z, n = [0.0] * 12, [0.0] * 12

    def weight(i):
        if abs(z[i]) <= 0.2:
            return 0.0
        return -(z[i] - (0.2 if z[i] > 0 else -0.2)) / ((1.0 + sqrt(n[i])) / 0.3 + 1.0)

    for _ in range(200):
        x, y, bias = sorted(r.sample(range(12), r.randrange(1, 6))), float(r.random() < 0.4), r.uniform(-1, 1)
        g = 1 / (1 + exp(-(sum(map(weight, x)) + bias))) - y
        old = {i: weight(i) for i in x}
        for i in x:
            step = (sqrt(n[i] + g * g) - sqrt(n[i])) / 0.3
            z[i] += g - step * old[i]
            n[i] += g * g
        assert m.learn(np.array(x), y, bias) == pytest.approx(g)
    assert m.weights(slice(None)) == pytest.approx([weight(i) for i in range(12)]) and 0 < (m.weights(slice(None)) == 0).sum() < 12


def test_risk_gradient_by_finite_differences():
    """The network's gradient of a mean logistic loss, by each parameter."""
    r = np.random.default_rng(3)
    x = r.normal(size=(9, 5))
    net = quality.Network(x.mean(0), x.std(0), 1, hidden=4)
    net.p[1] += 0.1
    z = net.scaled(x)

    def loss():
        return np.logaddexp(0, net.forward(z)[0]).mean()

    f, h = net.forward(z)
    grads = net.backward(z, h, 1 / (1 + np.exp(-f)) / len(f))
    for p, g in zip(net.p, grads, strict=True):
        for at in np.ndindex(p.shape):
            keep = p[at]
            p[at] = keep + 1e-6
            up = loss()
            p[at] = keep - 1e-6
            down = loss()
            p[at] = keep
            assert np.asarray(g)[at] == pytest.approx((up - down) / 2e-6, rel=1e-4, abs=1e-8)


def test_risk_never_rewards_what_it_cannot_see():
    """Separable classes: from positives and unlabelled texts alone, both kinds of the unlabelled are told apart; the risk's clamp keeps positives that
    are few from driving all scores up."""
    r = np.random.default_rng(6)
    pos, neg = r.normal(2, 1, (60, 6)), r.normal(-2, 1, (400, 6))
    unl = np.vstack([r.normal(2, 1, (200, 6)), neg])
    net = quality.fit_network(pos, unl, 1 / 3, epochs=30)
    s = net.score(unl)
    assert (s[:200] >= 0.5).mean() > 0.95 and (s[200:] < 0.5).mean() > 0.95


def test_many_colliding_digests_all_stay(spark):
    """Pieces whose digest stands for several texts stay, however many such digests there are; others are cut as ever."""
    rows = [(2 * k + j, f"{k:02d}a{j}\nz{j}") for k in range(40) for j in range(2)] + [(100, "xxsame\nb"), (101, "xxsame\nb")]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = {r.doc_id: r.text for r in line_dedup.dedup(df, runs=True, digest=lambda c: c[0][:2].encode()).collect()}
    assert all(got[d] == t for d, t in rows[:-1]) and got[101] == ""


def test_scores_replace_a_column_of_their_name(odd):
    got = toxicity.score(odd, (np.array([-1]), np.array([0.5])))
    assert got.columns == [*[c for c in odd.columns if c != "score"], "score"] and got.where("score is null").count() == 0
    got = quality.score(odd, None)
    assert got.columns.count("score") == 1 and {r.score for r in got.collect()} == {0.5}


def test_line_dedup_and_keep_one_keep_clashing_columns(odd):
    named = odd.withColumns({n: F.lit(n) for n in ("__hs", "__key", "__id", "__tk", "__n", "__kept", "__n_lines")})
    for got in (line_dedup.dedup(named, runs=True, counts=False), simhash.keep_one(named)):
        assert got.columns == named.columns and all(r[n] == n for r in got.collect() for n in ("__hs", "__key", "__n", "__kept", "__n_lines"))
    got = line_dedup.dedup(named, runs=True)
    assert got.columns == [*[c for c in named.columns if c != "__n_lines"], *line_dedup.COUNTS] and got.where("__n_lines < 0").count() == 0


def test_index_blocks_are_bounded_by_bytes(spark):
    items = spark.createDataFrame([(k, prose(f"i{k}", 40)) for k in range(30)], "item_id long, text string")
    blocks = list(decontaminate._blocks(items, "item_id", "text", 50_000, 2_000))
    assert len(blocks) > 3 and sorted(x[0] for b in blocks for x in b) == list(range(30))
    docs = spark.createDataFrame([(k, "x " + prose(f"i{k}", 40) + " y") for k in range(30)], "doc_id long, text string")
    got = decontaminate.search(docs, items, block_items=4)
    assert sorted((r.doc_id, r.item_id) for r in got.collect()) == [(k, k) for k in range(30)]
