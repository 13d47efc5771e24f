"""Vectors against brute force; the pipeline's stages on their own inputs."""

import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from idagg.llm import embeddings
from idagg.llm._common import components


def brute(vec, threshold=0.95):
    n = len(vec)
    ok = [v is not None and len(v) > 0 and all(x is not None and math.isfinite(x) for x in v) and any(v) for v in vec]
    links, up = [0] * n, list(range(n))

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for i in range(n):
        for j in range(i):
            if ok[i] and ok[j] and len(vec[i]) == len(vec[j]):
                a, b = np.array(vec[i], np.float32).astype(float), np.array(vec[j], np.float32).astype(float)
                if a @ b / math.sqrt((a @ a) * (b @ b)) >= threshold:
                    links[i] += 1
                    links[j] += 1
                    x, y = root(i), root(j)
                    up[max(x, y)] = min(x, y)
    return links, [root(x) for x in range(n)]


@pytest.mark.parametrize("bucket", [6, 1024])
def test_vectors(spark, bucket, monkeypatch):
    monkeypatch.setattr(embeddings, "BUCKET", bucket)
    r = np.random.default_rng(2)
    base = r.normal(size=(8, 16))
    vec = [(base[k % 8] + r.normal(scale=0.06, size=16)).tolist() for k in range(60)]
    vec += [vec[0], vec[0], [2 * x for x in vec[1]], None, [], [0.0] * 16, [float("nan")] + [1.0] * 15, [None] + [1.0] * 15, [float("inf")] * 16, [1.0, 0.0], [1.0, 0.01]]
    df = spark.createDataFrame([(k, v, "x") for k, v in enumerate(vec)], "vec_id long, embedding array<float>, node string").repartition(3)
    got = embeddings.clusters(df).toPandas().sort_values("vec_id")
    links, comp = brute(vec)
    assert got.n_links.tolist() == links and got.component_id.tolist() == comp and (got.kept == (got.vec_id == got.component_id)).all()


def test_vectors_of_any_size(spark):
    """Parallel vectors link however large or small their components are; opposite ones don't."""
    vec = [[1e200, 2e200], [2e200, 4e200], [1e-200, 2e-200], [1e-310, 2e-310], [1.7e308, -1.7e308], [-3.0, 3.0], [5e-324, -5e-324]]
    got = embeddings.clusters(spark.createDataFrame(list(enumerate(vec)), "vec_id long, embedding array<double>")).toPandas().sort_values("vec_id")
    assert got.component_id.tolist() == [0, 0, 0, 0, 4, 5, 4] and got.n_links.tolist() == [3, 3, 3, 3, 1, 0, 1]


def test_recall_near_the_threshold(spark):
    """Pairs whose cosine is just above 0.95, the hardest to meet: none is missed, and none below it is linked."""
    r = np.random.default_rng(8)
    a = r.normal(size=(700, 64))
    a /= np.linalg.norm(a, axis=1)[:, None]
    o = r.normal(size=a.shape)
    o -= (o * a).sum(1)[:, None] * a
    o /= np.linalg.norm(o, axis=1)[:, None]
    c = r.uniform(0.94, 0.96, len(a))
    vec = np.vstack([a, a * c[:, None] + o * np.sqrt(1 - c * c)[:, None]]).astype(np.float32)
    got = embeddings.clusters(spark.createDataFrame([(k, v.tolist()) for k, v in enumerate(vec)], "vec_id long, embedding array<float>")).toPandas().sort_values("vec_id")
    x = vec.astype(np.float64)
    x /= np.linalg.norm(x, axis=1)[:, None]
    near = x @ x.T >= 0.95
    np.fill_diagonal(near, False)
    assert near.sum() > 600 and got.n_links.tolist() == near.sum(1).tolist()


def test_vectors_empty(spark):
    assert embeddings.clusters(spark.createDataFrame([], "vec_id long, embedding array<float>")).count() == 0


def test_tables_grow_slowly():
    bits, tables = embeddings.tables_for(10_000, 0.95)
    more_bits, more = embeddings.tables_for(1_000_000, 0.95)
    assert more_bits > bits and more < 4 * tables
    p = 1 - math.acos(0.95) / math.pi
    assert (1 - p**bits) ** tables <= 1e-5


def test_components(spark):
    r = random.Random(1)
    edges = [(r.randrange(300), r.randrange(300)) for _ in range(220)] + [(k, k + 1) for k in range(1000, 1100)] + [(5000, k) for k in range(5001, 5200)]
    got = {x.node: x.root for x in components(spark.createDataFrame(edges, "a long, b long"), spark).collect()}
    up: dict[int, int] = {}

    def root(x):
        while up.setdefault(x, x) != x:
            x = up[x]
        return x

    for a, b in edges:
        x, y = root(a), root(b)
        up[max(x, y)] = min(x, y)
    assert got == {x: root(x) for a, b in edges for x in (a, b) if a != b or root(a) != a or any(a in e and e[0] != e[1] for e in edges)}


def test_pipeline_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    assert len(corpus_pipeline.STAGES) == 5
    seen = {r.doc_id for r in docs.collect()}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, sf)
        assert out.columns == docs.columns, name
        assert dict(out.dtypes) == dict(docs.dtypes)
        now = {r.doc_id for r in out.select("doc_id").collect()}
        assert now and now <= seen, name
        seen, docs = now, out.cache()
    last = corpus_pipeline.STAGES[-1][1](spark, docs, sf)
    assert {r.doc_id for r in last.collect()} == seen
    assert corpus_pipeline.run(spark, sf).count() == len(seen)


def test_pipeline_keeps_clashing_columns(spark, sf):
    """Columns that are named like those inside the operators come out as they went in."""
    names = ["__quality", "__hs", "__key", "__id", "__tk", "__n", "__kept", "__n_lines", "score", "h"]
    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(60).withColumns({n: F.concat(F.lit(n), F.col("doc_id").cast("string")) for n in names})
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, sf)
        assert out.columns == docs.columns, name
        for x in out.limit(5).collect():
            assert all(x[n] == f"{n}{x.doc_id}" for n in names), name


def test_pipeline_plain_python(spark, sf):
    """The final rows against plain Python for every stage but the classifier's weights, which are taken as fitted."""
    import hashlib
    import re

    import public_tokenizers
    import xxhash
    from tokenizers import Tokenizer

    from idagg.llm import quality

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    net = quality.fit(docs, spark.read.parquet(f"{sf}/labels.parquet"), may_learn=F.crc32(F.col("id").cast("string")) % 3 != 1)
    text = {r.doc_id: r.text or "" for r in docs.orderBy("doc_id").collect()}
    text = {d: t for d, t in text.items() if net.score(quality.features([t]))[0] >= 0.5}
    # lines that stand in a pair which an earlier place has too
    seen, cut = set(), {}
    for d, t in text.items():
        ls = t.split("\n")
        gone = set()
        for k in range(len(ls) - 1):
            if (ls[k], ls[k + 1]) in seen:
                gone |= {k, k + 1}
            seen.add((ls[k], ls[k + 1]))
        cut[d] = "\n".join(x for k, x in enumerate(ls) if k not in gone)
    # one of each component within three bits
    fp = {}
    for d, t in cut.items():
        w = re.findall("[^\x20\x09-\x0d]+", re.sub("[A-Z]", lambda m: m[0].lower(), t))
        hs = [xxhash.xxh64_intdigest(x.encode(), seed=42) for x in ([" ".join(w[i : i + 3]) for i in range(len(w) - 2)] or [" ".join(w)])] if w else []
        fp[d] = sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs)) if hs else 0
    up = {d: d for d in fp}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    ids = sorted(fp)
    for i, a in enumerate(ids):
        for b in ids[:i]:
            if (fp[a] ^ fp[b]).bit_count() <= 3:
                x, y = sorted((root(a), root(b)))
                up[y] = x
    kept = [d for d in ids if root(d) == d]
    # no benchmark item at four fifths of its five-word shingles

    def shingles(t):
        w = re.findall(r"\w+", t.lower())
        return {tuple(w[i : i + 5]) for i in range(len(w) - 4)}

    items = [shingles(r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    assert all(items)
    kept = [d for d in kept if not any(len(i & own) >= 0.8 * len(i) for own in [shingles(cut[d])] for i in items)]
    tok = Tokenizer.from_file(str(public_tokenizers.path("word_bpe_49k.json")))
    tok.no_truncation()
    tok.no_padding()
    want = {}
    for d in kept:
        e = tok.encode(cut[d], add_special_tokens=False).ids
        want[d] = (len(e), hashlib.sha256(" ".join(map(str, e)).encode()).hexdigest(), hashlib.sha256(tok.decode(e, skip_special_tokens=False).encode()).hexdigest())
    got = {r.doc_id: (r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in corpus_pipeline.run(spark, sf).collect()}
    assert got == want and len(want) > 50


def test_pipeline_empty(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").where("false").withColumn("extra", F.lit(1))
    for _, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, sf)
        assert out.count() == 0
