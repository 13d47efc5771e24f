"""Quality scores by positive-unlabelled learning with the non-negative unbiased risk.

Trusted positives (rows labelled good) and unlabelled web texts are all that the risk uses; the share of good texts, the
class prior, is estimated from the labelled rows that may be learnt from. The risk of calling a text bad is the unlabelled risk
less the prior times the positives' share of it, held at zero or above: where a step makes it negative, the step undoes that part instead.

Features are character-class shares, word and line statistics of the whole text; a small network with one hidden layer is
fitted in one task on bounded samples (max_positive, max_unlabelled rows, those whose id hashes lowest). Scoring is a map over
whole texts with a model of a few kilobytes, no shuffle.

Edge cases: null counts as empty text, whose features are all zero and whose score is the network's for them; rows are scored one
by one, so repeated rows and ties give equal scores; without positives the score is 0.5 for all. Extra columns are carried along; one that
has the score's name gives way to it.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._common import bounded_sample, keep_memo_of, with_field

MAX_POSITIVE, MAX_UNLABELLED = 6_000, 10_000
_SIGNS = b"!?.,;:'\"()[]{}<>/\\|*%&$#@=+-_~^`"
N_CLASS = 40


def _classes() -> np.ndarray:
    """Character class of each byte."""
    c = np.full(256, 0, np.uint8)
    c[list(range(65, 91))], c[list(range(97, 123))], c[list(range(48, 58))] = 1, 2, 3
    c[32], c[10], c[[9, 13, 11, 12]], c[128:] = 4, 5, 6, 7
    for k, s in enumerate(_SIGNS):
        c[s] = 8 + k
    return c


_CLASS = _classes()


def features(texts: list[str]) -> np.ndarray:
    """One row a text: shares of character classes, then log sizes, word and line statistics."""
    raw = [t.encode("utf-8", "replace") for t in texts]
    n = len(raw)
    out = np.zeros((n, N_CLASS + 8))
    for k, (t, r) in enumerate(zip(texts, raw, strict=True)):
        if not r:
            continue
        count = np.bincount(_CLASS[np.frombuffer(r, np.uint8)], minlength=N_CLASS)[:N_CLASS]
        out[k, :N_CLASS] = count / len(r)
        words = t.split()
        lines = [x for x in t.split("\n") if x]
        m, u = len(words), len(set(words))
        punct = count[8:].sum()
        out[k, N_CLASS:] = (
            np.log1p(len(r)), np.log1p(m), len(r) / (m + 1) / 10, u / (m + 1), np.log1p(m) - np.log1p(u),
            len(set(lines)) / (len(lines) + 1), np.log1p(m / (len(lines) + 1)), min(punct / (m + 1), 4),
        )
    return out


class Network:
    """Features are standardised, then one hidden layer of tanh units; the output is a margin for good."""

    def __init__(self, mean, std, seed: int = 0, hidden: int = 24):
        r = np.random.default_rng(seed)
        self.mean, self.std = mean, std
        d = len(mean)
        self.p = [r.normal(0, d**-0.5, (d, hidden)), np.zeros(hidden), r.normal(0, hidden**-0.5, hidden), np.zeros(1)]

    def scaled(self, x: np.ndarray) -> np.ndarray:
        return np.clip((x - self.mean) / self.std, -6, 6)

    def forward(self, z: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        h = np.tanh(z @ self.p[0] + self.p[1])
        return h @ self.p[2] + self.p[3], h

    def backward(self, z, h, g) -> list[np.ndarray]:
        gh = np.outer(g, self.p[2]) * (1 - h * h)
        return [z.T @ gh, gh.sum(0), h.T @ g, np.array([g.sum()])]

    def score(self, x: np.ndarray) -> np.ndarray:
        m = self.forward(self.scaled(x))[0]
        return 1 / (1 + np.exp(-np.clip(m, -35, 35)))


def fit_network(pos: np.ndarray, unl: np.ndarray, prior: float, epochs: int = 60, batch: int = 256, rate: float = 0.01, seed: int = 0) -> Network:
    """Minimise the non-negative risk with the logistic loss by Adam."""
    both = np.vstack([pos, unl])
    net = Network(both.mean(0), both.std(0) + 1e-3, seed)
    p, u = net.scaled(pos), net.scaled(unl)
    r = np.random.default_rng(seed + 1)
    m1, m2, t = [np.zeros_like(x) for x in net.p], [np.zeros_like(x) for x in net.p], 0
    share = max(1, round(batch * len(p) / max(1, len(u))))

    def sig(x):
        return 1 / (1 + np.exp(-np.clip(x, -35, 35)))

    for epoch in range(epochs):
        order, porder = r.permutation(len(u)), r.permutation(len(p))
        for lo in range(0, len(u), batch):
            zu = u[order[lo : lo + batch]]
            zp = p[porder[np.arange(lo // batch * share, lo // batch * share + share) % len(p)]]
            fu, hu = net.forward(zu)
            fp, hp = net.forward(zp)
            bad = np.logaddexp(0, fu).mean() - prior * np.logaddexp(0, fp).mean()
            gu, gp_bad, gp_good = sig(fu) / len(fu), -prior * sig(fp) / len(fp), -prior * sig(-fp) / len(fp)
            if bad >= 0:
                g = [a + b for a, b in zip(net.backward(zu, hu, gu), net.backward(zp, hp, gp_good + gp_bad), strict=True)]
            else:
                g = [-(a + b) for a, b in zip(net.backward(zu, hu, gu), net.backward(zp, hp, gp_bad), strict=True)]
            t += 1
            step = rate * (1 - epoch / epochs)
            for k, x in enumerate(g):
                x = x + 1e-4 * net.p[k]
                m1[k] = 0.9 * m1[k] + 0.1 * x
                m2[k] = 0.999 * m2[k] + 0.001 * x * x
                net.p[k] = net.p[k] - step * (m1[k] / (1 - 0.9**t)) / (np.sqrt(m2[k] / (1 - 0.999**t)) + 1e-8)
    return net


def _train(batches: Iterator[pa.RecordBatch], prior: float) -> Iterator[pa.RecordBatch]:
    x, pos, unl = [], [], []
    for b in batches:
        x.append(features([t or "" for t in b.column("text").to_pylist()]))
        pos += b.column("pos").to_pylist()
        unl += b.column("unl").to_pylist()
    net = None
    if x:
        x, pos, unl = np.vstack(x), np.array(pos, bool), np.array(unl, bool)
        if pos.any() and unl.any():
            net = fit_network(x[pos], x[unl], prior)
    yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(net)], pa.binary())], ["net"])


def fit(docs: DataFrame, labels: DataFrame, label: str = "quality", may_learn: Column | None = None, id_col: str = "doc_id",
        text_col: str = "text", max_positive: int = MAX_POSITIVE, max_unlabelled: int = MAX_UNLABELLED) -> Network | None:
    rows = labels.select(F.col(id_col).alias("id"), F.col(label).cast("double").alias("y")).where("id is not null and y in (0, 1)")
    if may_learn is not None:
        rows = rows.where(may_learn)
    share = rows.agg(F.sum("y").alias("p"), F.count("*").alias("n")).first()
    if not share.n or not share.p:
        return None
    prior = min(0.98, max(0.02, (share.p + 1) / (share.n + 2)))
    good = bounded_sample(rows.where("y = 1").select("id").distinct(), ["id"], max_positive)
    web = bounded_sample(docs.select(F.col(id_col).alias("id")).where("id is not null"), ["id"], max_unlabelled, 1)
    picked = (
        good.select("id", F.lit(1).alias("pos"), F.lit(0).alias("unl")).union(web.select("id", F.lit(0), F.lit(1)))
        .groupBy("id").agg(F.max("pos").alias("pos"), F.max("unl").alias("unl"))
    )
    sample = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).join(F.broadcast(picked), "id")
    got = (
        sample.repartition(1).sortWithinPartitions(F.xxhash64("id", F.lit(2)), "id", F.xxhash64("text")).select("text", "pos", "unl")
        .mapInArrow(lambda it: _train(it, prior), "net binary").collect()
    )
    return pickle.loads(got[0].net) if got else None


def score(docs: DataFrame, net: Network | None, text_col: str = "text", out: str = "score") -> DataFrame:
    docs = docs.drop(out)
    shared = docs.sparkSession.sparkContext.broadcast(net)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keep_memo_of(None)
        net = shared.value
        for b in batches:
            p = np.full(b.num_rows, 0.5)
            for lo in range(0, b.num_rows if net else 0, 512):
                p[lo : lo + 512] = net.score(features([t or "" for t in b.column(text_col).slice(lo, 512).to_pylist()]))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(p)], [*b.schema.names, out])

    return docs.mapInArrow(run, with_field(docs, out, "double"))
