"""Toxicity scores: logistic regression fitted by FTRL-proximal over hashed word n-grams and skip-grams.

Features of a text are the distinct hashed words, word pairs and pairs that skip one word; a word also counts by its stems (cut to a
few letters), so that inflected and compound forms share evidence. Each coordinate has its own
learning rate and an L1 threshold, so most weights are exactly zero and the model that is broadcast is a short list of
(slot, weight) pairs, bounded by the hash space (2**SLOT_BITS) whatever the corpus size.

Fit: at most ``max_rows`` labelled rows (those whose id hashes lowest), read by one task as a stream; the labels are a
bounded, broadcast list, so texts are filtered in the scan. Score: one map over the whole texts, no shuffle.

Edge cases: null and empty texts get the score of the bias alone; rows are scored one by one, so repeated rows and ties give
equal scores; with no labelled rows, or labels of one kind only, the bias is the smoothed log odds and no weight is set. Extra columns are
carried along; one that has the score's name gives way to it.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._common import bounded_sample, keep_memo_of, owns_memo, with_field

SLOT_BITS = 20
STEMS = (3, 4, 5, 7)
MAX_ROWS = 12_000
_WORDS = re.compile(r"\w+").findall
_A, _B, _MIX = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F), np.uint64(0xD6E8FEB86659FD93)
_SHIFT = np.uint64(64 - SLOT_BITS)


class _WordRows(dict):
    """Row of each known word in a table of hashes: the word itself, then its stems (the word cut to so many letters)."""

    def __init__(self):
        super().__init__()
        self.table = np.zeros((1024, 1 + len(STEMS)), np.uint64)

    def __missing__(self, w: str) -> int:
        k = len(self)
        if k == len(self.table):
            self.table = np.concatenate([self.table, np.zeros_like(self.table)])
        own = xxhash.xxh3_64_intdigest(w)
        self.table[k, 0] = own
        for j, n in enumerate(STEMS):
            self.table[k, 1 + j] = xxhash.xxh3_64_intdigest(w[:n], n) if len(w) > n else own
        self[w] = k
        return k


_ROWS = _WordRows()


def _forget() -> None:
    global _ROWS
    _ROWS = _WordRows()


owns_memo("toxicity", _forget)


def slots(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Hashed features of the texts, all in one array, and the text that each belongs to (repeats included)."""
    global _ROWS
    if len(_ROWS) > 400_000:
        _ROWS = _WordRows()
    words = [_WORDS(t.lower()) for t in texts]
    sizes = np.fromiter(map(len, words), np.int64, len(words))
    n = int(sizes.sum())
    rows = np.fromiter(map(_ROWS.__getitem__, chain.from_iterable(words)), np.int64, n)
    at = np.repeat(np.arange(len(words), dtype=np.int32), sizes)
    every = _ROWS.table[rows]
    h = every[:, 0]
    with np.errstate(over="ignore"):
        one = (every * _MIX) >> _SHIFT
        two = ((h[:-1] * _A + h[1:]) * _MIX) >> _SHIFT
        skip = ((h[:-2] * _B + h[2:] + _A) * _MIX) >> _SHIFT
    in2, in3 = at[1:] == at[:-1], at[2:] == at[:-2]
    return (
        np.concatenate([one.T.ravel(), two[in2], skip[in3]]).astype(np.int64),
        np.concatenate([np.tile(at, every.shape[1]), at[1:][in2], at[2:][in3]]),
    )


class Ftrl:
    """FTRL-proximal: z and n by coordinate; weights follow in closed form."""

    def __init__(self, size: int, alpha: float = 0.3, beta: float = 1.0, l1: float = 1.5, l2: float = 1.0):
        self.z, self.n = np.zeros(size), np.zeros(size)
        self.alpha, self.beta, self.l1, self.l2 = alpha, beta, l1, l2

    def weights(self, i) -> np.ndarray:
        z, n = self.z[i], self.n[i]
        w = -(z - np.sign(z) * self.l1) / ((self.beta + np.sqrt(n)) / self.alpha + self.l2)
        return np.where(np.abs(z) <= self.l1, 0.0, w)

    def learn(self, i: np.ndarray, y: float, bias: float) -> float:
        """One step on the distinct coordinates i; returns the gradient by the margin."""
        w = self.weights(i)
        p = 1 / (1 + np.exp(-np.clip(w.sum() + bias, -35, 35)))
        g = p - y
        n = self.n[i]
        sigma = (np.sqrt(n + g * g) - np.sqrt(n)) / self.alpha
        self.z[i] += g - sigma * w
        self.n[i] = n + g * g
        return g


def _fit(batches: Iterator[pa.RecordBatch], epochs: int) -> Iterator[pa.RecordBatch]:
    docs, ys = [], []
    for b in batches:
        y = b.column("y").to_pylist()
        texts = [t or "" for t in b.column("text").to_pylist()]
        for lo in range(0, len(texts), 256):
            s, at = slots(texts[lo : lo + 256])
            cuts = np.argsort(at, kind="stable")
            s, at = s[cuts], at[cuts]
            ends = np.searchsorted(at, np.arange(len(texts[lo : lo + 256]) + 1))
            docs += [np.unique(s[a:z]).astype(np.int32) for a, z in zip(ends[:-1], ends[1:], strict=True)]
        ys += y
    pos = sum(ys)
    bias = float(np.log((pos + 1) / (len(ys) - pos + 1)))
    model, square = Ftrl(1 << SLOT_BITS), 1.0
    if 0 < pos < len(ys):
        for _ in range(epochs):
            for i, y in zip(docs, ys, strict=True):
                g = model.learn(i, y, bias)
                square += g * g
                bias -= 0.1 * g / np.sqrt(square)
    w = model.weights(slice(None))
    keep = np.flatnonzero(w)
    yield pa.RecordBatch.from_arrays([pa.array(np.append(-1, keep)), pa.array(np.append(bias, w[keep]))], ["slot", "weight"])


def fit(docs: DataFrame, labels: DataFrame, label: str = "toxic", may_learn: Column | None = None, id_col: str = "doc_id",
        text_col: str = "text", max_rows: int = MAX_ROWS, epochs: int = 3) -> tuple[np.ndarray, np.ndarray]:
    """Slots and weights, slot -1 being the bias. may_learn: which labelled rows (by a condition on the id) may be used."""
    rows = labels.select(F.col(id_col).alias("id"), F.col(label).cast("double").alias("y")).where("id is not null and y in (0, 1)")
    if may_learn is not None:
        rows = rows.where(may_learn)
    rows = bounded_sample(rows.groupBy("id").agg(F.max("y").alias("y")), ["id"], max_rows)
    sample = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).join(F.broadcast(rows), "id")
    got = (
        sample.repartition(1).sortWithinPartitions("__o", "id", F.xxhash64("text")).select("text", "y")
        .mapInArrow(lambda it: _fit(it, epochs), "slot long, weight double").collect()
    )
    if not got:
        return np.array([-1]), np.array([0.0])
    return np.array([r.slot for r in got]), np.array([r.weight for r in got])


def score(docs: DataFrame, model: tuple[np.ndarray, np.ndarray], text_col: str = "text", out: str = "score") -> DataFrame:
    """docs with a score column: the probability that a text is toxic."""
    docs = docs.drop(out)
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keep_memo_of("toxicity")
        table = np.zeros(1 << SLOT_BITS)
        at, w = shared.value
        bias = float(w[at < 0].sum())
        table[at[at >= 0]] = w[at >= 0]
        for b in batches:
            logit = np.full(b.num_rows, bias)
            for lo in range(0, b.num_rows, 512):
                s, d = slots([t or "" for t in b.column(text_col).slice(lo, 512).to_pylist()])
                hit = np.flatnonzero(table[s])
                pairs = np.unique((d[hit].astype(np.int64) << SLOT_BITS) | s[hit])
                np.add.at(logit, lo + (pairs >> SLOT_BITS), table[pairs & ((1 << SLOT_BITS) - 1)])
            p = 1 / (1 + np.exp(-np.clip(logit, -35, 35)))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(p)], [*b.schema.names, out])

    return docs.mapInArrow(run, with_field(docs, out, "double"))
