"""Benchmark decontamination: which test items does a document hold, wholly or nearly so?

An item counts as found where at least ``threshold`` of its distinct 5-word shingles occur in the document. Candidates come from a
size-partitioned MinHash search: items are partitioned by shingle count into classes of sizes (c/2, c]; for a class, a document is read
as windows of two adjacent blocks of c shingles, so that a place which holds an item shares a large part of its window however long the
document is. In a class the containment threshold gives a least Jaccard similarity of item and window, and with it the chance to miss
with ``hashes`` minima (at most 4e-5); any equal minimum makes a candidate. Items of up to TINY shingles are looked up by their shingles. Block minima are computed once for the smallest class and merged in pairs for
larger ones. Candidates are verified by exact containment, comparing shingle texts over the whole document.

Items are a stated query set. They are broadcast in blocks of at most ``block_items`` and about BLOCK_BYTES, each block one pass over the documents;
documents aren't shuffled. A worker makes a block's index once.

Edge cases: null or empty texts hold nothing; an item of one to four words is one shingle of all its words: it is looked up
at every place of a document of five words or more, and is found in a shorter one where that has the same words and no others; items
without words are never found; repeated rows are each reported; several items may be found in one document, each on its own row. Extra columns of
any name don't matter to ``search`` and are carried along by ``drop_contaminated``.
"""

from __future__ import annotations

import re
import uuid
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._common import keep_memo_of, owns_memo

SHINGLE, HASHES, BASE, BLOCK_ITEMS, BLOCK_BYTES = 5, 48, 8, 50_000, 32 << 20
TINY = 4  # items of so few shingles are looked up by each of them: a window would dwarf them
_WORDS = re.compile(r"\w+").findall
_A = np.uint64(0x9E3779B97F4A7C15)
_STEP = [np.uint64((0xC2B2AE3D27D4EB4F * (2 * k + 1)) % (1 << 64)) for k in range(5)]
_MUL = np.random.default_rng(5).integers(1, 1 << 32, HASHES, dtype=np.uint64).astype(np.uint32) | np.uint32(1)
_ADD = np.random.default_rng(6).integers(0, 1 << 32, HASHES, dtype=np.uint64).astype(np.uint32)


class _Words(dict):
    def __missing__(self, w: str) -> int:
        if len(self) > 250_000:
            self.clear()
        h = self[w] = xxhash.xxh3_64_intdigest(w)
        return h


_HASH = _Words()
_INDEX: dict[str, ItemIndex] = {}  # the last block's index that a worker made


def _forget() -> None:
    _HASH.clear()
    _INDEX.clear()


owns_memo("decontaminate", _forget)


def words_of(text: str | None) -> list[str]:
    return _WORDS((text or "").lower())


def _mix(h: np.ndarray, k: int) -> np.ndarray:
    """A 32-bit hash of each k adjacent words."""
    n = len(h) - k + 1
    with np.errstate(over="ignore"):
        s = np.full(n, np.uint64(k))
        for j in range(k):
            s = (s ^ (h[j : n + j] * _STEP[j])) * _A
            s ^= s >> np.uint64(29)
    return (s >> np.uint64(32)).astype(np.uint32)


def shingle_hashes(words: list[list[str]]) -> list[np.ndarray]:
    """Of each text of SHINGLE words or more, a hash of each shingle, in order; of shorter ones none."""
    sizes = [len(w) for w in words]
    h = np.fromiter(map(_HASH.__getitem__, chain.from_iterable(words)), np.uint64, sum(sizes))
    s = _mix(h, SHINGLE) if len(h) >= SHINGLE else np.zeros(0, np.uint32)
    out, at = [], 0
    for n in sizes:
        out.append(s[at : at + max(0, n - SHINGLE + 1)] if n >= SHINGLE else s[:0])
        at += n
    return out


def shingle_text(words: list[str], at: int) -> str:
    return " ".join(words[at : at + SHINGLE])


def item_minima(s: np.ndarray) -> np.ndarray:
    """The least value of each hash function over a shingle set."""
    with np.errstate(over="ignore"):
        return (s[:, None] * _MUL[None] + _ADD[None]).min(0)


def block_minima(many: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """blocks x HASHES minima of blocks of BASE shingles, and the number of blocks of each text; the last block of a text is filled up
    with its last shingle, which changes no minimum."""
    counts = np.array([-(-len(s) // BASE) for s in many])
    buf = np.empty(int(counts.sum()) * BASE, np.uint32)
    at = 0
    for s, n in zip(many, counts.tolist(), strict=True):
        buf[at : at + len(s)] = s
        buf[at + len(s) : at + n * BASE] = s[-1]
        at += n * BASE
    out = np.empty((len(buf) // BASE, HASHES), np.uint32)
    with np.errstate(over="ignore"):
        for k in range(HASHES):
            v = (buf * _MUL[k] + _ADD[k]).reshape(-1, BASE)
            v = np.minimum(v[:, :4], v[:, 4:])
            v = np.minimum(v[:, :2], v[:, 2:])
            np.minimum(v[:, 0], v[:, 1], out=out[:, k])
    return out, counts


def _pairs(m: np.ndarray, counts: np.ndarray, step: int, made: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Minima of blocks i * step and the next one within each text, for i below ``made`` of the text; and the text of each."""
    text = np.repeat(np.arange(len(counts)), made)
    i = np.arange(len(text)) - np.repeat(np.cumsum(made) - made, made)
    start = np.repeat(np.cumsum(counts) - counts, made)
    left = start + i * step
    right = np.minimum(left + 1, start + np.repeat(counts, made) - 1)
    return np.minimum(m[left], m[right]), text


def miss_chance(q: int, c: int, threshold: float, hashes: int = HASHES) -> float:
    """Of an item of q shingles in class c that is found at the threshold exactly."""
    shared = threshold * q
    return (1 - shared / (q + 2 * c - shared)) ** hashes


class ItemIndex:
    """Items by size class, with their minima by hash function."""

    def __init__(self, items: list[tuple], threshold: float):
        self.threshold = threshold
        self.ids, self.sets = [], []
        self.short: dict[str, list[int]] = {}
        tiny: list[tuple[int, int]] = []
        by_class: dict[int, list[tuple[int, np.ndarray]]] = {}
        for item, text in items:
            w = words_of(text)
            if not w:
                continue
            k = len(self.ids)
            own = {shingle_text(w, i) for i in range(max(1, len(w) - SHINGLE + 1))}
            self.ids.append(item)
            self.sets.append(own)
            if len(w) < SHINGLE:
                self.short.setdefault(" ".join(w), []).append(k)
                continue
            if len(own) <= TINY:
                tiny += [(int(x), k) for x in shingle_hashes([w])[0]]
                continue
            c = BASE
            while c < len(own):
                c *= 2
            by_class.setdefault(c, []).append((k, shingle_hashes([w])[0]))
        tiny.sort()
        self.tiny = np.array([x for x, _ in tiny], np.uint32)
        self.tiny_items = np.array([k for _, k in tiny], np.int64)
        self.tiny_table = np.zeros(1 << 16, bool)
        self.tiny_table[self.tiny >> np.uint32(16)] = True
        self.classes: dict[int, tuple] = {}
        for c, found in by_class.items():
            keys = np.array([item_minima(s) for _, s in found])  # items x HASHES
            which = np.array([k for k, _ in found])
            coded = (np.arange(HASHES, dtype=np.uint64) << np.uint64(32)) | keys.astype(np.uint64)
            order = np.argsort(coded.ravel(), kind="stable")
            flat = coded.ravel()[order]
            table = np.zeros((HASHES, 1 << 16), bool)  # which upper halves of minima any item has
            table[np.tile(np.arange(HASHES), len(found)), (keys >> np.uint32(16)).ravel()] = True
            self.classes[c] = (flat, np.repeat(which, HASHES)[order], table)
        self.short_sizes = sorted({x.count(" ") + 1 for x in self.short})

    def candidates(self, many: list[np.ndarray]) -> list[set[int]]:
        """Of each text, the items that share a minimum with a window of its shingles (each text has some)."""
        out: list[set[int]] = [set() for _ in many]
        for text, s in enumerate(many if len(self.tiny) else ()):
            s = s[self.tiny_table[s >> np.uint32(16)]]
            lo, hi = np.searchsorted(self.tiny, s, "left"), np.searchsorted(self.tiny, s, "right")
            for j in np.flatnonzero(hi > lo):
                out[text].update(self.tiny_items[lo[j] : hi[j]].tolist())
        if not many or not self.classes:
            return out
        m, counts = block_minima(many)
        size, top, cols = BASE, max(self.classes), np.arange(HASHES)
        while True:
            if size in self.classes:
                flat, which, table = self.classes[size]
                w, text = _pairs(m, counts, 1, np.maximum(1, counts - 1))
                r, k = np.nonzero(table[cols, w >> np.uint32(16)])
                if len(r):
                    code = (k.astype(np.uint64) << np.uint64(32)) | w[r, k].astype(np.uint64)
                    lo, hi = np.searchsorted(flat, code, "left"), np.searchsorted(flat, code, "right")
                    for j in np.flatnonzero(hi > lo):
                        out[text[r[j]]].update(which[lo[j] : hi[j]].tolist())
            if size >= top:
                return out
            m, _ = _pairs(m, counts, 2, -(-counts // 2))
            counts, size = -(-counts // 2), size * 2

    def find_many(self, texts: list[str | None]) -> list[list[tuple]]:
        """Of each text, (item, containment) of the items that it holds."""
        words = [words_of(t) for t in texts]
        hashes = shingle_hashes(words)
        long = [k for k, s in enumerate(hashes) if len(s)]
        got = dict(zip(long, self.candidates([hashes[k] for k in long]), strict=True))
        out: list[list[tuple]] = []
        for k, w in enumerate(words):
            found = []
            if got.get(k):
                have = {shingle_text(w, i) for i in range(len(w) - SHINGLE + 1)}
                for j in sorted(got[k]):
                    share = len(self.sets[j] & have) / len(self.sets[j])
                    if share >= self.threshold:
                        found.append((self.ids[j], share))
            out.append(found + [(self.ids[j], 1.0) for j in self._short_in(w)])
        return out

    def _short_in(self, words: list[str]) -> list[int]:
        """Items of fewer words than a shingle that stand anywhere in the words; in as few words, those that equal them."""
        sizes = self.short_sizes if len(words) >= SHINGLE else [len(words)]
        runs = {" ".join(words[i : i + n]) for n in sizes for i in range(len(words) - n + 1)}
        return sorted(j for x in runs & self.short.keys() for j in self.short[x])

    def find_in(self, column: pa.Array, slice_rows: int = 64) -> Iterator[list[tuple]]:
        """find_many over a column of texts, a bounded slice at a time."""
        for lo in range(0, len(column), slice_rows):
            yield from self.find_many(column.slice(lo, slice_rows).to_pylist())


def _index(name: str, items: list[tuple], threshold: float) -> ItemIndex:
    """The index of a block, made once a worker and not once a task."""
    if name not in _INDEX:
        _INDEX.clear()
        _INDEX[name] = ItemIndex(items, threshold)
    return _INDEX[name]


def _blocks(benchmark: DataFrame, item_col: str, item_text: str, block_items: int, block_bytes: int = BLOCK_BYTES) -> Iterator[list[tuple]]:
    """The items, a block at a time that is bounded in rows and bytes (about: items are dealt by hash; no item is cut)."""
    items = benchmark.select(F.col(item_col).cast("long").alias("item"), F.col(item_text).alias("text")).where("text is not null")
    size = items.agg(F.count("*").alias("n"), F.coalesce(F.sum(F.octet_length("text")), F.lit(0)).alias("b")).first()
    n = max(1, -(-size.n // block_items), -(-size.b // block_bytes))
    for k in range(n):
        part = items if n == 1 else items.where(F.pmod(F.xxhash64("item", "text"), F.lit(n)) == k)
        yield [tuple(r) for r in part.collect()]


def search(docs: DataFrame, benchmark: DataFrame, threshold: float = 0.8, id_col: str = "doc_id", text_col: str = "text",
           item_col: str = "item_id", item_text: str = "text", block_items: int = BLOCK_ITEMS) -> DataFrame:
    """(id, item, containment): a row for each item found in a document."""
    d = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    kind = docs.schema[id_col].dataType.simpleString()

    def searched(shared, name):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            keep_memo_of("decontaminate")
            index = _index(name, shared.value, threshold)
            for b in batches:
                ids, items, shares = [], [], []
                for d, found in zip(b.column(0).to_pylist(), index.find_in(b.column(1)), strict=True):
                    for item, share in found:
                        ids.append(d)
                        items.append(item)
                        shares.append(share)
                yield pa.RecordBatch.from_arrays([pa.array(ids, b.schema.field(0).type), pa.array(items, pa.int64()), pa.array(shares, pa.float64())], ["id", "item", "containment"])

        return d.mapInArrow(run, f"id {kind}, item long, containment double")

    out = None
    for block in _blocks(benchmark, item_col, item_text, block_items):
        got = searched(docs.sparkSession.sparkContext.broadcast(block), uuid.uuid4().hex)
        out = got if out is None else out.union(got)
    return out.select(F.col("id").alias(id_col), F.col("item").alias(item_col), "containment")


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, threshold: float = 0.8, text_col: str = "text",
                      item_col: str = "item_id", item_text: str = "text", block_items: int = BLOCK_ITEMS) -> DataFrame:
    """The rows of docs that hold no item, with all columns; no shuffle."""

    def kept(df: DataFrame, shared, name):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            keep_memo_of("decontaminate")
            index = _index(name, shared.value, threshold)
            for b in batches:
                yield b.filter(pa.array([not found for found in index.find_in(b.column(text_col))], pa.bool_()))

        return df.mapInArrow(run, df.schema)

    for block in _blocks(benchmark, item_col, item_text, block_items):
        docs = kept(docs, docs.sparkSession.sparkContext.broadcast(block), uuid.uuid4().hex)
    return docs


def oracle(threshold: float = 0.8) -> str:
    """The items of five words or more in documents as DuckDB SQL: every item's shingles against every document's."""
    words = "regexp_extract_all(lower({}), '[\\p{{L}}\\p{{N}}_]+')"
    pieces = f"unnest([array_to_string(w[i : i + {SHINGLE - 1}], ' ') for i in range(1, len(w) - {SHINGLE - 2})]) AS s"
    return f"""
WITH iw AS (SELECT item_id, {words.format('text')} AS w FROM benchmark WHERE text IS NOT NULL),
i AS (SELECT DISTINCT item_id, {pieces} FROM iw WHERE len(w) >= {SHINGLE}),
n AS (SELECT item_id, count(*) AS n FROM i GROUP BY item_id),
dw AS (SELECT doc_id, {words.format('text')} AS w FROM documents WHERE text IS NOT NULL),
d AS (SELECT DISTINCT doc_id, {pieces} FROM dw WHERE len(w) >= {SHINGLE}),
x AS (SELECT doc_id, item_id, count(*) AS c FROM d JOIN i USING (s) GROUP BY ALL)
SELECT doc_id, item_id, c::DOUBLE / n AS containment FROM x JOIN n USING (item_id) WHERE c::DOUBLE / n >= {threshold}
"""
