"""Line dedup by content-defined chunks of lines.

Every line is hashed; a rolling hash over the hashes of the last ``window`` lines ends a chunk where its low bits are zero. So boundaries
depend on nearby lines only, and a passage that is shifted by inserted lines falls into the same chunks after its first boundary. Chunks
of two lines or more that occur again anywhere, in the same or another document, are removed but for their first occurrence (smallest id,
then place). Chunks of one line stay.

With ``runs`` a boundary stands after every line instead, and neighbouring lines that repeat together, two or more, make up a chunk: each pair of
adjacent lines is looked up, and pairs that overlap are one chunk. So every line of every run of two or more lines that occurred before
goes, wherever the run begins and ends. A line is only cut where the same line, in the same pair, stands at an earlier place, so some copy
of each line stays.

Two jobs: chunk digests (128 bits) are counted, aggregated before the shuffle, and the occurrences to remove are listed by document;
then documents are joined with their lists. Every removal is decided by a comparison of bytes: the texts of repeated chunks are
aggregated to least and greatest by digest, and chunks of a digest where those differ (none, short of a collision of 128 bits) all stay.

Edge cases: null text stays null, empty text stays empty; line ends are "\\n" and every other character belongs to its line; null ids come
first and rows that repeat an id are told apart by their text's digest, exact repeats of a row all keeping what the first keeps; an empty
table gives no rows. Extra columns are carried along whatever their names; only with ``counts`` do columns named like the counts give way to them.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._common import fresh, keep_memo_of, materialize

WINDOW, MASK = 2, 3  # a chunk ends after one line in four on average
_MULT = 0x9E3779B97F4A7C15


def chunks(text: str, window: int = WINDOW, mask: int = MASK) -> list[list[str]]:
    """The text's lines in chunks; joining all lines by "\\n" gives the text back."""
    lines = text.split("\n")
    hashes = [xxhash.xxh3_64_intdigest(x.encode("utf-8", "replace")) for x in lines]
    out, start = [], 0
    for i in range(len(lines)):
        roll = 0
        for h in hashes[max(0, i - window + 1) : i + 1]:
            roll = ((roll ^ h) * _MULT) & 0xFFFFFFFFFFFFFFFF
        if (roll >> 40) & mask == 0:
            out.append(lines[start : i + 1])
            start = i + 1
    if start < len(lines):
        out.append(lines[start:])
    return out


def pieces(text: str, runs: bool) -> list[tuple[int, list[str]]]:
    """First line's number and lines of each piece that is looked up: chunks of two lines or more, or all pairs of adjacent lines."""
    if runs:
        lines = text.split("\n")
        return [(k, lines[k : k + 2]) for k in range(len(lines) - 1)]
    out, at = [], 0
    for c in chunks(text):
        if len(c) > 1:
            out.append((at, c))
        at += len(c)
    return out


def _digest(chunk: list[str]) -> bytes:
    return xxhash.xxh3_128_digest("\n".join(chunk).encode("utf-8", "replace"))


def _text_key(text: str | None) -> int:
    return xxhash.xxh3_64_intdigest((text or "").encode("utf-8", "replace")) - (1 << 63)


def _scan(runs: bool, digest):
    """Pieces by digest."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keep_memo_of(None)
        for b in batches:
            ids, keys, places, digests = [], [], [], []
            for d, t in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                t = t.as_py()
                if not t or "\n" not in t:
                    continue
                key = _text_key(t)
                for k, c in pieces(t, runs):
                    ids.append(d)
                    keys.append(key)
                    places.append(k)
                    digests.append(digest(c))
            yield pa.RecordBatch.from_arrays(
                [pa.array(ids, b.schema.field(0).type), pa.array(keys, pa.int64()), pa.array(places, pa.int32()), pa.array(digests, pa.binary())], ["id", "tk", "place", "h"])

    return run


def repeated(docs: DataFrame, id_col: str, text_col: str, runs: bool = False, digest=_digest) -> DataFrame:
    """(id, tk, hs): of each document, the digests and first lines of its pieces that repeat, and whether each is the first."""
    kind = docs.schema[id_col].dataType.simpleString()
    found = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).mapInArrow(_scan(runs, digest), f"id {kind}, tk long, place int, h binary")
    found = materialize(found, "line-chunks")
    first = found.groupBy("h").agg(F.count("*").alias("n"), F.min(F.struct("id", "tk", "place")).alias("first")).where("n > 1").select("h", "first")
    first = materialize(first, "line-first")  # read back, so that the join below deals both sides anew and can split a hot digest
    occ = found.join(first, "h").select("id", "tk", "place", "h", F.struct("id", "tk", "place").eqNullSafe(F.col("first")).alias("is_first"))
    return materialize(occ.groupBy("id", "tk").agg(F.collect_set(F.struct("place", "h", "is_first")).alias("hs")), "line-repeats")


def _flagged(runs: bool):
    """Text of each listed piece, once a digest and batch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            seen: dict[tuple, bytes] = {}
            for t, hs in zip(b.column("text"), b.column("hs").to_pylist(), strict=True):
                cs = dict(pieces(t.as_py(), runs))
                for x in hs:
                    raw = "\n".join(cs[x["place"]]).encode("utf-8", "replace")
                    seen[x["h"], raw] = raw
            yield pa.RecordBatch.from_arrays([pa.array([h for h, _ in seen], pa.binary()), pa.array(list(seen.values()), pa.binary())], ["h", "chunk"])

    return run


def _cut(text: str, drop: set[int], runs: bool) -> tuple[str, int, int]:
    """The text without the pieces that begin at the lines of drop, how many lines went, and how many chunks: pieces that overlap are one."""
    gone: set[int] = set()
    n_chunks = 0
    for k, c in pieces(text, runs):
        if k in drop:
            n_chunks += k not in gone
            gone.update(range(k, k + len(c)))
    return "\n".join(x for k, x in enumerate(text.split("\n")) if k not in gone), len(gone), n_chunks


COUNTS = ("__n_lines", "__cut_lines", "__cut_chunks")


def _rebuild(text_at: int, hs_at: int, runs: bool, counts: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts, n_lines, cut_lines, cut_chunks = [], [], [], []
            for t, hs in zip(b.column(text_at), b.column(hs_at), strict=True):
                t, hs = t.as_py(), hs.as_py()
                drop = {x["place"] for x in hs or () if not x["is_first"]}
                n = 0 if t is None else t.count("\n") + 1
                gone = n_chunks = 0
                if drop:
                    t, gone, n_chunks = _cut(t, drop, runs)
                texts.append(t)
                n_lines.append(n)
                cut_lines.append(gone)
                cut_chunks.append(n_chunks)
            cols = [pa.array(texts, pa.string()) if k == text_at else b.column(k) for k in range(b.num_columns) if k != hs_at]
            names = [n for k, n in enumerate(b.schema.names) if k != hs_at]
            if counts:
                cols += [pa.array(n_lines, pa.int64()), pa.array(cut_lines, pa.int64()), pa.array(cut_chunks, pa.int64())]
                names += COUNTS
            yield pa.RecordBatch.from_arrays(cols, names)

    return run


def dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", runs: bool = False, counts: bool = True, digest=_digest) -> DataFrame:
    """docs with repeated chunks cut from text_col, and (with ``counts``) columns __n_lines, __cut_lines, __cut_chunks."""
    if counts:
        docs = docs.drop(*COUNTS)
    lists = repeated(docs, id_col, text_col, runs, digest)

    @F.pandas_udf("long")
    def text_key(s):
        return s.map(_text_key, na_action=None).astype("int64")

    key, lid, ltk, lhs = (fresh(docs, n) for n in ("__key", "__id", "__tk", "__hs"))
    keyed = docs.withColumn(key, text_key(F.col(text_col)))

    def with_lists(how):
        named = lists.select(F.col("id").alias(lid), F.col("tk").alias(ltk), F.col("hs").alias(lhs))
        return keyed.hint("merge").join(named, F.col(id_col).eqNullSafe(F.col(lid)) & (F.col(key) == F.col(ltk)), how)

    texts = with_lists("inner").select(F.col(text_col).alias("text"), F.col(lhs).alias("hs")).mapInArrow(_flagged(runs), "h binary, chunk binary")
    differ = materialize(texts.groupBy("h").agg(F.min("chunk").alias("lo"), F.max("chunk").alias("hi")).where("lo <> hi").select("h"), "line-differ")
    if differ.limit(1).count():  # digests that stand for several texts, however many: their chunks all stay
        each = lists.select("id", "tk", F.explode("hs").alias("x")).withColumn("h", F.col("x.h")).join(differ, "h", "left_anti")
        lists = materialize(each.groupBy("id", "tk").agg(F.collect_set("x").alias("hs")), "line-repeats")
    joined = with_lists("left").drop(key, lid, ltk)
    names = joined.columns
    schema = docs
    for n in COUNTS if counts else ():
        schema = schema.withColumn(n, F.lit(0).cast("long"))
    return joined.mapInArrow(_rebuild(names.index(text_col), names.index(lhs), runs, counts), schema.schema)


def oracle() -> str:
    """Runs of repeated lines in documents as DuckDB SQL, comparing lines themselves: every pair of adjacent lines but its first place is cut."""
    return """
WITH d AS (SELECT doc_id, text, string_split(text, chr(10)) AS ls FROM documents),
l AS (SELECT doc_id, unnest(range(1, len(ls) + 1)) AS k, unnest(ls) AS line FROM d WHERE text IS NOT NULL),
p AS (SELECT doc_id, k, line, lead(line) OVER (PARTITION BY doc_id ORDER BY k) AS nxt FROM l),
c AS (SELECT doc_id, k, row_number() OVER (PARTITION BY line, nxt ORDER BY doc_id, k) > 1 AS drop_ FROM p WHERE nxt IS NOT NULL),
g AS (SELECT l.doc_id, l.k, line, coalesce(c.drop_, FALSE) AS begins, coalesce(c.drop_, FALSE) OR coalesce(b.drop_, FALSE) AS gone, coalesce(c.drop_, FALSE) AND NOT coalesce(b.drop_, FALSE) AS first_
  FROM l LEFT JOIN c ON c.doc_id = l.doc_id AND c.k = l.k LEFT JOIN c b ON b.doc_id = l.doc_id AND b.k = l.k - 1)
SELECT d.doc_id, coalesce(any_value(len(ls)), 0)::BIGINT AS n_lines, count(*) FILTER (gone) AS n_removed_lines, count(*) FILTER (first_) AS n_removed_chunks,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY k) FILTER (NOT gone), '')) AS kept_sha256
FROM d LEFT JOIN g ON g.doc_id = d.doc_id GROUP BY d.doc_id
"""
