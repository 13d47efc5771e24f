"""Removal of every byte that lies in a string of ``length`` bytes which starts more than once in the corpus.

1. Anchors. Of each window of ``length`` bytes, the ``k``-byte string with the least hash (the rightmost of equals) is its anchor, so equal
   windows have equal anchors at equal offsets. Consecutive windows with one anchor make a snippet. A scan emits each anchor's hash, its
   snippet's digest (128 bits) and place: about one row in 170 bytes, no text.
2. Anchors that occur once anywhere rule out repeats. Snippets whose digest occurs twice repeat as a whole. What is left are snippets that
   are unique but share their anchor, as at the edges of a copied passage.
3. Texts of these and of the snippets they may share strings with, once a digest, meet by anchor. In a task, suffix arrays over the
   snippets' text after the anchor and, reversed, before it (cut into phrases, which count as symbols in byte order) put snippets with
   long common extensions next to each other; common lengths of neighbours then tell, for each offset, who shares the whole window.
4. Anchors with more than ``cap`` different snippets don't go to one task: their windows are split by offset range, ranges that are whole
   repeats or unique are settled by digest, and the windows of the rest are counted one by one, all in built-in aggregations.
5. Each document gets its list of repeated window starts and cuts their bytes.

Texts are shuffled twice (packed by Zstandard): to fetch snippets, and to cut. Equal snippets are aggregated before every shuffle.

The same search runs over words in place of bytes: ``passages`` finds places where 51 adjacent words stand in another document too, however
white space parts them. Short words make such a passage shorter than ``length`` bytes, so it's reported beside the cut, which is by bytes alone.

Edge cases: null text counts as empty; texts shorter than ``length`` keep all bytes; matches stay within a document's bytes, and
overlapping occurrences in one document count; rows that repeat id and text are documents of their own, copies of each other; null ids are
allowed; a text of one repeated byte is cut but for nothing; an empty table gives no rows. For passages, rows that repeat id and text
are one document, and what repeats within one document only doesn't count.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
import zstandard as zstd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._common import keep_memo_of, key_change, materialize, n_parts, scratch, whole_groups
from .suffix_array import suffix_array

LENGTH, ANCHOR, CAP, PHRASE = 400, 64, 512, 64
PASSAGE, PASSAGE_ANCHOR = 51, 8  # words
WORD = 8  # bytes that stand for a word
_BASE = 0x9E3779B97F4A7C15
_BYTE = np.random.default_rng(11).integers(0, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_MIX = np.uint64(0xD6E8FEB86659FD93)
_LOW = np.uint64(0xFFFFFFFF)
_POWERS: list[np.ndarray] = []
_INK = np.ones(256, bool)
_INK[[9, 10, 11, 12, 13, 32]] = False
_ZERO = np.zeros(1, np.uint64)


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse modulo 2**64."""
    if not _POWERS or len(_POWERS[0]) < n:
        m = max(1 << 16, 1 << n.bit_length())
        with np.errstate(over="ignore"):
            _POWERS[:] = [np.cumprod(np.full(m, b, np.uint64)) for b in (np.uint64(_BASE), np.uint64(pow(_BASE, -1, 1 << 64)))]
    return _POWERS[0][:n], _POWERS[1][:n]


def _prefix_hash(values: np.ndarray, up: np.ndarray) -> np.ndarray:
    """Sums of values times rising powers of the base: a run's hash is the difference of two, brought to its start by an inverse power."""
    with np.errstate(over="ignore"):
        return np.cumsum(values * up, dtype=np.uint64)


def _mixed(h: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        h ^= h >> np.uint64(31)
        h *= _MIX
        h ^= h >> np.uint64(32)
    return h


def symbols(raws: list[bytes], unit: int) -> list[bytes]:
    """Texts as symbols of ``unit`` bytes: their bytes themselves (1) or a hash of each word (8), words being what ASCII white space parts."""
    if unit == 1 or not raws:
        return raws
    x = np.frombuffer(b" ".join(raws) + b" ", np.uint8)
    edge = np.flatnonzero(np.diff(_INK[x].view(np.int8), prepend=np.int8(0)))
    start, end = edge[::2], edge[1::2]
    up, down = _powers(len(x))
    c = np.concatenate([_ZERO, _prefix_hash(_BYTE[x], up)])
    with np.errstate(over="ignore"):
        h = _mixed((c[end] - c[start]) * down[start] + (end - start).astype(np.uint64))
    cuts = np.searchsorted(start, np.cumsum([len(r) + 1 for r in raws])).tolist()  # words are in order; none crosses the blank between texts
    return [h[i:j].tobytes() for i, j in zip([0, *cuts[:-1]], cuts, strict=True)]


def anchors(raws: list[bytes], length: int = LENGTH, k: int = ANCHOR, unit: int = 1) -> list[list[tuple[int, int, int, int]]]:
    """For each sequence of symbols, (hash, place, first window, last window) of each run of windows with one anchor, counted in symbols.

    Sequences go through the arithmetic together; windows that reach from one into the next are left out."""
    sizes = np.array([len(r) // unit for r in raws], np.int64)
    n = int(sizes.sum())
    out: list[list] = [[] for _ in raws]
    if not len(raws) or sizes.max() < length:
        return out
    x = b"".join(raws)
    up, down = _powers(n)
    c = _prefix_hash(_BYTE[np.frombuffer(x, np.uint8)] if unit == 1 else np.frombuffer(x, np.uint64), up)
    with np.errstate(over="ignore"):
        h = c[k - 1 :].copy()
        h[1:] -= c[:-k]
        h *= down[: n - k + 1]
    h = _mixed(h)
    m = len(h)
    v = (h & ~_LOW) | (_LOW - np.arange(m, dtype=np.uint64))  # ties go to the rightmost
    w, span = length - k + 1, 1
    while span * 2 <= w:
        v = np.minimum(v[:-span], v[span:])
        span *= 2
    if span < w:
        v = np.minimum(v[: len(v) - (w - span)], v[w - span :])
    at = (_LOW - (v & _LOW)).astype(np.int64)
    begin = np.cumsum(sizes) - sizes
    count = np.maximum(0, sizes - length + 1)  # windows of each sequence
    of = np.repeat(np.arange(len(raws)), count)
    i = np.arange(len(of)) - np.repeat(np.cumsum(count) - count, count)
    p = at[np.repeat(begin, count) + i]
    new = np.ones(len(of), bool)
    new[1:] = (p[1:] != p[:-1]) | (of[1:] != of[:-1])
    first = np.flatnonzero(new)
    last = np.append(first[1:], len(of)) - 1
    of, p = of[first], p[first]
    for d, *row in zip(of.tolist(), h[p].view(np.int64).tolist(), (p - begin[of]).tolist(), i[first].tolist(), i[last].tolist(), strict=True):
        out[d].append(tuple(row))
    return out


TOGETHER = {1: 1 << 14, WORD: 1 << 16}  # bytes of text that go through the arithmetic at once, so that it stays in a core's cache


def _together(column: pa.Array, most: int) -> Iterator[tuple[int, list[bytes]]]:
    """(place of the first, texts as bytes): neighbours of ``most`` bytes or little more, a longer text alone."""
    held, size, lo = [], 0, 0
    for k, t in enumerate(column):
        raw = (t.as_py() or "").encode("utf-8", "replace")
        if held and size + len(raw) > most:
            yield lo, held
            held, size, lo = [], 0, k
        held.append(raw)
        size += len(raw)
    if held:
        yield lo, held


def text_key(raw: bytes) -> int:
    return xxhash.xxh3_64_intdigest(raw) - (1 << 63)


def _two(d: bytes) -> tuple[int, int]:
    return int.from_bytes(d[:8], "little", signed=True), int.from_bytes(d[8:], "little", signed=True)


def _scan(length: int, k: int, unit: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keep_memo_of(None)
        for b in batches:
            rows: list[tuple] = []
            ids: list = []
            names = b.column(0).to_pylist()
            for lo_, raws in _together(b.column(1), TOGETHER[unit]):
                encoded = symbols(raws, unit)
                for d, raw, x, found in zip(names[lo_ : lo_ + len(raws)], raws, encoded, anchors(encoded, length, k, unit), strict=True):
                    if not found:
                        continue
                    tk = text_key(raw)
                    own: dict[tuple, list] = {}
                    for h, p, i, j in found:
                        own.setdefault((h, xxhash.xxh3_128_digest(x[i * unit : (j + length) * unit]), p - j, p - i), []).append(p)
                    for (h, s, lo, hi), places in own.items():
                        ids.append(d)
                        rows.append((tk, h, *_two(s), lo, hi, places))
            cols = list(zip(*rows, strict=True)) or [()] * 7
            kinds = [pa.int64()] * 4 + [pa.int16()] * 2 + [pa.list_(pa.int32())]
            yield pa.RecordBatch.from_arrays(
                [pa.array(ids, b.schema.field(0).type), *(pa.array(c, t) for c, t in zip(cols, kinds, strict=True))], ["id", "tk", "h", "s1", "s2", "lo", "hi", "at"])

    return run


def _packed(docs: DataFrame, kind: str) -> DataFrame:
    """(id, tk, z): texts packed for a shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        comp = zstd.ZstdCompressor(level=3)
        for b in batches:
            raw = [(t.as_py() or "").encode("utf-8", "replace") for t in b.column(1)]
            yield pa.RecordBatch.from_arrays(
                [b.column(0), pa.array([text_key(r) for r in raw], pa.int64()), pa.array([comp.compress(r) for r in raw], pa.binary())], ["id", "tk", "z"])

    return docs.mapInArrow(run, f"id {kind}, tk long, z binary")


def _snippets(length: int, unit: int):
    """Symbols before and after the anchor of each listed snippet."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keep_memo_of(None)
        un = zstd.ZstdDecompressor()
        for b in batches:
            ids, out = [], []
            for d, tk, z, want in zip(b.column("id").to_pylist(), b.column("tk").to_pylist(), b.column("z"), b.column("want").to_pylist(), strict=True):
                raw = symbols([un.decompress(z.as_py())], unit)[0]
                for w in want:
                    p = w["p"]
                    ids.append(d)
                    out.append((
                        tk, w["h"], p, w["lo"], w["hi"], w["once"], w["hot"], raw[(p - w["hi"]) * unit : p * unit], raw[p * unit : (p - w["lo"] + length) * unit]))
            cols = list(zip(*out, strict=True)) or [()] * 9
            kinds = [pa.int64(), pa.int64(), pa.int32(), pa.int16(), pa.int16(), pa.bool_(), pa.bool_(), pa.binary(), pa.binary()]
            yield pa.RecordBatch.from_arrays(
                [pa.array(ids, b.schema.field("id").type), *(pa.array(c, t) for c, t in zip(cols, kinds, strict=True))], ["id", "tk", "h", "p", "lo", "hi", "once", "hot", "l", "r"])

    return run


def order_by_suffix(strings: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """The strings' order, by a suffix array over all of them, and the common length of each with the one before it (zero-padded)."""
    n = len(strings)
    width = max(1, -(-max(map(len, strings), default=1) // PHRASE)) * PHRASE
    m = np.frombuffer(b"".join(s.ljust(width, b"\0") for s in strings), np.uint8).reshape(n, width)
    count = np.array([-(-len(s) // PHRASE) for s in strings])
    phrases = m.reshape(n, width // PHRASE, PHRASE)[np.arange(width // PHRASE)[None] < count[:, None]]
    ranks = np.unique(phrases.copy().view(">u8").reshape(len(phrases), -1), axis=0, return_inverse=True)[1].ravel() + 1 if len(phrases) else np.zeros(0, int)
    starts = np.concatenate([[0], np.cumsum(count + 1)])[:-1]
    text = np.zeros(int(count.sum()) + n, np.int64)  # 0 ends a string
    inside = np.ones(len(text), bool)
    inside[starts + count] = False
    text[inside] = ranks
    which = np.full(len(text), -1)
    which[starts] = np.arange(n)
    o = which[np.array(suffix_array(text.tolist()), np.int64)]
    o = o[o >= 0]
    common = np.zeros(n, np.int64)
    for a in range(1, n, 4096):
        z = min(n, a + 4096)
        differ = m[o[a:z]] != m[o[a - 1 : z - 1]]
        common[a:z] = np.where(differ.any(1), differ.argmax(1), width)
    return o, common


def shared_windows(left: list[bytes], right: list[bytes], lo: np.ndarray, hi: np.ndarray, group: np.ndarray, length: int, unit: int = 1,
                   owner: np.ndarray | None = None) -> list[np.ndarray]:
    """For each snippet, the offsets x of its anchor in windows that another snippet of its group (of another owner, if owners are given) has
    too.

    left ends at the anchor, right begins with it; lo and hi bound x."""
    n = len(left)
    found: list[list[int]] = [[] for _ in range(n)]
    sides = []
    for strings in (right, [s[::-1] for s in left]):
        o, common = order_by_suffix(strings)
        back = np.empty(n, np.int64)
        back[o] = np.arange(n)
        sides.append((back, common))
    (br, cr), (bl, cl) = sides
    for x in range(int(lo.min()), int(hi.max()) + 1):
        live = np.flatnonzero((lo <= x) & (x <= hi))
        if len(live) < 2:
            continue
        r = np.cumsum(cr < (length - x) * unit)[br[live]]  # equal for those that share length - x symbols from the anchor on
        s = np.cumsum(cl < x * unit)[bl[live]] if x else np.zeros(len(live), np.int64)
        key = r * (n + 1) + s
        by = np.lexsort((key, group[live]))
        k, g = key[by], group[live][by]
        new = np.ones(len(by), bool)
        new[1:] = (k[1:] != k[:-1]) | (g[1:] != g[:-1])
        first = np.flatnonzero(new)
        if owner is None:
            many = np.diff(np.append(first, len(by))) > 1
        else:
            o = owner[live][by]
            many = np.minimum.reduceat(o, first) != np.maximum.reduceat(o, first)
        for i in live[by[many[np.cumsum(new) - 1]]]:
            found[i].append(x)
    return [np.array(f, np.int64) for f in found]


def _runs(x: np.ndarray) -> list[tuple[int, int]]:
    cut = np.flatnonzero(np.diff(x) != 1) + 1
    return [(int(c[0]), int(c[-1])) for c in np.split(x, cut)] if len(x) else []


def _solve(length: int, unit: int, across: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in whole_groups(batches, ["h"], 8_192):
            once = t.column("once").to_numpy(zero_copy_only=False)
            h = t.column("h").to_numpy()
            cuts = key_change(h)
            group = np.repeat(np.arange(len(cuts) - 1), np.diff(cuts))
            open_ = np.zeros(len(cuts) - 1, bool)
            open_[group[once]] = True  # groups where each snippet repeats as a whole are settled
            keep = np.flatnonzero(open_[group] & (np.diff(cuts)[group] > 1))
            ids, out = [], []
            if len(keep):
                s = t.take(pa.array(keep))
                lo, hi = s.column("lo").to_numpy().astype(np.int64), s.column("hi").to_numpy().astype(np.int64)
                owner = s.column("owner").to_numpy() if across else None
                got = shared_windows(s.column("l").to_pylist(), s.column("r").to_pylist(), lo, hi, group[keep], length, unit, owner)
                tk, p, of = s.column("tk").to_numpy(), s.column("p").to_numpy(), s.column("id").to_pylist()
                for i in np.flatnonzero(once[keep]):
                    for a, z in _runs(got[i]):
                        ids.append(of[i])
                        out.append((int(tk[i]), int(p[i]) - z, int(p[i]) - a))
            cols = list(zip(*out, strict=True)) or [()] * 3
            yield pa.RecordBatch.from_arrays(
                [pa.array(ids, t.schema.field("id").type), *(pa.array(c, k) for c, k in zip(cols, (pa.int64(), pa.int32(), pa.int32()), strict=True))], ["id", "tk", "first", "last"])

    return run


def _owner(across: bool):
    """What must differ between two occurrences: the document (id and text), or nothing. A snippet that stands in several documents has an
    owner of its own, unlike that of the document which represents it."""
    own = F.xxhash64("id", "tk")
    return F.when(F.col("once"), own).otherwise(F.bitwise_not(own)) if across else F.lit(0).cast("long")


def _hot(rows: DataFrame, length: int, unit: int, across: bool, step: int = 24) -> DataFrame:
    """(id, tk, first, last) for snippets of anchors that are too common for one task."""
    n = -(-(length + 1) // step)
    parts = F.filter(
        F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda r: F.struct(
            (r * step).alias("x0"), (r * step + step - 1).alias("x1"),
            F.greatest(F.col("lo").cast("int"), r * step).alias("a"), F.least(F.col("hi").cast("int"), r * step + step - 1).alias("z"))),
        lambda c: c["a"] <= c["z"])
    own = ["id", "tk", "owner", "h", "p", "once", "l", "r"]
    d = rows.select(*own, F.explode(parts).alias("c")).select(*own, "c.*")

    def before(x):
        return f"substring(l, length(l) - {x} * {unit} + 1, {x} * {unit})"

    def after(x):
        return f"substring(r, 1, greatest({length} - {x}, 0) * {unit})"

    d = d.select(
        "id", "tk", "owner", "h", "p", "once", "x0", "a", "z", F.expr(before("z")).alias("l"), F.expr(after("a")).alias("r"),
        F.expr(f"md5(concat({before('x0')}, {after('x1')}))").alias("core"))
    d = d.withColumn("whole", F.expr("md5(concat(cast(cast(a as string) as binary), cast('/' as binary), l, r))"))
    same = d.groupBy("h", "x0", "core", "whole").agg(
        F.count("*").alias("n"), F.min("owner").alias("o1"), F.max("owner").alias("o2"), F.first("id").alias("id"), F.first("tk").alias("tk"), F.first("p").alias("p"),
        F.max("once").alias("once"), F.first("a").alias("a"), F.first("z").alias("z"), F.first("l").alias("l"), F.first("r").alias("r"))
    same = materialize(same, "repeats-hot")
    # with owners, two rows of a range settle it where they are of two documents; rows of one document that are alike stay open as one
    many = F.col("o1") != F.col("o2") if across else F.col("n") > 1
    multi = same.groupBy("h", "x0", "core").agg(F.count("*").alias("m")).where("m > 1")
    settled = d.select("id", "tk", "h", "p", "once", "x0", "core", "whole", "a", "z").join(
        same.where(many).select("h", "x0", "core", "whole"), ["h", "x0", "core", "whole"], "left_semi").where("once").select(
        "id", "tk", (F.col("p") - F.col("z")).cast("int").alias("first"), (F.col("p") - F.col("a")).cast("int").alias("last"))
    if across:  # all places of a document in an open range, not one that stands for them
        open_ = d.join(same.where(~many).select("h", "x0", "core", "whole"), ["h", "x0", "core", "whole"], "left_semi")
        open_ = open_.withColumns({"o1": F.col("owner"), "o2": F.col("owner")}).drop("owner")
        same = open_.unionByName(same.where(many).drop("n").withColumn("once", F.lit(False)).select(*open_.columns))
    each = same.join(multi, ["h", "x0", "core"]).select(
        "id", "tk", "o1", "o2", "h", "p", (F.col("once") & ~many).alias("once"), "l", "r", "a", "z", F.explode(F.sequence("a", "z")).alias("x"))
    each = each.select("id", "tk", "o1", "o2", "p", "once", "h", "x", F.expr(f"md5(concat({before('x')}, {after('x')}))").alias("w"))
    seen = each.groupBy("h", "x", "w").agg(F.count("*").alias("n"), F.min("o1").alias("o1"), F.max("o2").alias("o2"))
    again = seen.where(many).select("h", "x", "w")
    single = each.where("once").join(again, ["h", "x", "w"], "left_semi").select(
        "id", "tk", (F.col("p") - F.col("x")).cast("int").alias("first"), (F.col("p") - F.col("x")).cast("int").alias("last"))
    return settled.union(single)


def repeated_starts(docs: DataFrame, length: int = LENGTH, k: int = ANCHOR, cap: int = CAP, unit: int = 1, across: bool = False) -> DataFrame:
    """(id, tk, first, last): runs of starts of windows that occur more than once; with ``across``, in another document. docs: id, text."""
    spark = docs.sparkSession
    kind = docs.schema["id"].dataType.simpleString()
    found = materialize(docs.mapInArrow(_scan(length, k, unit), f"id {kind}, tk long, h long, s1 long, s2 long, lo short, hi short, at array<int>"), "repeats-anchors")
    n, who = F.size("at"), F.struct("id", "tk")
    often = found.groupBy("h").agg(
        F.sum(n).alias("n"), F.min("s1").alias("a1"), F.max("s1").alias("z1"), F.min("s2").alias("a2"), F.max("s2").alias("z2"),
        *([F.min(who).alias("d1"), F.max(who).alias("d2")] if across else [])).where(F.expr("not (d1 <=> d2)" if across else "n > 1"))
    often = often.select("h", ((F.col("a1") != F.col("z1")) | (F.col("a2") != F.col("z2"))).alias("many"))
    often = materialize(often, "repeats-often")  # read back, so that the join deals both sides anew and can split a hot anchor
    shared = materialize(found.join(often, "h"), "repeats-shared")
    kinds = shared.groupBy("h", "s1", "s2").agg(
        F.sum(n).alias("n"), F.max("many").alias("many"), F.min(F.struct("id", "tk", "at", "lo", "hi")).alias("rep"), F.min(who).alias("d1"), F.max(who).alias("d2"))
    kinds = materialize(kinds.withColumn("once", F.expr("d1 <=> d2" if across else "n = 1")).drop("d1", "d2", "n"), "repeats-kinds")
    whole = shared.join(kinds.where("not once").select("h", "s1", "s2"), ["h", "s1", "s2"], "left_semi").select(
        "id", "tk", F.explode("at").alias("p"), "lo", "hi").select("id", "tk", (F.col("p") - F.col("hi")).cast("int").alias("first"), (F.col("p") - F.col("lo")).cast("int").alias("last"))
    groups = kinds.where("many").groupBy("h").agg(F.count("*").alias("m"), F.max("once").alias("open")).where("open").select("h", (F.col("m") > cap).alias("hot"))
    groups = materialize(groups, "repeats-groups")
    places = F.when(F.col("once"), F.col("rep.at")).otherwise(F.slice("rep.at", 1, 1))  # one place stands for a snippet that is settled
    want = kinds.where("many").join(groups, "h").withColumn("p", F.explode(places)).select(
        "rep.id", "rep.tk", F.struct("h", "p", F.col("rep.lo").alias("lo"), F.col("rep.hi").alias("hi"), "once", "hot").alias("w"))
    want = want.groupBy("id", "tk").agg(F.collect_list("w").alias("want"))
    texts = _packed(docs, kind).withColumnsRenamed({"id": "id0", "tk": "tk0"})
    snips = texts.hint("merge").join(want, F.col("id").eqNullSafe(F.col("id0")) & (F.col("tk") == F.col("tk0"))).select("id", "tk", "z", "want")
    snips = materialize(snips.mapInArrow(
        _snippets(length, unit), f"id {kind}, tk long, h long, p int, lo short, hi short, once boolean, hot boolean, l binary, r binary"), "repeats-snippets").withColumn("owner", _owner(across))
    cold = snips.where("not hot").repartition(n_parts(spark), "h").sortWithinPartitions("h", "id", "tk", "p").mapInArrow(
        _solve(length, unit, across), f"id {kind}, tk long, first int, last int")
    return whole.union(cold).union(_hot(snips.where("hot"), length, unit, across))


def passages(docs: DataFrame, words: int = PASSAGE, k: int = PASSAGE_ANCHOR, cap: int = CAP) -> DataFrame:
    """(id, tk, first, last): runs of places where ``words`` adjacent words begin that stand in another document too. docs: id, text."""
    with scratch(docs.sparkSession):
        return materialize(repeated_starts(docs, words, min(k, words), cap, WORD, True), "repeats-passages", keep=True)


def cut(raw: bytes, runs: list[tuple[int, int]], length: int = LENGTH) -> tuple[bytes, int, int]:
    """What is left of raw, bytes removed and maximal removed runs. runs: (first, last) starts of repeated windows."""
    kept, end, spans, gone = [], 0, 0, 0
    for a, z in sorted(runs):
        z += length
        if a > end or not spans:
            kept.append(raw[end:a])
            spans += 1
            gone += z - a
            end = z
        elif z > end:
            gone += z - end
            end = z
    kept.append(raw[end:])
    return b"".join(kept), gone, spans


def covered(runs: list[tuple[int, int]], length: int) -> int:
    """Symbols that lie in windows which begin in the runs."""
    n = end = 0
    for a, z in sorted(runs):
        n += max(0, z + length - max(a, end))
        end = max(end, z + length)
    return n


def dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", length: int = LENGTH, k: int = ANCHOR, cap: int = CAP, words: int = 0) -> DataFrame:
    """(id, kept binary, n_bytes, n_removed, n_spans, n_passage_words) of every row.

    n_passage_words: words of the whole text that lie in passages of at least ``words`` words which stand in another document too; 0 where
    ``words`` is 0. They aren't cut."""
    d = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    kind = d.schema["id"].dataType.simpleString()
    by_words = passages(d, words, cap=cap) if words else None
    runs = repeated_starts(d, length, k, cap).withColumn("words", F.lit(False))
    if words:
        runs = runs.union(by_words.withColumn("words", F.lit(True)))
    runs = runs.groupBy("id", "tk").agg(F.collect_set(F.struct("words", "first", "last")).alias("runs"))
    texts = _packed(d, kind).withColumnsRenamed({"id": "id0", "tk": "tk0"})
    both = texts.hint("merge").join(runs, F.col("id").eqNullSafe(F.col("id0")) & (F.col("tk") == F.col("tk0")), "left").select("id0", "z", "runs")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        un = zstd.ZstdDecompressor()
        for b in batches:
            rows = []
            for z, r in zip(b.column("z"), b.column("runs"), strict=True):
                raw = un.decompress(z.as_py())
                own: tuple[list, list] = ([], [])
                for x in r.as_py() or ():
                    own[x["words"]].append((x["first"], x["last"]))
                rows.append((*cut(raw, own[0], length), len(raw), covered(own[1], words)))
            kept, gone, spans, size, passage = zip(*rows, strict=True) if rows else ((),) * 5
            yield pa.RecordBatch.from_arrays(
                [b.column("id0"), pa.array(kept, pa.binary()), *(pa.array(c, pa.int64()) for c in (size, gone, spans, passage))],
                ["id", "kept", "n_bytes", "n_removed", "n_spans", "n_passage_words"])

    return both.mapInArrow(run, f"id {kind}, kept binary, n_bytes long, n_removed long, n_spans long, n_passage_words long").withColumnRenamed("id", id_col)
