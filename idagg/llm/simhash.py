"""SimHash near-duplicates by the generalised pigeonhole principle.

Fingerprint: 64 bits, each set if it is set in over half of the XXH64 values of the text's 3-word shingles. Texts link where
fingerprints differ in at most ``radius`` bits. Work is done on distinct fingerprints, so exact copies cost one row each.

Search: bits that agree together are grouped into parts, and each part gets a threshold t >= -1 such that the thresholds sum to
radius - parts + 1. Then two fingerprints within the radius agree on some part up to its threshold (-1: never asked). Dynamic
programming picks the thresholds, over several numbers of parts, that make the estimated candidates and probes fewest. Estimates
come from a bounded sample of fingerprints (``SAMPLE``) and affect cost only: every choice is exact.

Each fingerprint is sent to one bucket per part and probe; buckets above ``BUCKET`` rows are cut into blocks and each pair of blocks
meets in a task of its own. Inside a bucket all pairs are compared, but only a spanning set of links leaves it, so rows stay linear
in a bucket's size. Components then come from distributed star contraction.

Edge cases: null text counts as empty; texts without words have fingerprint zero, linked like any other; a text of one or two words
is one shingle; a null id never names a component unless all its members' ids are null; repeated rows are each returned; an empty
table gives no rows. Extra columns don't matter to ``clusters``; ``keep_one`` carries them along whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator
from math import comb

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._common import bounded_sample, components, fresh, keep_memo_of, key_change, materialize, n_parts, split_hot, whole_groups, with_field

SAMPLE, BUCKET = 4_096, 1_024
_LOWER = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")


def fingerprint(text: str | None, shingle: int = 3) -> int:
    words = (text or "").encode("utf-8", "replace").translate(_LOWER).split()  # bytes.split cuts at 0x20 and 0x09-0x0D exactly
    if not words:
        return 0
    joined = b" ".join(words)
    n = len(words) - shingle + 1
    digest = xxhash.xxh64_intdigest
    if n < 2:
        return digest(joined, 42)
    sizes = np.fromiter(map(len, words), np.int64, len(words)) + 1
    starts = np.concatenate([[0], np.cumsum(sizes)])
    h = np.array([digest(joined[a:z], 42) for a, z in zip(starts[:n].tolist(), (starts[shingle:] - 1).tolist(), strict=True)], np.uint64)
    counts = np.zeros(64, np.int64)
    for lo in range(0, n, 65_536):
        counts += np.unpackbits(h[lo : lo + 65_536].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * counts > n, bitorder="little").view(np.uint64)[0])


def fingerprints(docs: DataFrame, text_col: str = "text", out: str = "fp") -> DataFrame:
    """docs without text_col and with the fingerprint as a long."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keep_memo_of(None)
        for b in batches:
            at = b.schema.get_field_index(text_col)
            fps = np.array([fingerprint(t.as_py()) for t in b.column(at)], np.uint64).view(np.int64)
            keep = [k for k in range(b.num_columns) if k != at]
            yield pa.RecordBatch.from_arrays([*(b.column(k) for k in keep), pa.array(fps, pa.int64())], [*(b.schema.names[k] for k in keep), out])

    schema = with_field(docs.drop(text_col), out, "long")
    return docs.mapInArrow(run, schema)


def group_bits(bits: np.ndarray, parts: int) -> list[list[int]]:
    """Cut the 64 bits into parts of about equal size, correlated bits together. bits: sample x 64 of 0 and 1."""
    x = bits - bits.mean(0)
    s = np.sqrt((x * x).mean(0)) + 1e-9
    c = np.abs((x.T @ x) / max(1, len(x)) / np.outer(s, s))
    left, out = set(range(64)), []
    for k in range(parts):
        size = 64 * (k + 1) // parts - 64 * k // parts
        first = max(left, key=lambda i: (sum(c[i, j] for j in left), -i))
        part = [first]
        left.discard(first)
        while len(part) < size:
            nxt = max(left, key=lambda i: (sum(c[i, j] for j in part), -i))
            part.append(nxt)
            left.discard(nxt)
        out.append(sorted(part))
    return out


def expected_candidates(bits: np.ndarray, part: list[int], n: float, top: int) -> list[float]:
    """Estimated pairs among n fingerprints that differ in at most t bits of the part, for t = 0..top."""
    agree = (bits.mean(0) ** 2 + (1 - bits.mean(0)) ** 2)[part]
    dist = np.zeros(len(part) + 1)
    dist[0] = 1.0
    for p in agree:  # distribution of the number of differing bits, were bits independent
        dist[1:] = dist[1:] * p + dist[:-1] * (1 - p)
        dist[0] *= p
    word = (bits[:, part].astype(np.uint64) << np.arange(len(part), dtype=np.uint64)).sum(1, dtype=np.uint64)
    half = len(word) // 2
    seen = np.zeros(top + 1)
    pairs = 0
    for lag in range(1, min(half, 256) + 1):  # a bounded set of sampled pairs
        d = np.bitwise_count(word[lag:] ^ word[:-lag])
        seen += [(d <= t).sum() for t in range(top + 1)]
        pairs += len(d)
    return [max(float(dist[: t + 1].sum()), seen[t] / max(1, pairs)) * n * n / 2 for t in range(top + 1)]


def allocate(costs: list[list[float]], total: int) -> tuple[float, list[int]]:
    """Thresholds t_i >= -1 of the given sum and least cost; costs[i][t + 1] is part i's cost at t. Dynamic programming over parts."""
    best = {0: (0.0, [])}
    for c in costs:
        nxt: dict[int, tuple[float, list[int]]] = {}
        for s, (v, ts) in best.items():
            for k, w in enumerate(c):
                key = s + k - 1
                if key not in nxt or v + w < nxt[key][0]:
                    nxt[key] = (v + w, [*ts, k - 1])
        best = nxt
    return best[total]


def plan(sample: np.ndarray, n: int, radius: int, probe_cost: float = 40.0) -> list[tuple[int, int]]:
    """(mask, threshold) of each part that is asked. A probed row costs as much as probe_cost compared pairs."""
    bits = np.unpackbits(sample.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").astype(np.float64) if len(sample) else np.zeros((1, 64))
    found = []
    for parts in range(2, radius + 4):
        groups = group_bits(bits, parts)
        top = min(1, radius)
        costs = []
        for g in groups:
            e = expected_candidates(bits, g, n, top)
            costs.append([0.0, *(e[t] * sum(comb(len(g), j) for j in range(t + 1)) ** (t > 0) + probe_cost * n * sum(comb(len(g), j) for j in range(t + 1)) for t in range(top + 1))])
        total = radius - parts + 1
        if -parts <= total <= parts * top:
            cost, ts = allocate(costs, total)
            found.append((cost, parts, [(sum(1 << b for b in g), t) for g, t in zip(groups, ts, strict=True) if t >= 0]))
    return min(found)[2]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >= 1 << 63 else x


def probes(fps: DataFrame, parts: list[tuple[int, int]]) -> DataFrame:
    """(part, key, fp): a row for each part and, where its threshold is 1, each single-bit change of the part's bits."""
    keys = []
    for k, (mask, t) in enumerate(parts):
        at = F.col("fp").bitwiseAND(F.lit(_signed(mask)))
        flips = [0] + [1 << b for b in range(64) if t >= 1 and mask >> b & 1]
        keys += [F.struct(F.lit(k).alias("part"), at.bitwiseXOR(F.lit(_signed(f))).alias("key")) for f in flips]
    return fps.select("fp", F.explode(F.array(*keys)).alias("x")).select("x.part", "x.key", "fp")


def _links(radius: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in whole_groups(batches, ["part", "key", "blk"]):
            key = [t.column(c).to_numpy() for c in ("part", "key", "blk")]
            fp = t.column("fp").to_numpy().view(np.uint64)
            cuts = key_change(*key)
            group = np.repeat(np.arange(len(cuts) - 1), np.diff(cuts))
            longest = int(np.diff(cuts).max())
            up = np.arange(len(fp))  # within a group, each row's smallest linked row so far
            live = np.arange(len(fp))
            hits = []
            for lag in range(1, longest):  # rows lag apart in a group: every pair of a group meets at one lag
                live = live[: np.searchsorted(live, len(fp) - lag)]
                live = live[group[live + lag] == group[live]]
                if not len(live):
                    break
                d = np.bitwise_count(fp[live] ^ fp[live + lag])
                near = live[(d <= radius) & (d > 0)]
                if len(near):
                    hits.append((near, near + lag))
                if sum(len(h[0]) for h in hits) > 2_000_000:
                    _join(up, hits)
                    hits = []
            _join(up, hits)
            moved = np.flatnonzero(up != np.arange(len(up)))
            yield pa.RecordBatch.from_arrays([pa.array(fp[moved].view(np.int64)), pa.array(fp[up[moved]].view(np.int64))], ["a", "b"])

    return run


def _join(up: np.ndarray, hits: list) -> None:
    """Hook and shortcut until each row points to the smallest row of its class."""
    if not hits:
        return
    a, b = (np.concatenate(x) for x in zip(*hits, strict=True))
    while True:
        ra, rb = up[a], up[b]
        lo, hi = np.minimum(ra, rb), np.maximum(ra, rb)
        if (lo == hi).all():
            return
        np.minimum.at(up, hi, lo)
        while True:
            nxt = up[up]
            if (nxt == up).all():
                break
            up[:] = nxt


def links(fps: DataFrame, radius: int = 3, bucket: int = BUCKET) -> DataFrame:
    """Edges (a, b) between distinct fingerprints fp whose components are those of all pairs within the radius."""
    spark = fps.sparkSession
    n = fps.count()
    sample = np.array([r.fp for r in bounded_sample(fps.select("fp"), ["fp"], SAMPLE, 9).collect()], np.int64).view(np.uint64)
    rows = split_hot(probes(fps, plan(sample, n, radius)).distinct() if radius > 3 else probes(fps, plan(sample, n, radius)), ["part", "key"], "fp", bucket)
    return rows.repartition(n_parts(spark), "part", "key", "blk").sortWithinPartitions("part", "key", "blk", "fp").mapInArrow(_links(radius), "a long, b long")


def clusters(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", radius: int = 3, shingle: int = 3) -> DataFrame:
    """(id, fp, component_id) of every row."""
    spark = docs.sparkSession
    rows = materialize(fingerprints(docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))), "simhash")
    fps = materialize(rows.groupBy("fp").agg(F.min("id").alias("rep")), "simhash-distinct")
    cc = components(links(fps.select("fp"), radius), spark)
    named = fps.join(cc.withColumnRenamed("node", "fp"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    low = named.groupBy("root").agg(F.min("rep").alias("component_id"))
    of = named.join(low, "root").select("fp", "component_id")
    return rows.join(of, "fp").select(F.col("id").alias(id_col), "fp", "component_id")


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", radius: int = 3) -> DataFrame:
    """The rows of docs that stand for their component: its smallest id, and of rows that repeat it one. Rows with a null id stay."""
    c = clusters(docs, id_col, text_col, radius)
    own, many = fresh(docs, "__kept"), fresh(docs, "__n")
    kept = c.where(F.col(id_col).isNull() | (F.col(id_col) == F.col("component_id"))).groupBy(F.col(id_col).alias(own)).agg(F.count("*").alias(many))
    kept = materialize(kept, "simhash-kept")
    out = docs.hint("merge").join(kept, docs[id_col].eqNullSafe(kept[own]))
    repeats = (F.col(many) > 1) & F.col(own).isNotNull()
    if kept.where(repeats).limit(1).count():
        out = out.where(~repeats).unionByName(out.where(repeats).dropDuplicates([id_col]))
    return out.drop(own, many)
