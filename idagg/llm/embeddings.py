"""Near-duplicate vectors: random-hyperplane sign hashing in several tables, exact cosine verification, connected components.

Equal vectors are one row with a weight. A table's bucket is a word of ``bits`` signs; bits grow with the logarithm of the number
of vectors, so buckets keep their size, and the number of tables follows from the chance of a miss at the threshold itself
(``miss``); pairs above it are missed far less often. A pair that meets in several tables counts in the first one only, which the
vectors' own words tell, so exact link counts need no list of pairs: a bucket gives one row a vector, with its links, and one link
towards its class. Buckets above ``BUCKET`` rows are cut into blocks whose pairs meet in tasks of their own.

Edge cases: vectors that are null, empty, zero or hold null, NaN or infinite components link with nothing and stand alone; vectors of
different lengths don't link; ties and repeated vectors link (cosine 1); rows that repeat an id are vectors of their own, with the
same component; an empty table gives no rows; components may have any finite size, as vectors are scaled first. Extra columns don't matter.
"""

from __future__ import annotations

from collections.abc import Iterator
from math import acos, ceil, log, log2, pi

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._common import components, key_change, materialize, n_parts, split_hot, whole_groups

BUCKET = 1_024
FILL = 512  # vectors a bucket holds on average: more of them need fewer tables, and each table ships every vector once
MISS = 1e-5


def tables_for(n: int, threshold: float, miss: float = MISS, fill: int = FILL) -> tuple[int, int]:
    """Bits a word and number of tables for n vectors."""
    bits = max(4, min(30, round(log2(max(2, n / fill)))))
    agree = 1 - acos(threshold) / pi
    return bits, ceil(log(miss) / log(1 - agree**bits))


def _word(bits: int) -> str:
    """The smallest type that holds a word; a vector's words travel packed in it."""
    return "<u1" if bits <= 8 else "<u2" if bits <= 16 else "<u4"


def scaled(x: np.ndarray) -> np.ndarray:
    """Vectors (rows) by a power of two that brings their largest component near 1: no product over- or underflows, and no bit is lost."""
    return np.ldexp(x, -np.frexp(np.abs(x).max(-1, keepdims=True))[1])


def _hash(bits: int, tables: int, seed: int, kind: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        planes: dict[int, np.ndarray] = {}
        power = 1 << np.arange(bits, dtype=np.int64)
        for b in batches:
            vec = [scaled(np.frombuffer(v.as_py(), kind).astype(np.float64)) for v in b.column("raw")]
            words, packed = [], []
            for v in vec:
                if len(v) not in planes:
                    planes[len(v)] = np.random.default_rng([seed, len(v)]).normal(size=(tables * bits, len(v)))
                words.append((((planes[len(v)] @ v) > 0).reshape(tables, bits) @ power).astype(np.int32))
                packed.append(words[-1].astype(_word(bits)).tobytes())
            yield pa.RecordBatch.from_arrays(
                [b.column("raw"), b.column("node"), b.column("w"), pa.array([x.tolist() for x in words], pa.list_(pa.int32())), pa.array(packed, pa.binary())], ["raw", "node", "w", "words", "packed"])

    return run


def _verify(threshold: float, kind: str, bits: int, tables: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in whole_groups(batches, ["tab", "word", "dim", "blk"], 5_000):
            key = [t.column(c).to_numpy() for c in ("tab", "word", "dim", "blk")]
            cuts = key_change(*key)
            node, w, own = (t.column(c).to_numpy() for c in ("node", "w", "own"))
            raw = t.column("raw").combine_chunks()
            words = np.frombuffer(b"".join(t.column("packed").to_pylist()), _word(bits)).reshape(-1, tables)
            out: list[tuple] = []
            for a, z in zip(cuts[:-1], cuts[1:], strict=True):
                if z - a < 2:
                    continue
                x = np.stack([np.frombuffer(raw[k].as_py(), kind) for k in range(a, z)]).astype(np.float64)
                x = scaled(x)
                x = x / np.sqrt((x * x).sum(1))[:, None]
                wd, tab, of, blk = words[a:z], int(key[0][a]), own[a:z], int(key[3][a])
                links, low = np.zeros(z - a, np.int64), np.arange(z - a)
                for lo in range(0, z - a, 512):
                    c = x[lo : lo + 512] @ x.T
                    i, j = np.nonzero(c >= threshold)
                    i += lo
                    ok = i < j
                    if blk > 0:  # pairs inside a block count where the block meets itself
                        ok &= of[i] != of[j]
                    if tab:  # counted in the first table where the pair meets
                        ok &= ~(wd[i, :tab] == wd[j, :tab]).any(1)
                    i, j = i[ok], j[ok]
                    np.add.at(links, i, w[a + j])
                    np.add.at(links, j, w[a + i])
                    _hook(low, i, j)
                for k in np.flatnonzero(links):
                    out.append((node[a + k], links[k], node[a + low[k]]))
            n, l, r = zip(*out, strict=True) if out else ((), (), ())
            yield pa.RecordBatch.from_arrays([pa.array(n, pa.int64()), pa.array(l, pa.int64()), pa.array(r, pa.int64())], ["node", "links", "root"])

    return run


def _hook(up: np.ndarray, i: np.ndarray, j: np.ndarray) -> None:
    while len(i):
        a, b = up[i], up[j]
        lo, hi = np.minimum(a, b), np.maximum(a, b)
        if (lo == hi).all():
            return
        np.minimum.at(up, hi, lo)
        while (up[up] != up).any():
            up[:] = up[up]


def clusters(vectors: DataFrame, threshold: float = 0.95, id_col: str = "vec_id", vec_col: str = "embedding", miss: float = MISS, seed: int = 20) -> DataFrame:
    """(id, n_links, component_id, kept) of every row."""
    spark = vectors.sparkSession
    element = vectors.schema[vec_col].dataType.elementType.simpleString()
    kind = "<f4" if element == "float" else "<f8"  # comparisons are in double precision either way

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            raw = []
            for v in b.column("v").to_pylist():
                x = np.array([], kind) if v is None or None in v else np.array(v, kind)
                raw.append(x.tobytes() if len(x) and np.isfinite(x).all() and x.any() else None)
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array(raw, pa.binary())], ["id", "raw"])

    rows = materialize(vectors.select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).alias("v")).mapInArrow(pack, "id long, raw binary"), "vectors")
    # a node is a distinct vector; its number is fixed once the table is written
    own = rows.where("raw is not null").groupBy("raw").agg(F.count("*").alias("w"), F.min("id").alias("rep"))
    own = materialize(own.withColumn("node", F.monotonically_increasing_id()), "vectors-distinct")
    n = own.count()
    bits, tables = tables_for(n, threshold, miss)
    words = own.select("raw", "node", "w").mapInArrow(_hash(bits, tables, seed, kind), "raw binary, node long, w long, words array<int>, packed binary")
    spread = words.select("raw", "node", "w", "packed", F.length("raw").alias("dim"), F.posexplode("words").alias("tab", "word"))
    keys = ["tab", "word", "dim"]
    spread = split_hot(spread, keys, "node", BUCKET)
    found = materialize(
        spread.repartition(n_parts(spark), *keys, "blk").sortWithinPartitions(*keys, "blk", "node").mapInArrow(_verify(threshold, kind, bits, tables), "node long, links long, root long"),
        "vectors-links")
    counts = found.groupBy("node").agg(F.sum("links").alias("links"))
    cc = components(found.select(F.col("node").alias("a"), F.col("root").alias("b")), spark)
    named = own.select("raw", "node", "w", "rep").join(cc, "node", "left").join(counts, "node", "left").withColumn("root", F.coalesce("root", "node"))
    low = named.groupBy("root").agg(F.min("rep").alias("component_id"))
    of = named.join(low, "root").select(F.col("raw").alias("r2"), (F.coalesce("links", F.lit(0)) + F.col("w") - 1).alias("n"), "component_id")
    out = rows.join(of, F.col("raw") == F.col("r2"), "left")
    comp = F.coalesce("component_id", "id")
    return out.select(F.col("id").alias(id_col), F.coalesce("n", F.lit(0)).cast("long").alias("n_links"), comp.alias("component_id"), F.coalesce(F.col("id") == comp, F.lit(False)).alias("kept"))
