"""Plumbing that the corpus operators share: table access, shared-folder tables, Arrow grouping, connected components."""

from __future__ import annotations

import atexit
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

_ROOTS: dict[str, str] = {}
_MEMOS: dict[str, Callable[[], None]] = {}
_SCRATCH: list[list[str]] = []


def owns_memo(name: str, clear: Callable[[], None]) -> None:
    """Say how to empty the memo that a module keeps in each Python worker."""
    _MEMOS[name] = clear


def keep_memo_of(name: str | None) -> None:
    """Workers outlive stages: when a task begins, the memos of all operators but this one are emptied and their memory given back."""
    for k, clear in _MEMOS.items():
        if k != name:
            clear()
    try:
        import ctypes

        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library: it keeps what it keeps
        pass


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def fresh(df: DataFrame, name: str) -> str:
    """A column name that df doesn't have yet: name, or name with underscores."""
    have = {c.lower() for c in df.columns}
    while name.lower() in have:
        name += "_"
    return name


def with_field(df: DataFrame, name: str, kind: str) -> StructType:
    """The schema of df and one more field; df's own schema object is left alone."""
    return StructType([*df.schema.fields, StructType.fromDDL(f"{name} {kind}").fields[0]])


def bounded_sample(df: DataFrame, keys: list[str], k: int, seed: int = 0) -> DataFrame:
    """At most k rows of df, those whose keys hash lowest, with the hash in column __o.

    Rows are counted first and only those below a hash that about 3 k / 2 rows stay under are sorted, so what reaches the one sorting
    task doesn't grow with the table."""
    n = df.count()
    out = df.withColumn("__o", F.xxhash64(*keys, F.lit(seed)))
    if n > 2 * k:
        out = out.where(F.pmod(F.col("__o"), F.lit(1 << 31)) < int((1 << 31) * 1.5 * k / n) + 1)
    return out.orderBy(F.pmod("__o", F.lit(1 << 31)), "__o", *keys).limit(k)


def n_parts(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def shared_root(spark: SparkSession) -> str:
    """A folder of this application's own below spark.checkpoint.dir; a local one is chosen only where that is unset."""
    app = spark.sparkContext.applicationId
    if app not in _ROOTS:
        base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
        if not base:
            if not spark.sparkContext.master.startswith("local["):
                raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
            base = "file:///tmp/checkpoints/idagg"  # one machine: tests
        _ROOTS[app] = f"{base.rstrip('/')}/idagg-{app}-{uuid.uuid4().hex[:8]}"
        atexit.register(_forget, spark, _ROOTS[app])
    return _ROOTS[app]


def _forget(spark: SparkSession, root: str) -> None:
    try:
        path = spark._jvm.org.apache.hadoop.fs.Path(root)
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
    except Exception:  # noqa: BLE001  the session may be gone at exit; the folder is then the cluster's to clear
        pass


@contextmanager
def scratch(spark: SparkSession) -> Iterator[None]:
    """Tables that are materialized inside are deleted at the end, but those with keep=True, which must not be read from the others later."""
    _SCRATCH.append([])
    try:
        yield
    finally:
        for path in _SCRATCH.pop():
            _forget(spark, path)


def materialize(df: DataFrame, name: str, keep: bool = False) -> DataFrame:
    """Write df as Parquet into the shared folder and read it back: lineage ends there and survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_root(spark)}/{name}-{uuid.uuid4().hex[:8]}"
    if _SCRATCH and not keep:
        _SCRATCH[-1].append(path)
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def whole_groups(batches: Iterator[pa.RecordBatch], keys: list[str], least: int = 50_000) -> Iterator[pa.Table]:
    """Regroup a key-sorted stream of Arrow batches into tables that never cut a key in two.

    A table holds at least ``least`` rows unless the stream ends; a key's rows are bounded by the caller, which splits hot keys.
    """
    held: list[pa.RecordBatch] = []
    rows = 0
    for b in batches:
        if b.num_rows == 0:
            continue
        held.append(b)
        rows += b.num_rows
        if rows < least:
            continue
        t = pa.Table.from_batches(held).combine_chunks()
        cut = _last_key_start(t, keys)
        if cut:
            yield t.slice(0, cut)
        rest = t.slice(cut)
        held, rows = pa.Table.to_batches(rest.combine_chunks()), rest.num_rows
    if held:
        yield pa.Table.from_batches(held).combine_chunks()


def _last_key_start(t: pa.Table, keys: list[str]) -> int:
    last = t.num_rows - 1
    tail = [t.column(k)[last].as_py() for k in keys]
    lo, hi = 0, last  # the first row of the last key, by bisection over the sorted rows
    while lo < hi:
        mid = (lo + hi) // 2
        if [t.column(k)[mid].as_py() for k in keys] == tail:
            hi = mid
        else:
            lo = mid + 1
    return lo


def key_change(*cols: np.ndarray) -> np.ndarray:
    """Starts of runs of equal keys, and the end."""
    n = len(cols[0])
    new = np.zeros(n, bool)
    new[0] = True
    for c in cols:
        new[1:] |= c[1:] != c[:-1]
    return np.append(np.flatnonzero(new), n)


class UnionFind:
    """Over 0..n-1; the root of a class is its smallest member."""

    def __init__(self, n: int):
        self.up = list(range(n))

    def root(self, x: int) -> int:
        up = self.up
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    def join(self, a: int, b: int) -> None:
        a, b = self.root(a), self.root(b)
        if a != b:
            if a < b:
                self.up[b] = a
            else:
                self.up[a] = b


def split_hot(df: DataFrame, keys: list[str], payload: str, cap: int) -> DataFrame:
    """Give every bucket of more than ``cap`` rows several tasks: its rows are hashed to blocks (column own) and each pair of
    blocks becomes a group of its own (column blk), so each pair of rows still meets. blk is 0 in other buckets, negative where a
    block meets itself, positive where two blocks meet (their rows differ in own)."""
    hot = (
        df.groupBy(*keys).count().where(F.col("count") > cap)
        .select(*keys, F.ceil(F.col("count") / F.lit(cap)).cast("int").alias("__nb"))
    )
    d = df.join(hot, keys, "left").withColumn("own", F.expr(f"cast(pmod(xxhash64({payload}, 7), coalesce(__nb, 1)) as int)"))
    nb, b = F.col("__nb"), F.col("own")
    many = F.transform(
        F.sequence(F.lit(0), nb - 1),
        lambda j: F.when(j == b, -b - 1).otherwise(F.least(j, b) * nb + F.greatest(j, b) + 1).cast("int"),
    )
    return d.withColumn("blk", F.explode(F.when(nb.isNull(), F.array(F.lit(0))).otherwise(many))).drop("__nb")


def components(edges: DataFrame, spark: SparkSession) -> DataFrame:
    """Connected components of edges (a, b) by alternating large-star and small-star steps.

    Returns (node, root) with root the smallest node reachable, for each node that has an edge. Both steps aggregate a
    minimum before anything is shuffled, and rows never exceed one an edge, so a hub costs no more than its edges.
    """
    e = edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()
    e = materialize(e, "cc")
    while True:
        # done when each node points to one other that points to none; that is exact, whatever the numbers
        ends = e.select(F.col("u").alias("x"), F.lit(1).alias("up"), F.lit(0).alias("root")).union(e.select("v", F.lit(0), F.lit(1)))
        open_ = ends.groupBy("x").agg(F.sum("up").alias("up"), F.max("root").alias("root")).where("up > 1 or up = 1 and root = 1")
        if not open_.limit(1).count():
            return e.select(F.col("u").alias("node"), F.col("v").alias("root")).union(
                e.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())
        both = e.select("u", "v").union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = (
            both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        )
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).union(low.select("u", F.col("m").alias("v")))
        e = materialize(small.where("u <> v").distinct(), "cc")
