"""Register states: built, merged, rolled up, packed.

A state is a sparse relation (keys, j, r) with one row for each register that isn't empty, or m bytes. Building is a maximum by (keys, j):
partial maxima are taken before the shuffle, so a task sends at most m rows a state however many records it reads, a hot stream spreads over
m keys, and repeats need no deduplication.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from idagg.functions.hashing import hash64, index_rank
from idagg.spec import DEFAULT_P

PARTIAL_KEYS = 4_096  # dense states that a task holds before it sends them on


def with_registers(records: DataFrame, p: int = DEFAULT_P, seed: int = 0, family: str = "md5", identity: str = "identity") -> DataFrame:
    """records with columns j and r; those without identity are dropped. The hash is computed once."""
    d = records.where(F.col(identity).isNotNull()).withColumn("__h", hash64(F.col(identity).cast("string"), seed, family))
    j, r = index_rank(F.col("__h"), p)
    return d.withColumn("j", j).withColumn("r", r).drop("__h")


def build_registers(records: DataFrame, keys: list[str], p: int = DEFAULT_P, seed: int = 0, family: str = "md5", identity: str = "identity") -> DataFrame:
    return merge_registers(with_registers(records.select(*keys, identity), p, seed, family, identity), keys)


def merge_registers(regs: DataFrame, keys: list[str]) -> DataFrame:
    """One state a key from any number of them: the maximum of each register."""
    return regs.groupBy(*keys, "j").agg(F.max("r").alias("r"))


def coarser(k: int) -> tuple[Column, Column]:
    """(j, r) under k bits of index less, from j and r: the bits that leave the index lead the rest, so the maximum over registers is the same
    as from identities."""
    low = F.col("j").bitwiseAND(F.lit((1 << k) - 1))
    return F.shiftright("j", k), F.when(low == 0, F.col("r") + k).otherwise(F.lit(k + 1) - F.length(F.bin(low))).cast("int")


def update_states(stored: DataFrame, records: DataFrame, keys: list[str], **how) -> DataFrame:
    return merge_registers(stored.select(*keys, "j", "r").unionByName(build_registers(records, keys, **how)), keys)


def rollup_states(regs: DataFrame, keys: list[str], sets: str = "rollup") -> DataFrame:
    """States of coarser groups (rollup or cube of keys) from the finest ones, with grouping_id."""
    n = len(keys)
    kept = [keys[:k] for k in range(n, -1, -1)] if sets == "rollup" else [[k for i, k in enumerate(keys) if c >> i & 1] for c in range(1 << n)]
    return regs.groupingSets([["j", *k] for k in kept], "j", *keys).agg(F.max("r").alias("r"), F.grouping_id("j", *keys).alias("gid"))


def pack(regs: DataFrame, keys: list[str], p: int = DEFAULT_P) -> DataFrame:
    """(keys, state): m bytes, one a register, from the sparse rows of each key."""
    m = 1 << p
    got = regs.groupBy(*keys).agg(F.array_sort(F.collect_list(F.struct("j", "r"))).alias("__a"))

    def digits(x, i):
        """Two for this register, after a zero byte for each empty one since the register before."""
        gap = x["j"] - F.coalesce(F.get("__a", i - 1)["j"], F.lit(-1)) - 1
        return F.concat(F.repeat(F.lit("00"), gap.cast("int")), F.lpad(F.hex(x["r"].cast("long")), 2, "0"))

    return got.select(*keys, F.unhex(F.rpad(F.array_join(F.transform("__a", digits), ""), 2 * m, "0")).alias("state"))


def unpack(states: DataFrame, keys: list[str], p: int = DEFAULT_P, state: str = "state") -> DataFrame:
    """(keys, j, r) of dense states; empty registers have no row."""
    one = lambda k: F.substring(F.col(state), k + 1, F.lit(1))  # noqa: E731  a byte: cutting binary doesn't count characters from the start
    full = F.filter(F.sequence(F.lit(0), F.lit((1 << p) - 1)), lambda k: one(k) != F.lit(b"\0"))
    at = F.transform(full, lambda k: F.struct(k.alias("j"), F.conv(F.hex(one(k)), 16, 10).cast("int").alias("r")))
    return states.select(*keys, F.explode(at).alias("x")).select(*keys, "x.j", "x.r")


def merge_dense(states: DataFrame, keys: list[str], state: str = "state") -> DataFrame:
    """One dense state a key: the byte-wise maximum of any number of them.

    A task first merges what it holds, a bounded number of keys at a time, so repeats of a hot key shrink before they are shuffled. After
    the shuffle a key's states stand next to each other (sorted), so each key is emitted once, when the next one begins, however many keys
    a task has; one state is held at a time. Keys may be null; without keys all states merge to one."""
    import numpy as np
    import pyarrow as pa

    d = states.select(*keys, state)
    schema = d.schema

    def emit(rows: list[list]):
        from pyspark.sql.pandas.types import to_arrow_schema

        arrow = to_arrow_schema(schema)
        return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), arrow, strict=True)], schema=arrow)

    def read(batches):
        for b in batches:
            for *k, s in zip(*(c.to_pylist() for c in b.columns), strict=True):
                yield tuple("nan" if x != x else x for x in k), k, np.frombuffer(s, np.uint8)

    def partial(batches):
        best: dict[tuple, list] = {}
        for key, k, v in read(batches):
            if key in best:
                best[key][-1] = np.maximum(best[key][-1], v)
            else:
                best[key] = [*k, v]
            if len(best) >= PARTIAL_KEYS:
                yield emit([[*k, v.tobytes()] for *k, v in best.values()])
                best = {}
        if best:
            yield emit([[*k, v.tobytes()] for *k, v in best.values()])

    def final(batches):
        now, row, out = None, None, []
        for key, k, v in read(batches):
            if row is not None and key == now:
                row[-1] = np.maximum(row[-1], v)
                continue
            if row is not None:
                out.append([*row[:-1], row[-1].tobytes()])
            now, row = key, [*k, v]
            if len(out) >= PARTIAL_KEYS:
                yield emit(out)
                out = []
        if row is not None:
            yield emit([*out, [*row[:-1], row[-1].tobytes()]])

    first = d.mapInArrow(partial, schema)
    dealt = first.repartition(*keys).sortWithinPartitions(*keys) if keys else first.coalesce(1)
    return dealt.mapInArrow(final, schema)


def register_mismatches(a: DataFrame, b: DataFrame, keys: list[str]) -> DataFrame:
    """(keys, mismatches): registers that differ between two states of each key."""
    x = a.select(*keys, "j", F.col("r").alias("__a"), F.lit(0).alias("__b"))
    y = b.select(*keys, "j", F.lit(0).alias("__a"), F.col("r").alias("__b"))
    both = x.unionByName(y).groupBy(*keys, "j").agg(F.max("__a").alias("__a"), F.max("__b").alias("__b"))
    return both.groupBy(*keys).agg(F.sum((F.col("__a") != F.col("__b")).cast("long")).alias("mismatches"))


def merge_in_order(segments: DataFrame, keys: list[str], order: str = "left", fan: int = 2, segment: str = "segment_id") -> DataFrame:
    """The same merge in a stated order of segments: left (rising), reversed, or by levels of a tree of the given fan-in.

    Segment numbers are dense from 0; levels and folds are group-bys on halved numbers, not loops over segments."""
    d = segments.select(*keys, F.col(segment).alias("__s"), "j", "r")
    top = d.agg(F.max("__s")).first()[0] or 0
    if order == "reversed":
        d = d.withColumn("__s", F.lit(top) - F.col("__s"))
    width = fan if order == "tree" else max(2, top // 4 + 1)
    while top > 0:
        d = d.withColumn("__s", F.floor(F.col("__s") / width).cast("int")).groupBy(*keys, "__s", "j").agg(F.max("r").alias("r"))
        top //= width
    return d.drop("__s")


def fold_states(states: list[DataFrame], keys: list[str]) -> DataFrame:
    """States given one by one, folded from the left."""
    return reduce(lambda a, b: merge_registers(a.unionByName(b), keys), states)


def rank_of(col: Column, p: int, seed: int = 0, family: str = "md5") -> Column:
    return index_rank(hash64(col, seed, family), p)[1]
