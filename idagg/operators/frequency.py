"""Point frequencies: an exact counter for a probe known beforehand, and Count-Min tables."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from idagg.functions.hashing import hash64

DEPTH, WIDTH = 4, 64  # 4 x 64 counters of 8 bytes: the 2,048 bytes of a register state


def count_probe(records: DataFrame, probe: str, keys: list[str] | None = None, identity: str = "identity") -> DataFrame:
    return records.groupBy(*(keys or [])).agg(F.count_if(F.col(identity) == F.lit(probe)).alias("frequency"))


def column_of(identity: Column, row: int, w: int, seed: int, family: str) -> Column:
    """The low bits of a hash salted by the row: w is a power of two, so sign doesn't matter."""
    return hash64(F.concat(F.lit(f"{row}:"), identity), seed, family).bitwiseAND(F.lit(w - 1)).cast("int")


def build_countmin(records: DataFrame, keys: list[str], d: int = DEPTH, w: int = WIDTH, seed: int = 0, family: str = "md5", identity: str = "identity") -> DataFrame:
    """(keys, row, col, c). Equal identities are counted before they fan out to d rows, and counts are summed before the shuffle."""
    if w & (w - 1):
        raise ValueError("the width must be a power of two")
    z = F.col(identity).cast("string")
    cells = F.array(*(F.struct(F.lit(r).alias("row"), column_of(z, r, w, seed, family).alias("col")) for r in range(d)))
    x = records.where(F.col(identity).isNotNull()).select(*keys, F.explode(cells).alias("x"))
    return x.groupBy(*keys, F.col("x.row").alias("row"), F.col("x.col").alias("col")).agg(F.count("*").alias("c"))


def merge_countmin(cells: DataFrame, keys: list[str]) -> DataFrame:
    return cells.groupBy(*keys, "row", "col").agg(F.sum("c").alias("c"))


def read_frequency(cells: DataFrame, probes: DataFrame, keys: list[str] | None = None, d: int = DEPTH, w: int = WIDTH, seed: int = 0, family: str = "md5", identity: str = "identity") -> DataFrame:
    """(keys, identity, estimate): the least of the probe's d counters; a counter that was never raised is 0. probes: identity (and keys)."""
    keys = keys or []
    z = F.col(identity).cast("string")
    at = F.array(*(F.struct(F.lit(r).alias("row"), column_of(z, r, w, seed, family).alias("col")) for r in range(d)))
    asked = probes.select(*keys, identity, F.explode(at).alias("x")).select(*keys, identity, "x.row", "x.col")
    return asked.join(cells, [*keys, "row", "col"], "left").groupBy(*keys, identity).agg(F.min(F.coalesce("c", F.lit(0))).cast("long").alias("estimate"))


def bound(n: float, w: int = WIDTH, d: int = DEPTH) -> tuple[float, float]:
    """Most over-estimation, and the least probability that it holds."""
    return math.e * n / w, 1 - math.exp(-d)
