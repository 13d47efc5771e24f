"""Keyed 64-bit hashes of identities, and a hash's register index and rank."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def hash64(col: Column | str, seed: int = 0, family: str = "xx") -> Column:
    """family xx: the engine's own 64-bit hash, compiled into the scan. family md5: 64 bits of a keyed digest that any SQL
    engine can repeat, for comparing states register by register."""
    c = F.col(col) if isinstance(col, str) else col
    if family == "xx":
        return F.xxhash64(F.lit(seed), c)
    if family == "md5":
        return F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), c)), 1, 16), 16, -10).cast("long")
    raise ValueError(f"no hash family {family}")


def index_rank(h: Column, p: int) -> tuple[Column, Column]:
    """The top p bits, and 1 + the leading zeros of the other 64 - p (64 - p + 1 where they are all zero).

    Ranks come from the length of the binary text: logarithms round up next to powers of two."""
    q = 64 - p
    w = h.bitwiseAND(F.lit((1 << q) - 1))
    return F.shiftrightunsigned(h, q).cast("int"), (F.lit(q + 1) - F.when(w == 0, 0).otherwise(F.length(F.bin(w)))).cast("int")


def sql_hash(expr: str, seed: int = 0) -> str:
    """family md5 as DuckDB SQL."""
    return f"('0x' || substr(md5('{seed}:' || {expr}), 1, 16))::UBIGINT"


def sql_index(h: str, p: int) -> str:
    return f"CAST({h} >> {64 - p} AS INTEGER)"


def sql_rank(h: str, p: int) -> str:
    q = 64 - p
    w = f"({h} & {(1 << q) - 1}::UBIGINT)"
    return f"CAST({q + 1} - CASE WHEN {w} = 0 THEN 0 ELSE length(bin({w})) END AS INTEGER)"
