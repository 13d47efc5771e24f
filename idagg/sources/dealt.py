"""Streams of stated relative sizes from a table's own identities, for measuring errors: each distinct identity goes to exactly one stream."""

from __future__ import annotations

from itertools import accumulate

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from idagg.functions.hashing import hash64, sql_hash

LOW = (1 << 62) - 1


def dealt_streams(records: DataFrame, weights: list[int], repeats: int, seed: int = 77) -> DataFrame:
    """(size, rep, identity): ``repeats`` streams of each size k, which have shares in the proportion of ``weights``. None is left out."""
    u, total = F.col("u"), F.lit(sum(weights))
    size = F.coalesce(*(F.when(u % total < b, k) for k, b in enumerate(accumulate(weights))))
    ids = records.where("identity is not null").select("identity").distinct()
    return ids.withColumn("u", hash64("identity", seed, "md5").bitwiseAND(F.lit(LOW))).select(size.alias("size"), F.expr(f"u div {sum(weights)} % {repeats}").alias("rep"), "identity")


def dealt_sql(src: str, ident: str, weights: list[int], repeats: int, seed: int = 77) -> str:
    total = sum(weights)
    size = "CASE " + " ".join(f"WHEN u % {total} < {b} THEN {k}" for k, b in enumerate(accumulate(weights))) + " END"
    return f"(SELECT {size} AS size, (u // {total}) % {repeats} AS rep, z FROM (SELECT z, {sql_hash('z', seed)} & {LOW}::UBIGINT AS u FROM (SELECT DISTINCT {ident} AS z FROM {src}) WHERE z IS NOT NULL))"
