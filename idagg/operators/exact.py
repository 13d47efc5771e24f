"""Exact targets: what the readouts estimate."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def exact_distinct(records: DataFrame, keys: list[str] | None = None, identity: str = "identity", out: str = "exact") -> DataFrame:
    return records.groupBy(*(keys or [])).agg(F.count_distinct(F.col(identity)).alias(out))


def exact_regions(records: DataFrame, a: str, b: str, keys: list[str] | None = None, stream: str = "stream_id", identity: str = "identity") -> DataFrame:
    """(keys, n10, n01, n11): one shuffle on identity, no join: which streams name it is a pair of bits."""
    keys = keys or []
    d = records.where(F.col(stream).isin(a, b) & F.col(identity).isNotNull())
    bits = d.groupBy(*keys, identity).agg(F.max((F.col(stream) == a).cast("int")).alias("a"), F.max((F.col(stream) == b).cast("int")).alias("b"))
    return bits.groupBy(*keys).agg(
        F.count_if((F.col("a") == 1) & (F.col("b") == 0)).alias("n10"), F.count_if((F.col("a") == 0) & (F.col("b") == 1)).alias("n01"),
        F.count_if((F.col("a") == 1) & (F.col("b") == 1)).alias("n11"))


def ratios(regions: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """(keys, union_n, jaccard, containment_ab, containment_ba); 0 where a base is empty."""
    a, b, c = F.col("n10"), F.col("n01"), F.col("n11")

    def r(x, y):
        return F.when(y == 0, F.lit(0.0)).otherwise(x / y)

    return regions.select(*(keys or []), (a + b + c).alias("union_n"), r(c, a + b + c).alias("jaccard"), r(c, a + c).alias("containment_ab"), r(c, b + c).alias("containment_ba"))


def exact_frequency(records: DataFrame, probe: str, keys: list[str] | None = None, identity: str = "identity") -> DataFrame:
    return records.groupBy(*(keys or [])).agg(F.count_if(F.col(identity) == probe).alias("exact"))


def utf8_payload(records: DataFrame, identity: str = "identity") -> DataFrame:
    """(n, payload_bytes): the identities stored one by one."""
    return records.select(identity).where(F.col(identity).isNotNull()).distinct().agg(F.count("*").alias("n"), F.coalesce(F.sum(F.octet_length(identity)), F.lit(0)).alias("payload_bytes"))
