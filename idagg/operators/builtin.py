"""The engine's own sketches on the same tasks, for comparison."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

RSD = 0.0245  # gives the built-in estimator 2,048 registers


def builtin_distinct(records: DataFrame, keys: list[str] | None = None, identity: str = "identity") -> DataFrame:
    """approx_count_distinct and the HLL sketch (2**11 buckets), both in one pass."""
    return records.groupBy(*(keys or [])).agg(
        F.approx_count_distinct(identity, RSD).alias("approx_estimate"),
        F.hll_sketch_estimate(F.hll_sketch_agg(identity, 11)).alias("hll_estimate"))


def builtin_union(records: DataFrame, part: str, identity: str = "identity") -> DataFrame:
    """One sketch a part, then their union."""
    s = records.groupBy(part).agg(F.hll_sketch_agg(identity, 11).alias("s"))
    return s.agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("estimate"))


def builtin_overlap(records: DataFrame, a: str, b: str, stream: str = "stream_id", identity: str = "identity", lg: int = 12) -> DataFrame:
    """Theta sketches of two streams: sizes of both, of the union and of the intersection."""
    s = records.where(F.col(stream).isin(a, b)).groupBy(stream).agg(F.theta_sketch_agg(identity, lg).alias("s"))
    one = s.agg(F.max(F.when(F.col(stream) == a, F.col("s"))).alias("a"), F.max(F.when(F.col(stream) == b, F.col("s"))).alias("b"))
    e = F.theta_sketch_estimate
    return one.select(e("a").alias("n_a"), e("b").alias("n_b"), e(F.theta_union("a", "b")).alias("n_union"), e(F.theta_intersection("a", "b")).alias("n_both"))


def builtin_count_min(records: DataFrame, keys: list[str] | None = None, identity: str = "identity", seed: int = 0) -> DataFrame:
    """Serialised Count-Min table of the same 4 x 64 shape; the engine offers no SQL point query on it."""
    return records.groupBy(*(keys or [])).agg(F.count_min_sketch(F.col(identity), F.lit(0.03125), F.lit(0.9375), F.lit(seed)).alias("table"))
