"""Accuracy and cost measures over readouts."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from idagg.operators.learned import STATE_BYTES


def relerr(est: Column, exact: Column) -> Column:
    """|estimate - exact| over the exact value, or over 1 where that is smaller."""
    return F.abs(est - exact) / F.greatest(F.lit(1.0), F.abs(exact).cast("double"))


def summary(df: DataFrame, keys: list[str], est: str = "estimate", exact: str = "exact") -> DataFrame:
    """(keys, n, median, mean and root mean square of the relative error); NULL estimates (invalid readouts) are counted apart."""
    e = df.withColumn("__e", relerr(F.col(est), F.col(exact)))
    return e.groupBy(*keys).agg(
        F.count("__e").alias("n"), F.count_if(F.col("__e").isNull()).alias("invalid"), F.median("__e").alias("median_relerr"), F.avg("__e").alias("mean_relerr"),
        F.sqrt(F.avg(F.col("__e") * F.col("__e"))).alias("rms_relerr"))


def paired_median_diff(a: DataFrame, b: DataFrame, key: str, err: str = "err") -> DataFrame:
    """Median over streams of the difference of their errors (not the difference of medians)."""
    return a.select(key, F.col(err).alias("__a")).join(b.select(key, F.col(err).alias("__b")), key).agg(
        F.median(F.col("__a") - F.col("__b")).alias("median_paired_diff"), F.try_divide(F.median("__a"), F.median("__b")).alias("ratio_of_medians"))


def total_state_bytes(regs: DataFrame, keys: list[str], m: int) -> DataFrame:
    """(states, state_bytes): active states and what they carry at m bytes each."""
    return regs.select(*keys).distinct().agg(F.count("*").alias("states"), (F.count("*") * m).alias("state_bytes"))


def resource_table(spark: SparkSession, m: int = 2048) -> DataFrame:
    """Bytes by what they are: carried per stream, static parameters, shared trunk. Kinds are never added up."""
    from idagg.operators.learned import SetEncoder

    e = SetEncoder.create()
    static = 4 * (e.keys.size + e.values.size + e.w1.size + e.b1.size + e.w2.size + 1 + e.mean.size + e.scale.size)
    rows = [("registers", "carried", m), ("registers", "static", 0), ("set_encoder", "carried", STATE_BYTES), ("set_encoder", "static", int(static)),
            ("set_encoder", "shared_trunk", 0), ("count_min", "carried", 4 * 64 * 8)]
    return spark.createDataFrame(rows, "method string, kind string, bytes long")


def utf8_crossover(ids: DataFrame, m: int = 2048, identity: str = "identity") -> DataFrame:
    """(mean_bytes, crossover): how many identities of the mean length fill m bytes."""
    d = ids.select(identity).where(F.col(identity).isNotNull()).distinct()
    return d.agg(F.avg(F.octet_length(identity)).alias("mean_bytes"), (F.lit(float(m)) / F.avg(F.octet_length(identity))).alias("crossover"))


def running_crossover(ids: DataFrame, m: int = 2048, identity: str = "identity") -> DataFrame:
    """First number of identities, in hash order, whose payload reaches m bytes. Only the first m identities can matter (each has a byte)."""
    d = ids.select(identity).where(F.col(identity).isNotNull() & (F.octet_length(identity) > 0)).distinct()
    d = d.withColumn("__o", F.md5(identity)).orderBy("__o").limit(m)
    w = W.orderBy("__o")
    return d.select(F.row_number().over(w).alias("n"), F.sum(F.octet_length(identity)).over(w).alias("payload")).where(F.col("payload") >= m).agg(F.min("n").alias("first_n"))
