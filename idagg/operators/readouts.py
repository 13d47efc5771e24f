"""Distinct, union and grouped readouts of register states."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from idagg.functions.estimate import corrected_estimate
from idagg.operators.registers import merge_registers
from idagg.spec import DEFAULT_P


def read_distinct(regs: DataFrame, keys: list[str], p: int = DEFAULT_P, out: str = "estimate") -> DataFrame:
    """(keys, estimate) of each state. Without keys, an empty state reads 0."""
    m = 1 << p
    g = regs.groupBy(*keys).agg(F.sum(F.pow(F.lit(2.0), -F.col("r"))).alias("__s"), F.count("*").alias("__c"))
    z = F.coalesce("__s", F.lit(0.0)) + (F.lit(m) - F.col("__c"))
    return g.select(*keys, corrected_estimate(z, F.lit(m) - F.col("__c"), m).alias(out))


def read_union(regs: DataFrame, stream_ids: list[str], keys: list[str] | None = None, p: int = DEFAULT_P, stream: str = "stream_id") -> DataFrame:
    """The merge of the named streams' states, read and not stored; the states themselves stay as they are."""
    keys = keys or []
    return read_distinct(merge_registers(regs.where(F.col(stream).isin(*stream_ids)), keys), keys, p)


def read_grouped(regs: DataFrame, group: str, groups: DataFrame | None = None, p: int = DEFAULT_P) -> DataFrame:
    """(group, estimate); groups, if given, lists those asked for, and one that was never seen reads 0."""
    got = read_distinct(regs, [group], p)
    if groups is None:
        return got
    return groups.select(group).distinct().join(got, group, "left").withColumn("estimate", F.coalesce("estimate", F.lit(0.0)))


def running_distinct(regs: DataFrame, order: str, p: int = DEFAULT_P) -> DataFrame:
    """(order, estimate) of all states up to each point of a short order column (days, segments): a state's registers last until raised.

    Each register is followed along the order by itself; where its rank rises, the harmonic sum changes by a difference of powers of two (exact in
    a double). A point adds up its changes, and only those sums, a row a point, are accumulated in order. Rows without order are left out."""
    m = 1 << p
    d = merge_registers(regs.where(F.col(order).isNotNull()), [order])
    so_far = F.coalesce(F.max("r").over(W.partitionBy("j").orderBy(order).rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    d = d.withColumn("__b", so_far)
    fall = F.when(F.col("r") > F.col("__b"), F.pow(F.lit(2.0), -F.col("r")) - F.pow(F.lit(2.0), -F.col("__b"))).otherwise(0.0)
    per = d.groupBy(order).agg(F.sum(fall).alias("__s"), F.count_if(F.col("__b") == 0).alias("__c"))
    up_to = W.orderBy(order).rowsBetween(W.unboundedPreceding, W.currentRow)
    return per.select(order, corrected_estimate(F.lit(m) + F.sum("__s").over(up_to), F.lit(m) - F.sum("__c").over(up_to), m).alias("estimate"))


def sliding_distinct(regs: DataFrame, day: str, width: int, p: int = DEFAULT_P) -> DataFrame:
    """(day, estimate) over the ``width`` days that end on each day: a day's state goes to each window it is in."""
    d = merge_registers(regs, [day])
    spread = d.select(F.explode(F.sequence(F.lit(0), F.lit(width - 1))).alias("__k"), day, "j", "r").select(F.date_add(day, F.col("__k")).alias(day), "j", "r")
    last = d.agg(F.max(day).alias("__top"))
    spread = spread.join(F.broadcast(last), F.col(day) <= F.col("__top")).drop("__top")
    return read_distinct(merge_registers(spread, [day]), [day], p)
