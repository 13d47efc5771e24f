"""Normalised attention readouts, and why they neither ignore repeats nor merge."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def attention_state(df: DataFrame, a: str, v: str, keys: list[str] | None = None) -> DataFrame:
    """(keys, top, num, den): numerator and denominator relative to the largest score, so exponentials don't overflow; both merge by addition
    after a common shift."""
    keys = keys or []
    top = df.groupBy(*keys).agg(F.max(a).alias("top"))
    d = df.join(top, keys) if keys else df.crossJoin(F.broadcast(top))
    w = F.exp(F.col(a) - F.col("top"))
    return d.groupBy(*keys).agg(F.first("top").alias("top"), F.sum(w * F.col(v)).alias("num"), F.sum(w).alias("den"))


def attention_readout(df: DataFrame, a: str, v: str, keys: list[str] | None = None) -> DataFrame:
    return attention_state(df, a, v, keys).select(*(keys or []), (F.col("num") / F.col("den")).alias("o"))


def merge_nd(states: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """States merged: unlike the readouts these are mergeable, but a repeated record still counts twice."""
    keys = keys or []
    top = states.groupBy(*keys).agg(F.max("top").alias("__t"))
    d = states.join(top, keys) if keys else states.crossJoin(F.broadcast(top))
    s = F.exp(F.col("top") - F.col("__t"))
    return d.groupBy(*keys).agg(F.first("__t").alias("top"), F.sum(F.col("num") * s).alias("num"), F.sum(F.col("den") * s).alias("den"))


def duplicate_shift(state: DataFrame, w, v):
    """Change of the readout when a record of weight w = exp(score - top) and value v is repeated."""
    o = F.col("num") / F.col("den")
    return state.withColumn("shift", w * (v - o) / (F.col("den") + w))


def merge_counterexample(df: DataFrame, a: str, v: str, keys: list[str] | None = None) -> DataFrame:
    """(keys, context, alone, followed): a key's records (x) and one record that has their readout (y). Equal readouts differ once the same third
    context, a record of the top score and value zero, follows: no function of readouts can merge them, though the states merge."""
    by = [*(keys or []), "context"]
    o = F.col("num") / F.col("den")
    both = F.array(F.struct(F.lit("x").alias("context"), "top", "num", "den"), F.struct(F.lit("y").alias("context"), "top", o.alias("num"), F.lit(1.0).alias("den")))
    d = attention_state(df, a, v, keys).select(*(keys or []), F.explode(both).alias("s")).select(*(keys or []), "s.*")
    third = d.select(*by, "top", F.lit(0.0).alias("num"), F.lit(1.0).alias("den"))
    return d.select(*by, o.alias("alone")).join(merge_nd(d.unionByName(third), by).select(*by, o.alias("followed")), by)
