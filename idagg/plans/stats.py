"""Clustered statistics over arm rows: windows are the sampling unit, failures score zero."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

MAX_WINDOWS = 100_000
DRAWS_A_TASK = 2_000


class IntegrityError(ValueError):
    pass


def validate(rows: DataFrame) -> None:
    """Refuse arm rows that repeat a (task, arm), aren't terminal, or whose arms don't share their tasks and windows."""
    bad = rows.groupBy("task_id", "arm").count().where("count > 1").limit(1).count()
    if bad:
        raise IntegrityError("a (task, arm) occurs twice")
    if rows.where("status is null or status not in ('ok', 'failed')").limit(1).count():
        raise IntegrityError("a row isn't terminal")
    arms = rows.select("arm").distinct().count()
    if rows.groupBy("task_id").agg(F.count("*").alias("n"), F.count_distinct("window_id").alias("w")).where((F.col("n") != arms) | (F.col("w") != 1)).limit(1).count():
        raise IntegrityError("arms differ in their tasks or windows")


def accuracy(rows: DataFrame) -> DataFrame:
    return rows.groupBy("arm").agg(F.count("*").alias("n"), F.avg(F.col("score").cast("double")).alias("accuracy"))


def failures(rows: DataFrame) -> DataFrame:
    return rows.where("status = 'failed'").groupBy("arm", "failure_stage").agg(F.count("*").alias("n"))


def paired(rows: DataFrame, a: str, b: str) -> DataFrame:
    """(task_id, window_id, diff): score of arm a less that of b, on each task; one group-by, no join."""
    return rows.where(F.col("arm").isin(a, b)).groupBy("task_id", "window_id").agg(
        (F.sum(F.when(F.col("arm") == a, F.col("score")).otherwise(0)) - F.sum(F.when(F.col("arm") == b, F.col("score")).otherwise(0))).alias("diff"))


def window_sums(rows: DataFrame, value: str = "score", keys: tuple[str, ...] = ("arm",)) -> DataFrame:
    return rows.groupBy(*keys, "window_id").agg(F.sum(F.col(value).cast("double")).alias("s"), F.count("*").alias("n"))


def _windows(sums: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Window sums are one row a window; their number is checked before they are gathered for broadcasting."""
    if (n := sums.count()) > MAX_WINDOWS:
        raise ValueError(f"{n} windows: aggregate them to clusters first")
    rows = sums.orderBy("window_id").select("s", "n").collect()
    return np.array([r.s for r in rows], float), np.array([r.n for r in rows], float)


def cluster_bootstrap(sums: DataFrame, draws: int = 10_000, seed: int = 0, level: float = 0.95) -> DataFrame:
    """(estimate, low, high): task-weighted mean and percentile interval over resampled windows. Records are never resampled."""
    spark = sums.sparkSession
    s, n = _windows(sums)
    shared = spark.sparkContext.broadcast((s, n))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        s, n = shared.value
        for f in frames:
            out = []
            for d in f["id"]:
                c = np.random.default_rng([seed, int(d)]).multinomial(len(s), np.full(len(s), 1 / len(s)))
                out.append(float(c @ s / (c @ n)))
            yield pd.DataFrame({"x": out})

    parts = max(1, draws // DRAWS_A_TASK)
    got = spark.range(0, draws, 1, parts).mapInPandas(run, "x double")
    a = (1 - level) / 2
    return got.agg(F.lit(float(s.sum() / n.sum())).alias("estimate"), F.percentile("x", F.lit(a)).alias("low"), F.percentile("x", F.lit(1 - a)).alias("high"))


def bootstrap_ci(values: DataFrame, key: str, value: str, draws: int = 10_000, seed: int = 0, level: float = 0.95) -> DataFrame:
    """(estimate, low, high) of a mean over streams, each its own cluster."""
    rows = values.groupBy(F.col(key).cast("string").alias("window_id")).agg(F.sum(F.col(value).cast("double")).alias("s"), F.count(value).alias("n"))
    return cluster_bootstrap(rows, draws, seed, level)


def counterfactual_rate(rows: DataFrame) -> DataFrame:
    """Share of counterfactual tasks whose answer follows the altered evidence."""
    return accuracy(rows.where("arm = 'counterfactual'")).select("n", F.col("accuracy").alias("rate"))


def sign_flip_test(sums: DataFrame, draws: int = 100_000, seed: int = 0) -> DataFrame:
    """(diff, p): two-sided randomisation of one sign a window; the observed arrangement counts as one draw."""
    spark = sums.sparkSession
    s, n = _windows(sums)
    shared = spark.sparkContext.broadcast(s)
    seen = abs(float(s.sum()))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        s = shared.value
        for f in frames:
            r = np.random.default_rng([seed, int(f["id"].iloc[0])])
            flips = r.integers(0, 2, (len(f), len(s)), dtype=np.int8) * 2 - 1
            yield pd.DataFrame({"b": [int((np.abs(flips @ s) >= seen - 1e-9).sum())]})

    hits = spark.range(0, draws, 1, max(1, draws // DRAWS_A_TASK)).mapInPandas(run, "b long")
    return hits.agg(F.lit(float(s.sum() / n.sum())).alias("diff"), ((F.sum("b") + 1) / F.lit(float(draws + 1))).alias("p"))


def holm(pvals: DataFrame, name: str = "contrast", p: str = "p") -> DataFrame:
    """(name, p, p_holm): step-down adjusted values over all rows, a short list of contrasts."""
    n = F.count("*").over(W.partitionBy())
    order = W.orderBy(p, name)
    step = F.col(p) * (n - F.row_number().over(order) + 1)
    d = pvals.select(name, p, step.alias("__s"))
    return d.select(name, p, F.least(F.lit(1.0), F.max("__s").over(order.rowsBetween(W.unboundedPreceding, 0))).alias("p_holm"))


def digest(rows: DataFrame) -> str:
    """A digest of a set of rows, whatever their order: what a published result was computed from."""
    h = rows.select(F.xxhash64(*rows.columns).alias("h")).agg(F.bit_xor("h").alias("x"), F.count("*").alias("n"), F.sum(F.pmod("h", F.lit(1 << 31))).alias("s")).first()
    import hashlib

    return hashlib.sha256(repr((rows.columns, tuple(h))).encode()).hexdigest()
