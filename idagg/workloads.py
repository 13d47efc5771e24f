"""Registered queries of the library, and the flagship one."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from idagg.queries import ORACLES, QUERIES
from idagg.queries import campaign as _campaign  # noqa: F401
from idagg.queries import core as _core  # noqa: F401  each registers its queries
from idagg.queries import engine as _engine  # noqa: F401
from idagg.queries import evaluation as _evaluation  # noqa: F401


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distinct order keys by return flag: the sketch's readout, the exact value and the relative error."""
    from idagg.operators.exact import exact_distinct
    from idagg.operators.readouts import read_distinct
    from idagg.operators.registers import build_registers
    from idagg.plans.measures import relerr
    from idagg.sources.tables import load_table

    r = load_table(spark, sf_dir, "lineitem").select("l_returnflag", F.col("l_orderkey").alias("identity"))
    est = read_distinct(build_registers(r, ["l_returnflag"]), ["l_returnflag"])
    return est.join(exact_distinct(r, ["l_returnflag"]), "l_returnflag").withColumn("relative_error", relerr(F.col("estimate"), F.col("exact")))


def queries() -> dict:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
