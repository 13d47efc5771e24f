"""Tables in the folder that driver and executors share: where lineage ends and what several readouts read again."""

from __future__ import annotations

import atexit
import uuid

from pyspark.sql import DataFrame, SparkSession

_ROOTS: dict[str, str] = {}


def shared_base(spark: SparkSession) -> str:
    """spark.checkpoint.dir. Only a session on one machine (tests) may do without: it gets a local folder."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if base:
        return base.rstrip("/")
    if not spark.sparkContext.master.startswith("local["):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    return "file:///tmp/checkpoints/idagg"


def fresh_path(spark: SparkSession, name: str) -> str:
    """A path below the shared folder that nothing has used; this application's paths are deleted at its end."""
    app = spark.sparkContext.applicationId
    if app not in _ROOTS:
        _ROOTS[app] = f"{shared_base(spark)}/states-{app}-{uuid.uuid4().hex[:8]}"
        atexit.register(delete, spark, _ROOTS[app])
    return f"{_ROOTS[app]}/{name}-{uuid.uuid4().hex[:8]}"


def delete(spark: SparkSession, path: str) -> None:
    try:
        p = spark._jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)
    except Exception:  # noqa: BLE001  the session may be gone at exit; the folder is then the cluster's to clear
        pass


def written(df: DataFrame, name: str) -> DataFrame:
    """df written once and read back: what reads it any number of times scans the written table only, and survives lost executors."""
    path = fresh_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
