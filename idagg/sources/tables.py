"""Table sources and sinks: Parquet, ORC, CSV, JSON and text reads with explicit schemas, and streams of files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType, TimestampNTZType

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def zoned(df: DataFrame) -> DataFrame:
    """Zone-less timestamps as timestamps of the session zone: watermarks and windows need them."""
    return df.select(*(F.col(f.name).cast("timestamp").alias(f.name) if isinstance(f.dataType, TimestampNTZType) else F.col(f.name) for f in df.schema))


def load_table(spark: SparkSession, sf_dir: str, name: str, need: tuple[str, ...] = ()) -> DataFrame:
    """A Parquet table; missing columns are reported before anything runs."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    missing = [c for c in need if c not in df.columns]
    if missing:
        raise ValueError(f"{name} lacks {', '.join(missing)}")
    return df


def views(spark: SparkSession, sf_dir: str, *names: str) -> None:
    """Temporary views of tables for SQL text."""
    for n in names or TABLES:
        load_table(spark, sf_dir, n).createOrReplaceTempView(n)


def read_files(spark: SparkSession, path: str, kind: str, schema: StructType | str | None = None, **options) -> DataFrame:
    """CSV, JSON, ORC, Parquet or text files under a declared schema (nothing is inferred)."""
    if kind in ("csv", "json") and schema is None:
        raise ValueError(f"{kind} needs a schema")
    r = spark.read.format(kind).options(**options)
    return (r.schema(schema) if schema is not None else r).load(path)


def file_stream(spark: SparkSession, path: str, schema: StructType, kind: str = "parquet", per_trigger: int | None = None) -> DataFrame:
    r = spark.readStream.format(kind).schema(schema)
    return (r.option("maxFilesPerTrigger", per_trigger) if per_trigger else r).load(path)


def table_stream(spark: SparkSession, sf_dir: str, name: str, per_trigger: int | None = None) -> DataFrame:
    """A table's folder or file as a stream."""
    path = f"{sf_dir}/{name}.parquet"
    schema = spark.read.parquet(path).schema
    r = spark.readStream.format("parquet").schema(schema)
    r = r.option("maxFilesPerTrigger", per_trigger) if per_trigger else r
    return r.option("pathGlobFilter", f"{name}.parquet").load(sf_dir) if _is_file(spark, path) else r.load(path)


def _is_file(spark: SparkSession, path: str) -> bool:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(p).isFile()


def write_partitioned(df: DataFrame, path: str, *by: str, mode: str = "overwrite", kind: str = "parquet") -> None:
    df.write.mode(mode).partitionBy(*by).format(kind).save(path)
