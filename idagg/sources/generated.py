"""Identity streams made from keyed hashes: the same on every run, partition count and engine."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from idagg.functions.hashing import hash64

PIECE = 250_000


def stream_sizes(spark: SparkSession, streams: int, low: int, high: int, seed: int) -> DataFrame:
    """(stream_no, n): each stream's number of identities, drawn from low..high by a keyed hash."""
    return spark.range(streams).select(
        F.col("id").cast("int").alias("stream_no"),
        (F.pmod(hash64(F.concat(F.lit("size:"), F.col("id").cast("string")), seed, "md5"), F.lit(high - low + 1)) + low).alias("n"))


def identity_streams(spark: SparkSession, streams: int, length: int, low: int = 1_000, high: int = 4_000, seed: int = 0) -> DataFrame:
    """(stream_no, pos, identity): streams of ``length`` records over n identities each; the first n records name each once."""
    sizes = stream_sizes(spark, streams, low, high, seed)
    d = spark.range(streams * length).select((F.col("id") / length).cast("int").alias("stream_no"), (F.col("id") % length).alias("pos"))
    pick = F.pmod(F.xxhash64(F.lit(seed), "stream_no", "pos"), F.col("n"))
    k = F.when(F.col("pos") < F.col("n"), F.col("pos")).otherwise(pick)
    return d.join(F.broadcast(sizes), "stream_no").select("stream_no", "pos", F.concat_ws("-", F.lit(f"s{seed}"), F.col("stream_no").cast("string"), k.cast("string")).alias("identity"))


def distinct_streams(spark: SparkSession, sizes: list[int], repeats: int, seed: int = 0) -> DataFrame:
    """(cardinality, rep, identity): for each size, ``repeats`` sets of exactly that many identities. Tasks make pieces of a set, so that large
    sets don't pile up in one."""
    plan = [(n, r, a, min(n, a + PIECE)) for n in sizes for r in range(repeats) for a in range(0, n, PIECE)]
    parts = max(1, min(len(plan), sum(b - a for *_, a, b in plan) // PIECE))
    pieces = spark.createDataFrame(plan, "cardinality long, rep int, a long, b long").repartition(parts)
    return pieces.select("cardinality", "rep", F.explode(F.sequence("a", F.col("b") - 1)).alias("k")).select(
        "cardinality", "rep", F.concat_ws("-", F.lit(f"u{seed}"), F.col("cardinality").cast("string"), F.col("rep").cast("string"), F.col("k").cast("string")).alias("identity"))


def register_source(spark: SparkSession) -> None:
    """Format "identity_stream" with options length, distinct, seed, partitions: (pos, identity)."""
    from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

    class Reader(DataSourceReader):
        def __init__(self, options):
            self.length, self.distinct = int(options.get("length", "1000")), int(options.get("distinct", "100"))
            self.seed, self.parts = options.get("seed", "0"), int(options.get("partitions", "4"))

        def partitions(self):
            return [InputPartition(k) for k in range(self.parts)]

        def read(self, partition):
            import hashlib

            for pos in range(partition.value, self.length, self.parts):
                k = pos if pos < self.distinct else int(hashlib.md5(f"{self.seed}:{pos}".encode()).hexdigest()[:8], 16) % self.distinct
                yield pos, f"id-{self.seed}-{k}"

    class IdentityStream(DataSource):
        @classmethod
        def name(cls):
            return "identity_stream"

        def schema(self):
            return "pos long, identity string"

        def reader(self, schema):
            return Reader(self.options)

    spark.dataSource.register(IdentityStream)
