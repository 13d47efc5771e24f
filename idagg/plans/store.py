"""Stored states: Parquet by stream and segment, each with its descriptor, found again by what they stand for."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from idagg.operators.registers import merge_registers
from idagg.spec import IncompatibleStates, StateDescriptor, assert_compatible


class StateStore:
    """A folder of register rows (stream_id, segment, group_key, j, r, descriptor), partitioned by stream and segment.

    Each put writes new files of its own partition; reading prunes to the streams and segments asked for, so a request costs what its states
    hold and no scan of records. Registers merge by maximum, so putting the same segment twice changes nothing."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path

    def put(self, regs: DataFrame, descriptor: StateDescriptor, stream_id: str, segment: str = "all", mode: str = "append") -> None:
        group = F.col("group_key") if "group_key" in regs.columns else F.lit(None).cast("string")
        regs.select(
            group.cast("string").alias("group_key"), F.col("j").cast("short").alias("j"), F.col("r").cast("byte").alias("r"),
            F.lit(json.dumps(descriptor.as_dict(), sort_keys=True)).alias("descriptor"), F.lit(stream_id).alias("stream_id"), F.lit(segment).alias("segment"),
        ).write.mode(mode).partitionBy("stream_id", "segment").parquet(self.path)

    def rows(self, stream_ids: list[str] | None = None, segments: list[str] | None = None) -> DataFrame:
        d = self.spark.read.parquet(self.path)
        d = d.where(F.col("stream_id").isin(*stream_ids)) if stream_ids else d
        d = d.where(F.col("segment").cast("string").isin(*segments)) if segments else d
        return d.select("stream_id", F.col("segment").cast("string").alias("segment"), "group_key", F.col("j").cast("int").alias("j"), F.col("r").cast("int").alias("r"), "descriptor")

    def descriptors(self, stream_ids: list[str] | None = None) -> dict[str, set[StateDescriptor]]:
        got: dict[str, set[StateDescriptor]] = {}
        for r in self.rows(stream_ids).select("stream_id", "descriptor").distinct().collect():  # one row a kind of state
            got.setdefault(r.stream_id, set()).add(StateDescriptor(**json.loads(r.descriptor)))
        return got

    def get(self, stream_ids: list[str], descriptor: StateDescriptor, segments: list[str] | None = None, keys: tuple[str, ...] = ("stream_id", "group_key")) -> DataFrame:
        """The streams' states, merged over segments; anything stored under another descriptor is refused."""
        for s, ds in self.descriptors(stream_ids).items():
            for d in ds:
                assert_compatible(d, descriptor)
                if d.stream_def and descriptor.stream_def and d.stream_def != descriptor.stream_def and len(stream_ids) == 1:
                    raise IncompatibleStates(f"{s} is stored for another definition")
        return merge_registers(self.rows(stream_ids, segments), list(keys))

    def compact(self, stream_id: str, descriptor: StateDescriptor, into: StateStore, segment: str = "all") -> None:
        """Write the stream's states, merged over all their segments and versions, as one segment of another store; readers move to it when they
        choose, so no file that is being read is replaced."""
        merged = self.get([stream_id], descriptor, keys=("group_key",))
        into.put(merged, descriptor, stream_id, segment)

    def covered(self, stream_id: str) -> set[str]:
        """Segments that need no scan."""
        return {r.segment for r in self.rows([stream_id]).select("segment").distinct().collect()}

    def active_groups(self, stream_id: str) -> DataFrame:
        return self.rows([stream_id]).select("group_key").distinct()
