"""States over streams: a micro-batch is a segment, so streaming and batch builds give the same registers.

Records of a register maximum may repeat or come late within the watermark without harm; counters need deduplication first.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from idagg.functions.estimate import corrected_estimate
from idagg.operators.frequency import DEPTH, WIDTH, column_of
from idagg.operators.registers import merge_registers, with_registers
from idagg.sources.shared import fresh_path
from idagg.spec import DEFAULT_P


def running_registers(stream: DataFrame, keys: list[str], p: int = DEFAULT_P, **how) -> DataFrame:
    """Update or complete mode: at most m state rows a key."""
    return merge_registers(with_registers(stream.select(*keys, "identity"), p, **how).drop("identity"), keys)


def windowed_registers(stream: DataFrame, keys: list[str], late: str, length: str, slide: str | None = None, time: str = "event_time", p: int = DEFAULT_P) -> DataFrame:
    """(window, keys, j, r) in append mode: tumbling, or sliding where slide is given."""
    d = with_registers(stream.withWatermark(time, late).select(time, *keys, "identity"), p)
    return d.groupBy(F.window(time, length, slide or length).alias("window"), *keys, "j").agg(F.max("r").alias("r"))


def windowed_estimates(stream: DataFrame, keys: list[str], late: str, length: str, slide: str | None = None, time: str = "event_time", p: int = DEFAULT_P) -> DataFrame:
    """(window, keys, estimate): registers, then the readout, as chained aggregations."""
    m = 1 << p
    g = windowed_registers(stream, keys, late, length, slide, time, p).groupBy("window", *keys).agg(F.sum(F.pow(F.lit(2.0), -F.col("r"))).alias("s"), F.count("*").alias("c"))
    return g.select(F.col("window.start").alias("start"), *keys, corrected_estimate(F.col("s") + (F.lit(m) - F.col("c")), F.lit(m) - F.col("c"), m).alias("estimate"))


def sessions(stream: DataFrame, user: str, gap: str, late: str, time: str = "event_time") -> DataFrame:
    return stream.withWatermark(time, late).groupBy(F.session_window(time, gap).alias("w"), user).agg(F.count("*").alias("n")).select(user, F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def countmin_once(stream: DataFrame, event_id: str, late: str, time: str = "event_time", d: int = DEPTH, w: int = WIDTH, seed: int = 0) -> DataFrame:
    """Count-Min cells of events that may be replayed: each event counts once within the watermark."""
    once = stream.withWatermark(time, late).dropDuplicatesWithinWatermark([event_id])
    z = F.col("identity")
    cells = F.array(*(F.struct(F.lit(r).alias("row"), column_of(z, r, w, seed, "md5").alias("col")) for r in range(d)))
    return once.select(F.explode(cells).alias("x")).groupBy("x.row", "x.col").agg(F.count("*").alias("c"))


def interval_join(a: DataFrame, b: DataFrame, key: str, within: str, late: str, time: str = "event_time") -> DataFrame:
    """Pairs of events of both streams with one key, b at most ``within`` after a. Both sides' state is bounded by the watermarks."""
    x = a.withWatermark(time, late).select(F.col(key).alias("k"), F.col(time).alias("ta"))
    y = b.withWatermark(time, late).select(F.col(key).alias("k2"), F.col(time).alias("tb"))
    return x.join(y, F.expr(f"k = k2 AND tb >= ta AND tb <= ta + interval {within}")).select(F.col("k").alias(key), "ta", "tb")


def dense_states(stream: DataFrame, key: str, p: int = DEFAULT_P) -> DataFrame:
    """(key, state, n): m bytes a key as arbitrary state; registers are reduced in the batch before they reach it."""
    m = 1 << p
    d = with_registers(stream.select(key, "identity"), p).select(key, "j", "r")
    from pyspark.sql.streaming.state import GroupState

    def fold(k: tuple, frames, state: GroupState):
        v = np.frombuffer(state.get[0], np.uint8).copy() if state.exists else np.zeros(m, np.uint8)
        n = state.get[1] if state.exists else 0
        for f in frames:
            np.maximum.at(v, f["j"].to_numpy(), f["r"].to_numpy().astype(np.uint8))
            n += len(f)
        state.update((v.tobytes(), n))
        yield pd.DataFrame({key: [k[0]], "state": [v.tobytes()], "n": [n]})

    kind = stream.schema[key].dataType.simpleString()
    return d.groupBy(key).applyInPandasWithState(fold, f"{key} {kind}, state binary, n long", "state binary, n long", "update", "NoTimeout")


def upsert_to(store_path: str, keys: list[str]) -> Callable[[DataFrame, int], None]:
    """For foreachBatch: each batch writes the registers it adds as a version of its own; readers take the maximum over versions.

    A batch that is tried again overwrites its own version, so the store is exact whatever is retried."""
    def put(batch: DataFrame, number: int) -> None:
        merge_registers(with_registers(batch.select(*keys, "identity")).drop("identity"), keys).write.mode("overwrite").parquet(f"{store_path}/batch={number}")

    return put


def drain(stream: DataFrame, mode: str, spark: SparkSession) -> DataFrame:
    """Run a stream over what is there and return the sink's rows; for tests and batch comparisons of bounded results."""
    name = f"idagg_{uuid.uuid4().hex[:8]}"
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)


def drain_files(stream: DataFrame, spark: SparkSession, name: str) -> DataFrame:
    """Run an append stream over what is there into files of the shared folder and return them: for results that grow with the records, which the
    memory sink would gather on the driver."""
    path = fresh_path(spark, name)
    q = stream.writeStream.format("parquet").option("checkpointLocation", fresh_path(spark, f"{name}-progress")).outputMode("append").trigger(availableNow=True).start(path)
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(path)


def drain_batches(stream: DataFrame, put: Callable[[DataFrame, int], None], checkpoint: str) -> None:
    q = stream.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
