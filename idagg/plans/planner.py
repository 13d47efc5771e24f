"""Many requests over shared states: one scan, one build, one written table, any number of readouts."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from idagg.functions.hashing import hash64, index_rank
from idagg.operators.extract import extract
from idagg.operators.frequency import DEPTH, WIDTH, column_of, read_frequency
from idagg.operators.readouts import read_distinct, read_grouped, read_union
from idagg.operators.registers import merge_registers
from idagg.operators.relation import relate
from idagg.sources.shared import written
from idagg.spec import OperandSpec, Request, StateDescriptor

CM_SEED = 1


@dataclass
class SharedStates:
    """The states of all operands as one written table (stream_id, kind, name, slot, r, c): registers by group (kind r, name the group), Count-Min
    cells (kind m) and exact counters of the probes that were named beforehand (kind c, name the probe). Requests read it, never the records."""

    made: DataFrame
    descriptor: StateDescriptor
    probes: tuple[str, ...] = ()

    @property
    def regs(self) -> DataFrame:
        return self.made.where("kind = 'r'").select("stream_id", F.col("name").alias("group_key"), F.col("slot").alias("j"), "r")

    def answer(self, q: Request) -> DataFrame:
        """(estimate), by group for grouped requests, with valid for relations. A frequency is exact for a probe that was named beforehand, else the
        Count-Min readout."""
        p = self.descriptor.p
        ids = list(q.operands)
        if q.op == "distinct":
            return read_union(self.regs, ids[:1], p=p)
        if q.op == "union":
            return read_union(self.regs, ids, p=p)
        if q.op == "grouped_distinct":
            of = merge_registers(self.regs.where(F.col("stream_id") == ids[0]), ["group_key"])
            asked = None if q.groups is None else of.sparkSession.createDataFrame([(g,) for g in q.groups], "group_key string")
            return read_grouped(of, "group_key", asked, p)
        if q.op in ("jaccard", "containment", "overlap"):
            both = merge_registers(self.regs.where(F.col("stream_id").isin(*ids)), ["stream_id"])
            got = relate(both, ids[0], ids[1], p=p)
            return got.select(F.col({"jaccard": "jaccard", "containment": "containment_ab", "overlap": "overlap"}[q.op]).alias("estimate"), "valid")
        if q.op == "frequency":
            own = self.made.where(F.col("stream_id") == ids[0])
            if q.probe in self.probes:
                return own.where((F.col("kind") == "c") & (F.col("name") == q.probe)).agg(F.coalesce(F.sum("c"), F.lit(0)).alias("estimate"))
            cells = own.where("kind = 'm'").select(F.floor(F.col("slot") / WIDTH).cast("int").alias("row"), (F.col("slot") % WIDTH).alias("col"), "c")
            return read_frequency(cells, own.sparkSession.createDataFrame([(q.probe,)], "identity string"), seed=CM_SEED).select("estimate")
        raise ValueError(f"no operator {q.op}")


def build(df: DataFrame, specs: list[OperandSpec], descriptor: StateDescriptor | None = None, probes: tuple[str, ...] = ()) -> SharedStates:
    """States of all operands from one scan of df; partial maxima and sums are taken before the shuffle. probes: a short list."""
    d = descriptor or StateDescriptor()
    z, zero, one, none = F.col("identity"), F.lit(0), F.lit(1), F.lit(None).cast("string")
    j, r = index_rank(F.col("h"), d.p)
    up = [F.struct(F.lit("r").alias("kind"), F.col("group_key").alias("name"), j.alias("slot"), r.alias("r"), zero.alias("c"))]
    up += [F.struct(F.lit("m").alias("kind"), none.alias("name"), (column_of(z, k, WIDTH, CM_SEED, "md5") + k * WIDTH).alias("slot"), zero.alias("r"), one.alias("c")) for k in range(DEPTH)]
    if probes:
        up.append(F.when(z.isin(*probes), F.struct(F.lit("c").alias("kind"), z.alias("name"), zero.alias("slot"), zero.alias("r"), one.alias("c"))))
    x = extract(df, specs).withColumn("h", hash64(z, d.seed, d.family)).select("stream_id", F.explode(F.array_compact(F.array(*up))).alias("x")).select("stream_id", "x.*")
    made = x.groupBy("stream_id", "kind", "name", "slot").agg(F.max("r").alias("r"), F.sum("c").alias("c"))
    return SharedStates(written(made, "shared-states"), d, tuple(probes))


def all_distinct(states: SharedStates) -> DataFrame:
    return read_distinct(merge_registers(states.regs, ["stream_id"]), ["stream_id"], states.descriptor.p)


def scans(df: DataFrame) -> int:
    """File scans in the plan of df."""
    return df._jdf.queryExecution().optimizedPlan().toString().count("Relation [")
