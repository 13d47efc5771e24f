"""SQL names: functions, aggregates and table functions over identities and states."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from idagg.functions.estimate import estimate_registers


def _ints(*names: str) -> T.StructType:
    """Types are objects, not text: text can be parsed only where a session runs already."""
    return T.StructType([T.StructField(n, T.IntegerType()) for n in names])


@F.pandas_udf(T.DoubleType())
def idagg_estimate(state: pd.Series) -> pd.Series:
    """Distinct count of a dense state."""
    return state.map(lambda s: None if s is None else estimate_registers(np.frombuffer(s, np.uint8), len(s)))


@F.pandas_udf(T.BinaryType())
def idagg_merge2(a: pd.Series, b: pd.Series) -> pd.Series:
    """The merge of two dense states."""
    return pd.Series([np.maximum(np.frombuffer(x, np.uint8), np.frombuffer(y, np.uint8)).tobytes() for x, y in zip(a, b, strict=True)])


@F.pandas_udf(T.BinaryType())
def idagg_hll_merge(state: pd.Series) -> bytes:
    """The merge of a group's dense states. A group's states come to one task: for many, merge_dense takes partials first."""
    return np.maximum.reduce([np.frombuffer(s, np.uint8) for s in state]).tobytes() if len(state) else b""


@F.udtf(returnType=_ints("j", "r"))
class IdaggRegisters:
    """A dense state's registers that aren't empty."""

    def eval(self, state: bytes):
        for j in np.flatnonzero(np.frombuffer(state, np.uint8)):
            yield int(j), int(state[j])


@F.udtf(returnType=_ints("row", "col"))
class IdaggCmCells:
    """The Count-Min cells of an identity, by row."""

    def eval(self, identity: str, seed: int, d: int, w: int):
        import hashlib

        for r in range(d):
            yield r, int(hashlib.md5(f"{seed}:{r}:{identity}".encode()).hexdigest()[:16], 16) & (w - 1)


def register(spark: SparkSession) -> None:
    """Make idagg_* known to SQL in this session. hash64 and rank are SQL expressions, compiled like any other."""
    q = "conv(substr(md5(concat('0:', z)), 1, 16), 16, -10)"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION idagg_hash64(z STRING) RETURNS BIGINT RETURN CAST({q} AS BIGINT)")
    low = "(h & 9007199254740991)"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION idagg_rank(h BIGINT) RETURNS INT RETURN 54 - IF({low} = 0, 0, length(bin({low})))")
    spark.udf.register("idagg_estimate", idagg_estimate)
    spark.udf.register("idagg_merge2", idagg_merge2)
    spark.udf.register("idagg_hll_merge", idagg_hll_merge)
    spark.udtf.register("idagg_registers", IdaggRegisters)
    spark.udtf.register("idagg_cm_cells", IdaggCmCells)
