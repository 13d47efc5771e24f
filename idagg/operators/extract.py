"""Operand extraction: tables to (stream_id, group_key, segment_id, identity, event_time) records."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from idagg.functions.canon import canonical
from idagg.spec import OperandSpec


def extract(df: DataFrame, specs: list[OperandSpec]) -> DataFrame:
    """The records of all operands in one scan: a row goes to each operand whose predicate it meets. Records without identity are dropped."""
    def part(s: OperandSpec) -> Column:
        return F.when(F.expr(s.where), F.struct(
            F.lit(s.stream_id).alias("stream_id"),
            (F.expr(s.group).cast("string") if s.group else F.lit(None).cast("string")).alias("group_key"),
            (F.expr(s.segment).cast("int") if s.segment else F.lit(0)).alias("segment_id"),
            canonical(F.expr(s.identity)).alias("identity"),
            (F.expr(s.event_time).cast("timestamp") if s.event_time else F.lit(None).cast("timestamp")).alias("event_time")))

    if len(specs) == 1:
        rows = df.where(specs[0].where).select(part(OperandSpec(**{**specs[0].__dict__, "where": "true"})).alias("r"))
    else:
        if all(s.where != "true" for s in specs):  # what no operand wants needn't leave the scan
            df = df.where(" OR ".join(f"({s.where})" for s in specs))
        rows = df.select(F.explode(F.array_compact(F.array(*map(part, specs)))).alias("r"))
    return rows.select("r.*").where("identity is not null")


def extract_tokens(df: DataFrame, col: str, pattern: str | None = None, lower: bool = False) -> DataFrame:
    """df with a row for each token of a text column (white space between tokens, or all matches of a pattern) in column identity."""
    c = F.lower(col) if lower else F.col(col)
    tokens = F.regexp_extract_all(c, F.lit(pattern), F.lit(0)) if pattern else F.filter(F.split(c, r"\s+"), lambda x: x != "")
    return df.withColumn("identity", F.explode(tokens))


def url_host(col: str) -> Column:
    return F.regexp_extract(F.col(col), r"^[a-z]+://([^/:?#]+)", 1)


def with_segments(df: DataFrame, parts: int, how: str, key: Column | None = None) -> DataFrame:
    """df with segment_id in 0..parts-1: by hash of a key, round robin or contiguous ranges of an integer key, by time (truncated to
    days, then dealt), or by input file."""
    if how == "hash":
        s = F.pmod(F.xxhash64(key), F.lit(parts))
    elif how == "round_robin":
        s = F.pmod(key.cast("long"), F.lit(parts))
    elif how == "contiguous":
        top = df.agg(F.min(key).alias("a"), F.max(key).alias("z")).first()
        width = max(1, -(-((top.z or 0) - (top.a or 0) + 1) // parts))
        s = F.floor((key - F.lit(top.a or 0)) / width)
    elif how == "time":
        s = F.pmod(F.datediff(key, F.lit("1970-01-01")), F.lit(parts))
    elif how == "file":
        s = F.pmod(F.xxhash64(F.input_file_name()), F.lit(parts))
    else:
        raise ValueError(f"no way {how} to cut segments")
    return df.withColumn("segment_id", s.cast("int"))


def sampled(df: DataFrame, key: str, percent: int, seed: int = 0) -> DataFrame:
    """Rows whose key's hash falls below a share: the same rows each time."""
    from idagg.functions.hashing import hash64

    return df.where(F.pmod(hash64(F.col(key).cast("string"), seed, "md5"), F.lit(100)) < percent)
