"""Windows, two-way decision tasks and their subsets, all from keyed hashes: no random state, so any engine can generate them again."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from idagg.functions.hashing import hash64
from idagg.operators.exact import exact_regions, ratios
from idagg.sources.tables import load_table

# The generator's settings.
MAX_CANDIDATES, MIN_ITEMS, NON_ADDITIVE_SHARE, TARGET_TASKS, ATTEMPTS, GENERATOR_SEED, VALIDATION_WINDOWS = 30, 16, 0.60, 26, 16, 20260720, 30
MATCHED_WINDOWS, CODE_TASKS = 174, 1200

OPERATORS = ("distinct", "union", "jaccard", "containment", "grouped_distinct", "frequency")
VARIANTS = 4  # tasks an operator and window: thresholds at different distances on both sides
CHUNKS = 4


def unit(key: Column, seed: int = GENERATOR_SEED) -> Column:
    """A number in [0, 1) that depends on the key alone."""
    return hash64(key, seed, "md5").bitwiseAND(F.lit(65535)).cast("double") / 65536


def window_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(window_id, identity, group_key, in_a, in_b, chunk, chars): event days, ship months and order months as windows.

    Operand a and operand b are marked on the record, so all streams of all windows come from one scan a table."""
    ev = load_table(spark, sf_dir, "events").select(
        F.concat(F.lit("ev:"), F.date_format("ts", "yyyy-MM-dd")).alias("window_id"), F.col("user_id").cast("string").alias("identity"),
        F.col("event_type").alias("group_key"), (F.col("event_type") == "error").alias("in_a"), (F.col("event_type") == "view").alias("in_b"),
        F.pmod("event_id", F.lit(CHUNKS)).cast("int").alias("chunk"), (F.length("event_type") + F.length("props") + 40).cast("long").alias("chars"))
    li = load_table(spark, sf_dir, "lineitem").select(
        F.concat(F.lit("li:"), F.date_format("l_shipdate", "yyyy-MM")).alias("window_id"), F.col("l_partkey").cast("string").alias("identity"),
        F.concat("l_returnflag", "l_linestatus").alias("group_key"), (F.col("l_quantity") > 25).alias("in_a"), (F.col("l_discount") >= 0.05).alias("in_b"),
        F.pmod("l_orderkey", F.lit(CHUNKS)).cast("int").alias("chunk"), F.lit(80).cast("long").alias("chars"))
    od = load_table(spark, sf_dir, "orders").select(
        F.concat(F.lit("od:"), F.date_format("o_orderdate", "yyyy-MM")).alias("window_id"), F.col("o_custkey").cast("string").alias("identity"),
        F.col("o_orderpriority").alias("group_key"), F.col("o_orderpriority").isin("1-URGENT", "2-HIGH").alias("in_a"), (F.col("o_totalprice") > 150000).alias("in_b"),
        F.pmod("o_orderkey", F.lit(CHUNKS)).cast("int").alias("chunk"), F.lit(64).cast("long").alias("chars"))
    return ev.unionByName(li).unionByName(od)


WINDOW_SQL = f"""
wr AS (
  SELECT 'ev:' || strftime(ts, '%Y-%m-%d') AS window_id, CAST(user_id AS VARCHAR) AS identity, event_type AS group_key, event_type = 'error' AS in_a,
         event_type = 'view' AS in_b, CAST(event_id % {CHUNKS} AS INTEGER) AS chunk, CAST(length(event_type) + length(props) + 40 AS BIGINT) AS chars FROM events
  UNION ALL SELECT 'li:' || strftime(l_shipdate, '%Y-%m'), CAST(l_partkey AS VARCHAR), l_returnflag || l_linestatus, l_quantity > 25, l_discount >= 0.05,
         CAST(l_orderkey % {CHUNKS} AS INTEGER), 80 FROM lineitem
  UNION ALL SELECT 'od:' || strftime(o_orderdate, '%Y-%m'), CAST(o_custkey AS VARCHAR), o_orderpriority, o_orderpriority IN ('1-URGENT', '2-HIGH'),
         o_totalprice > 150000, CAST(o_orderkey % {CHUNKS} AS INTEGER), 64 FROM orders)"""


def windows(records: DataFrame) -> DataFrame:
    """(window_id, n_records, n_items, token_proxy, split): a token for each four characters of rendered records; split by hash."""
    w = records.groupBy("window_id").agg(
        F.count("*").alias("n_records"), F.count_distinct("identity").alias("n_items"), F.ceil(F.sum("chars") / 4).cast("long").alias("token_proxy"))
    return w.withColumn("split", F.when(unit(F.col("window_id")) < 0.15, "validation").otherwise("test"))


def candidates(records: DataFrame) -> DataFrame:
    """(window_id, identity, rank): up to MAX_CANDIDATES items of each window that has MIN_ITEMS or more, in hash order."""
    items = records.select("window_id", "identity").distinct()
    o = hash64(F.concat("window_id", F.lit("/"), "identity"), GENERATOR_SEED, "md5")
    ranked = items.select("window_id", "identity", F.row_number().over(W.partitionBy("window_id").orderBy(o, "identity")).alias("rank"))
    enough = items.groupBy("window_id").agg(F.count("*").alias("n")).where(F.col("n") >= MIN_ITEMS)
    return ranked.where(F.col("rank") <= MAX_CANDIDATES).join(enough.select("window_id"), "window_id", "left_semi")


def streams(records: DataFrame) -> DataFrame:
    """(window_id, stream_id, group_key, identity) for operands a and b; a record may belong to both."""
    return records.select("window_id", "group_key", "identity", F.explode(F.array_compact(F.array(F.when(F.col("in_a"), "a"), F.when(F.col("in_b"), "b")))).alias("stream_id"))


def targets(records: DataFrame) -> DataFrame:
    """(window_id, operator, group_key, probe, exact): the value that each operator asks for in each window."""
    reg = exact_regions(streams(records), "a", "b", ["window_id"])
    r = reg.join(ratios(reg, ["window_id"]), "window_id").select("window_id", F.explode(F.array(
        F.struct(F.lit("distinct").alias("operator"), (F.col("n10") + F.col("n11")).cast("double").alias("exact")),
        F.struct(F.lit("union").alias("operator"), F.col("union_n").cast("double").alias("exact")),
        F.struct(F.lit("jaccard").alias("operator"), F.col("jaccard").alias("exact")),
        F.struct(F.lit("containment").alias("operator"), F.col("containment_ab").alias("exact")))).alias("x"))
    none = F.lit(None).cast("string")
    r = r.select("window_id", "x.operator", none.alias("group_key"), none.alias("probe"), "x.exact")
    picks = records.groupBy("window_id").agg(F.min("group_key").alias("g"), F.max("identity").alias("z"))
    d = records.select("window_id", "group_key", "identity").join(picks, "window_id")
    g = d.groupBy("window_id", "g", "z").agg(F.count_distinct(F.when(F.col("group_key") == F.col("g"), F.col("identity"))).alias("gd"), F.count_if(F.col("identity") == F.col("z")).alias("f"))
    return r.unionByName(g.select("window_id", F.lit("grouped_distinct").alias("operator"), F.col("g").alias("group_key"), none.alias("probe"), F.col("gd").cast("double").alias("exact"))).unionByName(
        g.select("window_id", F.lit("frequency").alias("operator"), none.alias("group_key"), F.col("z").alias("probe"), F.col("f").cast("double").alias("exact")))


def generate(target: DataFrame) -> DataFrame:
    """(task_id, window_id, operator, group_key, probe, variant, threshold, exact, gold): is the aggregate above the threshold, then act, else
    watch. Thresholds stand 3 to 53 percent off the exact value, the side and distance by hash."""
    t = target.withColumn("variant", F.explode(F.sequence(F.lit(0), F.lit(VARIANTS - 1))))
    t = t.withColumn("task_id", F.concat_ws("/", "window_id", "operator", F.col("variant").cast("string")))
    side = F.when(unit(F.concat(F.lit("side:"), "task_id")) < 0.5, -1.0).otherwise(1.0)
    off = 0.03 + 0.5 * unit(F.concat(F.lit("off:"), "task_id"))
    t = t.withColumn("threshold", F.round(F.col("exact") * (1 + side * off), 6))
    return t.select("task_id", "window_id", "operator", "group_key", "probe", "variant", "threshold", "exact", F.when(F.col("exact") > F.col("threshold"), "act").otherwise("watch").alias("gold"))


def _sql_unit(expr: str) -> str:
    return f"(CAST(('0x' || substr(md5('{GENERATOR_SEED}:' || {expr}), 1, 16))::UBIGINT & 65535::UBIGINT AS DOUBLE) / 65536)"


TASK_SQL = WINDOW_SQL + f""",
pa AS (SELECT window_id, identity, bool_or(in_a) AS a, bool_or(in_b) AS b FROM wr GROUP BY ALL),
reg AS (SELECT window_id, count(*) FILTER (a AND NOT b)::DOUBLE AS n10, count(*) FILTER (b AND NOT a)::DOUBLE AS n01, count(*) FILTER (a AND b)::DOUBLE AS n11
        FROM pa WHERE a OR b GROUP BY window_id),
picks AS (SELECT window_id, min(group_key) AS g, max(identity) AS z FROM wr GROUP BY window_id),
gd AS (SELECT wr.window_id, any_value(g) AS g, any_value(z) AS z, count(DISTINCT identity) FILTER (group_key = g)::DOUBLE AS gd, count(*) FILTER (identity = z)::DOUBLE AS f
       FROM wr JOIN picks USING (window_id) GROUP BY wr.window_id),
tg AS (SELECT window_id, 'distinct' AS operator, NULL::VARCHAR AS group_key, NULL::VARCHAR AS probe, n10 + n11 AS exact FROM reg
  UNION ALL SELECT window_id, 'union', NULL, NULL, n10 + n01 + n11 FROM reg
  UNION ALL SELECT window_id, 'jaccard', NULL, NULL, CASE WHEN n10 + n01 + n11 = 0 THEN 0.0 ELSE n11 / (n10 + n01 + n11) END FROM reg
  UNION ALL SELECT window_id, 'containment', NULL, NULL, CASE WHEN n10 + n11 = 0 THEN 0.0 ELSE n11 / (n10 + n11) END FROM reg
  UNION ALL SELECT window_id, 'grouped_distinct', g, NULL, gd FROM gd
  UNION ALL SELECT window_id, 'frequency', NULL, z, f FROM gd),
tv AS (SELECT *, window_id || '/' || operator || '/' || variant AS task_id FROM tg, range({VARIANTS}) AS v(variant)),
tt AS (SELECT *, round(exact * (1 + (CASE WHEN {_sql_unit("'side:' || task_id")} < 0.5 THEN -1.0 ELSE 1.0 END)::DOUBLE * (0.03::DOUBLE + 0.5::DOUBLE * {_sql_unit("'off:' || task_id")})), 6) AS threshold FROM tv),
tasks AS (SELECT task_id, window_id, operator, group_key, probe, CAST(variant AS INTEGER) AS variant, threshold, exact,
          CASE WHEN exact > threshold THEN 'act' ELSE 'watch' END AS gold FROM tt)"""


def matched(tasks: DataFrame, n_windows: int | None = None) -> DataFrame:
    """One task a window, chosen by hash and so blind to its answer; optionally the first n_windows windows in hash order."""
    o = hash64(F.concat(F.lit("match:"), "task_id"), GENERATOR_SEED, "md5")
    one = tasks.withColumn("__k", F.row_number().over(W.partitionBy("window_id").orderBy(o, "task_id"))).where("__k = 1").drop("__k")
    return one.orderBy(hash64(F.concat(F.lit("window:"), "window_id"), GENERATOR_SEED, "md5"), "window_id").limit(n_windows) if n_windows else one


def code_subset(tasks: DataFrame, n: int = CODE_TASKS) -> DataFrame:
    """A fixed subset that goes round windows and operators evenly: each (window, operator) gives its tasks in hash order."""
    o = hash64(F.concat(F.lit("code:"), "task_id"), GENERATOR_SEED, "md5")
    return tasks.withColumn("__k", F.row_number().over(W.partitionBy("window_id", "operator").orderBy(o, "task_id"))).withColumn("__o", o).orderBy("__k", "__o").limit(n).drop("__k", "__o")


def context_limit(wins: DataFrame, share: float = 0.54) -> DataFrame:
    """(limit_tokens): the length that this share of windows stays within."""
    return wins.agg(F.floor(F.percentile("token_proxy", F.lit(share))).cast("long").alias("limit_tokens"))
