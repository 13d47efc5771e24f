"""Streams, and the relational and SQL surface around the methods."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import functions as F
from pyspark.sql import Window as W

from idagg.functions import sqlapi
from idagg.functions.hashing import sql_hash
from idagg.operators import readouts, registers
from idagg.queries import query, sql
from idagg.queries.core import CMC, R4, cm_sql
from idagg.sources import generated, tables
from idagg.sources.shared import fresh_path
from idagg.sources.tables import load_table as T
from idagg.streaming import states as S

# ---- streams: availableNow over the events, against batch SQL


def ev(s, d, per=None):
    e = tables.zoned(tables.table_stream(s, d, "events", per))
    return e.select("event_id", F.col("ts").alias("event_time"), "event_type", F.col("user_id").cast("string").alias("identity"))




@query("stream_running", "WITH " + sql.regs("g", "events", "event_type", "user_id") + " SELECT event_type, j, r FROM g")
def stream_running(s, d):
    return S.drain(S.running_registers(ev(s, d), ["event_type"]), "complete", s)


@query("stream_running_estimate", "WITH " + sql.regs("g", "events", "event_type", "user_id") + " " + sql.estimate("g", "event_type"))
def stream_running_estimate(s, d):
    return readouts.read_distinct(stream_running(s, d), ["event_type"]).select("event_type", R4("estimate"))


CLOSED = "(SELECT ts, event_type, user_id FROM events WHERE CAST(ts AS DATE) < (SELECT CAST(max(ts) - INTERVAL 1 HOUR AS DATE) FROM events))"


@query("stream_tumbling", "WITH " + sql.regs("g", f"(SELECT CAST(ts AS DATE) AS day, user_id FROM {CLOSED})", "day", "user_id") + " SELECT strftime(day, '%Y-%m-%d') AS day, count(*) AS filled, CAST(sum(r) AS BIGINT) AS rank_sum FROM g GROUP BY day")
def stream_tumbling(s, d):
    """Windows that the watermark has closed: all but the newest."""
    x = S.drain(S.windowed_registers(ev(s, d), [], "1 hour", "1 day"), "append", s)
    return x.groupBy(F.date_format("window.start", "yyyy-MM-dd").alias("day")).agg(F.count("*").alias("filled"), F.sum("r").cast("long").alias("rank_sum"))


@query("stream_sliding", "WITH e AS (SELECT CAST(CAST(ts AS DATE) - CAST(k AS INTEGER) AS DATE) AS start, user_id FROM events, range(7) AS t(k)), top AS (SELECT CAST(max(ts) - INTERVAL 1 HOUR AS DATE) AS z FROM events), c AS (SELECT e.* FROM e, top WHERE start + 7 <= z), " + sql.regs("g", "c", "start", "user_id") + " SELECT strftime(start, '%Y-%m-%d') AS start, count(*) AS filled, CAST(sum(r) AS BIGINT) AS rank_sum FROM g GROUP BY ALL")
def stream_sliding(s, d):
    x = S.drain(S.windowed_registers(ev(s, d), [], "1 hour", "7 days", "1 day"), "append", s)
    return x.groupBy(F.date_format("window.start", "yyyy-MM-dd").alias("start")).agg(F.count("*").alias("filled"), F.sum("r").cast("long").alias("rank_sum"))


@query("stream_session", """WITH o AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w <= INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new_ FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
k AS (SELECT user_id, ts, sum(new_) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM o), z AS (SELECT user_id, k, count(*) AS n, max(ts) + INTERVAL 30 MINUTE AS e FROM k GROUP BY ALL)
SELECT CAST(user_id AS VARCHAR) AS identity, count(*) AS sessions, CAST(sum(n) AS BIGINT) AS events FROM z WHERE e <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events) GROUP BY user_id""")
def stream_session(s, d):
    """Sessions are nearly as many as events, so they go to files; the driver holds none."""
    x = S.drain_files(S.sessions(ev(s, d), "identity", "30 minutes", "1 hour"), s, "sessions")
    return x.groupBy("identity").agg(F.count("*").alias("sessions"), F.sum("n").alias("events"))


@query("stream_chained_estimate", "WITH " + sql.regs("g", f"(SELECT CAST(ts AS DATE) AS day, event_type, user_id FROM {CLOSED})", "day, event_type", "user_id") + ", e AS (" + sql.estimate("g", "day, event_type") + ") SELECT strftime(day, '%Y-%m-%d') AS day, event_type, estimate FROM e")
def stream_chained(s, d):
    x = S.drain(S.windowed_estimates(ev(s, d), ["event_type"], "1 hour", "1 day"), "append", s)
    return x.select(F.date_format("start", "yyyy-MM-dd").alias("day"), "event_type", R4("estimate"))


@query("stream_late_dropped", "SELECT count(*) AS on_time, 0::BIGINT AS late_kept FROM (SELECT DISTINCT CAST(ts AS DATE) FROM events WHERE CAST(ts AS DATE) < DATE '2024-01-20')")
def stream_late(s, d):
    """Records in order first, then a replayed old file: windows already closed don't come again."""
    path = fresh_path(s, "late")
    e = tables.zoned(T(s, d, "events")).select("event_id", F.col("ts").alias("event_time"), F.col("user_id").cast("string").alias("identity"))
    import time

    for cond in ("event_time < '2024-01-20'", "event_time >= '2024-01-21'", "event_time < '2024-01-02'"):
        e.where(cond).coalesce(1).write.mode("append").parquet(path)
        time.sleep(0.05)
    st = s.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(path)
    x = S.drain(S.windowed_registers(st, [], "1 hour", "1 day"), "append", s).groupBy(F.to_date("window.start").alias("day"), "j").agg(F.count("*").alias("n"))
    x = x.where("day < '2024-01-20'").groupBy("day").agg(F.max("n").alias("n"))
    return x.agg(F.count("*").alias("on_time"), F.count_if(F.col("n") > 1).alias("late_kept"))


@query("stream_dedup_frequency", "WITH " + cm_sql("events", "user_id") + " SELECT row, col, c FROM cm")
def stream_dedup(s, d):
    """Every event comes twice and counts once."""
    e = ev(s, d)
    twice = e.select(F.explode(F.array(F.lit(0), F.lit(1))).alias("copy"), *e.columns).drop("copy")
    return S.drain(S.countmin_once(twice, "event_id", "60 days", seed=1), "complete", s)


@query("stream_interval_join", "SELECT count(*) AS pairs, count(DISTINCT a.user_id) AS users FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'error' AND b.event_type = 'view'")
def stream_interval(s, d):
    a, b = (ev(s, d).where(F.col("event_type") == t) for t in ("error", "view"))
    return S.drain(S.interval_join(a, b, "identity", "1 hour", "2 hours"), "append", s).agg(F.count("*").alias("pairs"), F.count_distinct("identity").alias("users"))


@query("stream_static_join", "SELECT c_mktsegment, count(DISTINCT o_custkey) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY ALL")
def stream_static(s, d):
    """A stream enriched with a static group key; distinct is exact here, by key."""
    o = tables.zoned(tables.table_stream(s, d, "orders")).select("o_custkey")
    x = o.join(T(s, d, "customer").select("c_custkey", "c_mktsegment"), F.col("o_custkey") == F.col("c_custkey"))
    return S.drain(x.groupBy("c_mktsegment", "o_custkey").count(), "complete", s).groupBy("c_mktsegment").agg(F.count("*").alias("n"))


@query("stream_dense_state", "WITH " + sql.regs("g", "events", "event_type", "user_id") + " SELECT event_type, CAST(sum(r) AS BIGINT) AS rank_sum, count(*) AS filled, 2048::INTEGER AS bytes FROM g GROUP BY event_type")
def stream_dense(s, d):
    x = S.drain(S.dense_states(ev(s, d), "event_type"), "update", s)
    last = x.groupBy("event_type").agg(F.max_by("state", "n").alias("state"))
    u = registers.unpack(last.withColumn("bytes", F.octet_length("state")), ["event_type", "bytes"])
    return u.groupBy("event_type", "bytes").agg(F.sum("r").cast("long").alias("rank_sum"), F.count("*").alias("filled"))


@query("stream_upsert_store", "WITH " + sql.regs("g", "events", "event_type", "user_id") + " " + sql.estimate("g", "event_type"))
def stream_upsert(s, d):
    path = fresh_path(s, "upsert")
    S.drain_batches(ev(s, d), S.upsert_to(f"{path}/store", ["event_type"]), f"{path}/log")
    return readouts.read_distinct(registers.merge_registers(s.read.parquet(f"{path}/store"), ["event_type"]), ["event_type"]).select("event_type", R4("estimate"))


# ---- relational surface

LI = "lineitem"


def q(name, text):
    """A query whose Spark form is SQL text that both engines read alike."""
    def run(s, d):
        tables.views(s, d, *[t for t in tables.TABLES if t in text])
        return s.sql(text)

    query(name, text)(run)
    return run


@query("op_grouping_sets", "SELECT l_returnflag, l_linestatus, CAST(sum(l_linenumber) AS BIGINT) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_linestatus), ())")
def op_gs(s, d):
    return T(s, d, LI).groupingSets([["l_returnflag", "l_linestatus"], ["l_linestatus"], []], "l_returnflag", "l_linestatus").agg(F.sum("l_linenumber").alias("n"))


@query("op_rollup", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")
def op_rollup(s, d):
    return T(s, d, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@query("op_cube", "SELECT o_orderstatus, o_orderpriority, count(DISTINCT o_custkey) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
def op_cube(s, d):
    return T(s, d, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count_distinct("o_custkey").alias("n"))


@query("op_pivot", "SELECT strftime(ts, '%Y-%m-%d') AS day, count(*) FILTER (event_type = 'error') AS error, count(*) FILTER (event_type = 'view') AS view FROM events GROUP BY ALL")
def op_pivot(s, d):
    return T(s, d, "events").groupBy(F.date_format("ts", "yyyy-MM-dd").alias("day")).pivot("event_type", ["error", "view"]).agg(F.count("event_id")).na.fill(0)


@query("op_rank_windows", "SELECT p_partkey, CAST(row_number() OVER w AS INTEGER) AS rn, CAST(dense_rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS INTEGER) AS dr, CAST(ntile(4) OVER w AS INTEGER) AS nt FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_retailprice, p_partkey)")
def op_rank(s, d):
    w = W.partitionBy("p_brand").orderBy("p_retailprice", "p_partkey")
    return T(s, d, "part").select("p_partkey", F.row_number().over(w).alias("rn"), F.dense_rank().over(W.partitionBy("p_brand").orderBy("p_size")).alias("dr"), F.ntile(4).over(w).alias("nt"))


@query("op_lag_lead", "SELECT o_orderkey, lag(o_totalprice) OVER w AS before_, lead(o_totalprice, 2) OVER w AS after_ FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def op_lag(s, d):
    w = W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return T(s, d, "orders").select("o_orderkey", F.lag("o_totalprice").over(w).alias("before_"), F.lead("o_totalprice", 2).over(w).alias("after_"))


@query("op_frames", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS near, max(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS UNBOUNDED PRECEDING) AS top FROM orders")
def op_frames(s, d):
    w = W.partitionBy("o_custkey").orderBy("o_orderkey")
    return T(s, d, "orders").select("o_orderkey", F.count("*").over(w.rowsBetween(-2, 0)).alias("near"), F.max("o_totalprice").over(w.rowsBetween(W.unboundedPreceding, 0)).alias("top"))


@query("op_topk", "SELECT l_partkey, count(DISTINCT l_orderkey) AS n FROM lineitem GROUP BY l_partkey ORDER BY n DESC, l_partkey LIMIT 20")
def op_topk(s, d):
    return T(s, d, LI).groupBy("l_partkey").agg(F.count_distinct("l_orderkey").alias("n")).orderBy(F.desc("n"), "l_partkey").limit(20)


@query("op_range_join", "WITH b AS (SELECT k * 25.0 AS lo, k * 25.0 + 50 AS hi FROM range(5) AS t(k)) SELECT lo, count(*) AS n FROM events JOIN b ON value >= lo AND value < hi GROUP BY lo")
def op_range(s, d):
    """Records to overlapping bands by giving each record its bands, not by comparing all pairs."""
    e = T(s, d, "events").where("value >= 0 and value < 150").select("value")
    k = F.floor(F.col("value") / 25).cast("int")
    x = e.select(F.explode(F.array(k - 1, k)).alias("k")).where("k between 0 and 4")
    return x.groupBy((F.col("k") * F.lit(25.0)).alias("lo")).agg(F.count("*").alias("n"))


@query("op_broadcast_join", "SELECT r_name, count(DISTINCT c_custkey) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL")
def op_broadcast(s, d):
    n = T(s, d, "nation").join(F.broadcast(T(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))  # 25 and 5 rows at any scale
    return T(s, d, "customer").join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("r_name").agg(F.count_distinct("c_custkey").alias("n"))


@query("op_sort_merge_join", "SELECT strftime(l_shipdate, '%Y-%m') AS month, count(DISTINCT o_custkey) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY ALL")
def op_smj(s, d):
    x = T(s, d, LI).select("l_orderkey", "l_shipdate").join(T(s, d, "orders").select("o_orderkey", "o_custkey").hint("merge"), F.col("l_orderkey") == F.col("o_orderkey"))
    return x.groupBy(F.date_format("l_shipdate", "yyyy-MM").alias("month")).agg(F.count_distinct("o_custkey").alias("n"))


@query("op_full_outer", "SELECT coalesce(a.k, b.k) AS k, coalesce(a.n, 0) AS na, coalesce(b.n, 0) AS nb FROM (SELECT l_suppkey AS k, count(*) AS n FROM lineitem WHERE l_returnflag = 'R' GROUP BY ALL) a FULL JOIN (SELECT s_suppkey AS k, count(*) AS n FROM supplier WHERE s_acctbal > 0 GROUP BY ALL) b ON a.k = b.k")
def op_full(s, d):
    a = T(s, d, LI).where("l_returnflag = 'R'").groupBy(F.col("l_suppkey").alias("k")).agg(F.count("*").alias("na"))
    b = T(s, d, "supplier").where("s_acctbal > 0").groupBy(F.col("s_suppkey").alias("k")).agg(F.count("*").alias("nb"))
    return a.join(b, "k", "full").na.fill(0, ["na", "nb"])


@query("op_semi_anti", "SELECT count(*) FILTER (EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderpriority = '1-URGENT')) AS with_urgent, count(*) FILTER (NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)) AS without FROM customer")
def op_semi(s, d):
    c, o = T(s, d, "customer"), T(s, d, "orders")
    on = F.col("c_custkey") == F.col("o_custkey")
    return c.join(o.where("o_orderpriority = '1-URGENT'"), on, "left_semi").agg(F.count("*").alias("with_urgent")).crossJoin(c.join(o, on, "left_anti").agg(F.count("*").alias("without")))


@query("op_hof_arrays", "SELECT o_custkey, CAST(coalesce(list_sum(list_transform(list_filter(list(o_totalprice ORDER BY o_orderkey), lambda x: x > 100000), lambda x: CAST(floor(x) AS BIGINT))), 0) AS BIGINT) AS big FROM orders GROUP BY o_custkey")
def op_hof(s, d):
    g = T(s, d, "orders").groupBy("o_custkey").agg(F.collect_list("o_totalprice").alias("p"))
    big = F.filter("p", lambda x: x > 100000)
    return g.select("o_custkey", F.aggregate(big, F.lit(0).cast("long"), lambda a, x: a + F.floor(x)).alias("big"))


@query("op_maps", "SELECT o_orderstatus, CAST(max(n) FILTER (o_orderpriority = '1-URGENT') AS BIGINT) AS urgent, count(*) AS kinds FROM (SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY ALL) GROUP BY o_orderstatus")
def op_maps(s, d):
    g = T(s, d, "orders").groupBy("o_orderstatus", "o_orderpriority").count().groupBy("o_orderstatus").agg(F.map_from_entries(F.collect_list(F.struct("o_orderpriority", "count"))).alias("m"))
    return g.select("o_orderstatus", F.element_at("m", "1-URGENT").alias("urgent"), F.size("m").cast("long").alias("kinds"))


@query("op_json", "SELECT CAST(json_extract(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY ALL")
def op_json(s, d):
    return T(s, d, "events").groupBy(F.get_json_object("props", "$.k").cast("long").alias("k")).agg(F.count("*").alias("n"))


@query("op_dates", "SELECT CAST(year(o_orderdate) AS INTEGER) AS y, CAST(quarter(o_orderdate) AS INTEGER) AS q, CAST(max(date_diff('day', date_trunc('month', o_orderdate), o_orderdate)) AS INTEGER) AS last_day FROM orders GROUP BY ALL")
def op_dates(s, d):
    return T(s, d, "orders").groupBy(F.year("o_orderdate").alias("y"), F.quarter("o_orderdate").alias("q")).agg(F.max(F.datediff("o_orderdate", F.date_trunc("month", "o_orderdate"))).alias("last_day"))


@query("op_strings", "SELECT p_partkey, upper(substr(p_name, 1, 5)) AS head, replace(p_type, ' ', '_') AS kind, CAST(strlen(p_name) AS INTEGER) AS bytes, md5(p_name) AS digest FROM part")
def op_strings(s, d):
    return T(s, d, "part").select("p_partkey", F.upper(F.substring("p_name", 1, 5)).alias("head"), F.replace("p_type", F.lit(" "), F.lit("_")).alias("kind"), F.octet_length("p_name").alias("bytes"), F.md5("p_name").alias("digest"))


@query("op_bits", "SELECT s_suppkey, CAST(bit_count(s_suppkey) AS INTEGER) AS ones, s_suppkey & 7 AS low, s_suppkey >> 2 AS shifted, xor(s_suppkey, 5::BIGINT) AS x FROM supplier")
def op_bits(s, d):
    c = F.col("s_suppkey")
    return T(s, d, "supplier").select("s_suppkey", F.bit_count("s_suppkey").alias("ones"), c.bitwiseAND(7).alias("low"), F.shiftright("s_suppkey", 2).alias("shifted"), c.bitwiseXOR(5).alias("x"))


@query("op_conditional_agg", "SELECT event_type, count(*) FILTER (value > 50) AS high, round(quantile_cont(value, 0.5), 6) AS mid, round(stddev_samp(value), 6) AS sd FROM events GROUP BY event_type")
def op_cond(s, d):
    return T(s, d, "events").groupBy("event_type").agg(F.count_if(F.col("value") > 50).alias("high"), F.round(F.percentile("value", F.lit(0.5)), 6).alias("mid"), F.round(F.stddev("value"), 6).alias("sd"))


@query("op_set_operations", "SELECT count(*) AS n FROM ((SELECT o_custkey FROM orders WHERE o_orderstatus = 'F' UNION ALL SELECT o_custkey FROM orders WHERE o_orderstatus = 'O') INTERSECT ALL (SELECT o_custkey FROM orders WHERE o_totalprice > 100000))")
def op_sets(s, d):
    o = T(s, d, "orders")
    f, op_, big = (o.where(c).select("o_custkey") for c in ("o_orderstatus = 'F'", "o_orderstatus = 'O'", "o_totalprice > 100000"))
    return f.union(op_).intersectAll(big).agg(F.count("*").alias("n"))


@query("op_sampling", f"SELECT count(*) AS n FROM (SELECT * FROM orders WHERE CAST({sql_hash('CAST(o_orderkey AS VARCHAR)', 0)} AS HUGEINT) IS NOT NULL AND ((CASE WHEN {sql_hash('CAST(o_orderkey AS VARCHAR)', 0)} > 9223372036854775807::UBIGINT THEN CAST({sql_hash('CAST(o_orderkey AS VARCHAR)', 0)} AS HUGEINT) - 18446744073709551616::HUGEINT ELSE CAST({sql_hash('CAST(o_orderkey AS VARCHAR)', 0)} AS HUGEINT) END % 100 + 100) % 100) < 10)")
def op_sampling(s, d):
    """A stated share of rows by keyed hash: the operator is sampling itself."""
    from idagg.operators.extract import sampled

    return sampled(T(s, d, "orders"), "o_orderkey", 10).agg(F.count("*").alias("n"))


op_subqueries = q("op_subqueries", "WITH big AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey HAVING count(*) > (SELECT avg(c) FROM (SELECT count(*) AS c FROM orders GROUP BY o_custkey) x)) SELECT c_mktsegment, count(*) AS n FROM customer JOIN big ON c_custkey = o_custkey GROUP BY c_mktsegment")
op_predicates = q("op_predicates", "SELECT count(*) AS n FROM part WHERE p_brand IN ('Brand#11', 'Brand#23') OR (p_type LIKE '%S%' AND p_size BETWEEN 5 AND 20) OR p_name IS NULL")


MERGE_TREE = """WITH RECURSIVE g AS (SELECT ((l_orderkey % 256) + 256) % 256 AS seg, count(*) AS n FROM lineitem WHERE l_orderkey IS NOT NULL GROUP BY ((l_orderkey % 256) + 256) % 256),
m(k, seg, n) AS (SELECT 8, seg, n FROM g UNION ALL SELECT k - 1, CAST(floor(seg / 2) AS BIGINT), n FROM m WHERE k > 0)
SELECT k, count(*) AS parts, CAST(max(n) AS BIGINT) AS largest, CAST(sum(n) AS BIGINT) AS records FROM (SELECT k, seg, sum(n) AS n FROM m GROUP BY k, seg) AS x GROUP BY k"""


@query("op_recursive_cte", MERGE_TREE)
def op_recursive(s, d):
    """The levels of a merge tree over a table's 256 segments, up to the root: each step joins neighbours."""
    tables.views(s, d, LI)
    return s.sql(MERGE_TREE)


@query("op_udf", "WITH " + sql.regs("g", LI, "l_returnflag", "l_orderkey") + " " + sql.estimate("g", "l_returnflag"))
def op_udf(s, d):
    """Built with SQL functions, packed, read by the scalar function."""
    sqlapi.register(s)
    tables.views(s, d, LI)
    g = s.sql("SELECT l_returnflag, CAST(shiftrightunsigned(h, 53) AS INT) AS j, max(idagg_rank(h)) AS r FROM (SELECT l_returnflag, idagg_hash64(CAST(l_orderkey AS STRING)) AS h FROM lineitem) GROUP BY 1, 2")
    registers.pack(g, ["l_returnflag"]).createOrReplaceTempView("idagg_states")
    return s.sql("SELECT l_returnflag, round(idagg_estimate(state), 4) AS estimate FROM idagg_states")


@query("op_udaf", "WITH " + sql.regs("g", LI, "", "l_orderkey") + " " + sql.estimate("g", ""))
def op_udaf(s, d):
    sqlapi.register(s)
    g = registers.build_registers(T(s, d, LI).select("l_returnflag", F.col("l_orderkey").alias("identity")), ["l_returnflag"])
    registers.pack(g, ["l_returnflag"]).createOrReplaceTempView("idagg_states")
    return s.sql("SELECT round(idagg_estimate(m), 4) AS estimate FROM (SELECT idagg_hll_merge(state) AS m FROM idagg_states)")


@query("op_udtf", "SELECT " + ", ".join(f"{CMC(r, chr(39) + '149' + chr(39), 1)} AS c{r}" for r in range(4)))
def op_udtf(s, d):
    sqlapi.register(s)
    c = s.sql("SELECT * FROM idagg_cm_cells('149', 1, 4, 64)")
    return c.agg(*(F.max(F.when(F.col("row") == r, F.col("col"))).alias(f"c{r}") for r in range(4)))


@query("op_udtf_registers", "WITH " + sql.regs("g", "events", "", "user_id") + " SELECT j, r FROM g")
def op_udtf_registers(s, d):
    sqlapi.register(s)
    g = registers.build_registers(T(s, d, "events").select(F.lit(0).alias("k"), F.col("user_id").alias("identity")), ["k"])
    registers.pack(g, ["k"]).createOrReplaceTempView("idagg_one_state")
    return s.sql("SELECT x.j, x.r FROM idagg_one_state, LATERAL idagg_registers(state) AS x")


@query("src_identity_stream", "SELECT 2000::BIGINT AS n, 300::BIGINT AS ids")
def src_stream(s, d):
    generated.register_source(s)
    x = s.read.format("identity_stream").options(length="2000", distinct="300", seed="1").load()
    return x.agg(F.count("*").alias("n"), F.count_distinct("identity").alias("ids"))


@query("src_formats", "SELECT kind, n, total FROM (SELECT unnest(['csv', 'json', 'orc', 'text']) AS kind), (SELECT count(*) AS n, CAST(sum(n_nationkey) AS BIGINT) AS total FROM nation)")
def src_formats(s, d):
    path = fresh_path(s, "formats")
    n = T(s, d, "nation").select("n_nationkey", "n_name")
    schema = "n_nationkey int, n_name string"
    out = []
    for kind in ("csv", "json", "orc", "text"):
        (n.select(F.col("n_nationkey").cast("string").alias("value")) if kind == "text" else n).write.format(kind).save(f"{path}/{kind}")
        r = tables.read_files(s, f"{path}/{kind}", kind, schema if kind in ("csv", "json") else None)
        k = F.col("value").cast("int") if kind == "text" else F.col("n_nationkey")
        out.append(r.agg(F.count("*").alias("n"), F.sum(k).cast("long").alias("total")).select(F.lit(kind).alias("kind"), "n", "total"))
    return reduce(lambda a, b: a.unionByName(b), out)
