"""Exact targets, extraction, register states, readouts, frequencies, attention."""

from __future__ import annotations

from functools import reduce
from itertools import accumulate

from pyspark.sql import functions as F

from idagg.functions.canon import canonical
from idagg.functions.estimate import reference_error
from idagg.functions.hashing import hash64, index_rank, sql_hash, sql_index, sql_rank
from idagg.operators import attention, exact, frequency, readouts, registers
from idagg.operators import extract as E
from idagg.plans import measures, planner
from idagg.plans.store import StateStore
from idagg.queries import query, sql
from idagg.sources.dealt import dealt_sql, dealt_streams
from idagg.sources.shared import fresh_path, written
from idagg.sources.tables import load_table as T
from idagg.spec import OperandSpec, Request, StateDescriptor

R4 = lambda c: F.round(c, 4).alias("estimate")
FLAGS = [OperandSpec("R", "l_orderkey", "l_returnflag = 'R'"), OperandSpec("A", "l_orderkey", "l_returnflag = 'A'")]
DAY = [OperandSpec("error", "user_id", "event_type = 'error' AND ts >= '2024-01-05' AND ts < '2024-01-06'"),
       OperandSpec("view", "user_id", "event_type = 'view' AND ts >= '2024-01-05' AND ts < '2024-01-06'")]
FULFIL = [OperandSpec("urgent", "o_custkey", "o_orderpriority = '1-URGENT' AND o_orderstatus = 'F'"), OperandSpec("all", "o_custkey", "o_orderstatus = 'F'")]
DAY_SQL = "ts >= '2024-01-05' AND ts < '2024-01-06'"

# ---- exact targets


@query("x_distinct", "SELECT count(DISTINCT l_orderkey) AS exact FROM lineitem")
def x_distinct(s, d):
    return exact.exact_distinct(T(s, d, "lineitem"), identity="l_orderkey")


@query("x_distinct_by_group", "SELECT strftime(ts, '%Y-%m-%d') AS day, event_type, count(DISTINCT user_id) AS exact FROM events GROUP BY ALL")
def x_distinct_by_group(s, d):
    return exact.exact_distinct(T(s, d, "events").withColumn("day", F.date_format("ts", "yyyy-MM-dd")), ["day", "event_type"], "user_id")


@query("x_union", "SELECT count(DISTINCT o_custkey) AS exact FROM orders WHERE o_orderpriority IN ('1-URGENT', '2-HIGH')")
def x_union(s, d):
    o = T(s, d, "orders").select("o_custkey", "o_orderpriority")
    a, b = (o.where(F.col("o_orderpriority") == p).select("o_custkey") for p in ("1-URGENT", "2-HIGH"))
    return a.union(b).distinct().agg(F.count("*").alias("exact"))


def flag_regions(s, d):
    return exact.exact_regions(E.extract(T(s, d, "lineitem"), FLAGS), "R", "A")


FLAG_REG = """WITH p AS (SELECT l_orderkey, bool_or(l_returnflag = 'R') AS a, bool_or(l_returnflag = 'A') AS b FROM lineitem GROUP BY l_orderkey),
g AS (SELECT count(*) FILTER (a AND NOT b) AS n10, count(*) FILTER (b AND NOT a) AS n01, count(*) FILTER (a AND b) AS n11 FROM p)"""


@query("x_regions", FLAG_REG + " SELECT * FROM g")
def x_regions(s, d):
    return flag_regions(s, d)


@query("x_jaccard", FLAG_REG + " SELECT round(n11 / (n10 + n01 + n11), 9) AS jaccard FROM g")
def x_jaccard(s, d):
    return exact.ratios(flag_regions(s, d)).select(F.round("jaccard", 9).alias("jaccard"))


@query("x_containment_ab", FLAG_REG + " SELECT round(n11 / (n10 + n11), 9) AS containment FROM g")
def x_containment_ab(s, d):
    return exact.ratios(flag_regions(s, d)).select(F.round("containment_ab", 9).alias("containment"))


@query("x_containment_ba", FLAG_REG + " SELECT round(n11 / (n01 + n11), 9) AS containment FROM g")
def x_containment_ba(s, d):
    return exact.ratios(flag_regions(s, d)).select(F.round("containment_ba", 9).alias("containment"))


@query("x_frequency", "SELECT count(*) FILTER (user_id = 149) AS exact FROM events")
def x_frequency(s, d):
    return exact.exact_frequency(T(s, d, "events").select(F.col("user_id").cast("string").alias("identity")), "149")


@query("x_empty_conventions", "SELECT 0::BIGINT AS distinct_n, 0.0::DOUBLE AS jaccard, 0.0::DOUBLE AS containment, 0::BIGINT AS frequency")
def x_empty(s, d):
    none = E.extract(T(s, d, "events"), [OperandSpec("a", "user_id", "event_type = 'none'"), OperandSpec("b", "user_id", "event_type = 'nil'")])
    r = exact.ratios(exact.exact_regions(none, "a", "b")).select("jaccard", F.col("containment_ab").alias("containment"))
    n = exact.exact_distinct(none, out="distinct_n")
    f = exact.exact_frequency(none, "1").withColumnRenamed("exact", "frequency")
    return n.crossJoin(r).crossJoin(f)  # one row each


@query("x_setops_intersect", "SELECT count(*) AS n FROM (SELECT l_orderkey FROM lineitem WHERE l_returnflag = 'R' INTERSECT SELECT l_orderkey FROM lineitem WHERE l_returnflag = 'A')")
def x_intersect(s, d):
    a, b = (T(s, d, "lineitem").where(F.col("l_returnflag") == f).select("l_orderkey") for f in "RA")
    return a.intersect(b).agg(F.count("*").alias("n"))


@query("x_setops_except", "SELECT count(*) AS n FROM (SELECT o_custkey FROM orders WHERE o_orderstatus = 'F' EXCEPT ALL SELECT o_custkey FROM orders WHERE o_orderpriority = '1-URGENT')")
def x_except(s, d):
    o = T(s, d, "orders")
    return o.where("o_orderstatus = 'F'").select("o_custkey").exceptAll(o.where("o_orderpriority = '1-URGENT'").select("o_custkey")).agg(F.count("*").alias("n"))


@query("x_semi_anti_regions", FLAG_REG + " SELECT n11 AS in_both, n10 AS only_r FROM g")
def x_semi_anti(s, d):
    a, b = (T(s, d, "lineitem").where(F.col("l_returnflag") == f).select("l_orderkey").distinct() for f in "RA")
    return a.join(b, "l_orderkey", "left_semi").agg(F.count("*").alias("in_both")).crossJoin(a.join(b, "l_orderkey", "left_anti").agg(F.count("*").alias("only_r")))


# ---- extraction


@query("ext_operands_one_scan", f"""SELECT 'error' AS stream_id, count(*) AS n, count(DISTINCT user_id) AS ids FROM events WHERE event_type = 'error' AND {DAY_SQL}
UNION ALL SELECT 'view', count(*), count(DISTINCT user_id) FROM events WHERE event_type = 'view' AND {DAY_SQL}""")
def ext_operands(s, d):
    return E.extract(T(s, d, "events"), DAY).groupBy("stream_id").agg(F.count("*").alias("n"), F.count_distinct("identity").alias("ids"))


@query("ext_tokens", "SELECT source, count(*) AS tokens, count(DISTINCT t) AS ids FROM (SELECT source, unnest(regexp_split_to_array(text, '\\s+')) AS t FROM documents) WHERE t <> '' GROUP BY source")
def ext_tokens(s, d):
    return E.extract_tokens(T(s, d, "documents").select("source", "text"), "text").groupBy("source").agg(F.count("*").alias("tokens"), F.count_distinct("identity").alias("ids"))


@query("ext_json_group", "SELECT CAST(json_extract(props, '$.k') AS BIGINT) % 5 AS g, count(DISTINCT user_id) AS ids FROM events GROUP BY ALL")
def ext_json(s, d):
    return T(s, d, "events").select((F.from_json("props", "k long")["k"] % 5).alias("g"), "user_id").groupBy("g").agg(F.count_distinct("user_id").alias("ids"))


@query("ext_hosts", "SELECT regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host, count(*) AS n FROM pages GROUP BY ALL")
def ext_hosts(s, d):
    return T(s, d, "pages").groupBy(E.url_host("url").alias("host")).agg(F.count("*").alias("n"))


@query("ext_canonical", "SELECT length(CAST(o_custkey AS VARCHAR)) || ':' || o_custkey || length(o_orderpriority) || ':' || lower(o_orderpriority) AS identity, count(*) AS n FROM orders GROUP BY ALL")
def ext_canonical(s, d):
    return T(s, d, "orders").groupBy(canonical("o_custkey", "o_orderpriority", lower=True).alias("identity")).agg(F.count("*").alias("n"))


@query("ext_segments", "SELECT CAST(l_orderkey % 16 AS INTEGER) AS segment_id, count(*) AS n FROM lineitem GROUP BY ALL")
def ext_segments(s, d):
    return E.with_segments(T(s, d, "lineitem").select("l_orderkey"), 16, "round_robin", F.col("l_orderkey")).groupBy("segment_id").agg(F.count("*").alias("n"))


@query("ext_segments_time", "SELECT CAST(date_diff('day', DATE '1970-01-01', CAST(ts AS DATE)) % 7 AS INTEGER) AS segment_id, count(*) AS n FROM events GROUP BY ALL")
def ext_segments_time(s, d):
    return E.with_segments(T(s, d, "events").select("ts"), 7, "time", F.col("ts")).groupBy("segment_id").agg(F.count("*").alias("n"))


# ---- states

LI = "lineitem"


@query("hll_hash_rank", f"SELECT DISTINCT l_orderkey, CAST(h >> 53 AS INTEGER) AS j, {sql_rank('h', 11)} AS r FROM (SELECT l_orderkey, {sql_hash('CAST(l_orderkey AS VARCHAR)')} AS h FROM lineitem)")
def hll_hash_rank(s, d):
    ids = T(s, d, LI).select("l_orderkey").distinct()
    h = ids.withColumn("h", hash64(F.col("l_orderkey").cast("string"), 0, "md5"))
    j, r = index_rank(F.col("h"), 11)
    return h.select("l_orderkey", j.alias("j"), r.alias("r"))


def order_keys(s, d, keys=()):
    return T(s, d, LI).select(*keys, F.col("l_orderkey").alias("identity"))


@query("hll_registers", "WITH " + sql.regs("g", LI, "l_returnflag", "l_orderkey") + " SELECT * FROM g")
def hll_registers(s, d):
    return registers.build_registers(order_keys(s, d, ["l_returnflag"]), ["l_returnflag"])


@query("hll_dense_state", "WITH " + sql.regs("g", LI, "l_returnflag", "l_orderkey") + """,
k AS (SELECT DISTINCT l_returnflag FROM g), full_ AS (SELECT k.l_returnflag, t.j, coalesce(g.r, 0) AS r FROM k CROSS JOIN range(2048) AS t(j) LEFT JOIN g ON g.l_returnflag = k.l_returnflag AND g.j = t.j)
SELECT l_returnflag, 2048 AS bytes, md5(string_agg(printf('%02X', r), '' ORDER BY j)) AS digest FROM full_ GROUP BY l_returnflag""")
def hll_dense_state(s, d):
    st = registers.pack(hll_registers(s, d), ["l_returnflag"])
    return st.select("l_returnflag", F.octet_length("state").alias("bytes"), F.md5(F.hex("state")).alias("digest"))


@query("hll_dense_merge", "WITH " + sql.regs("g", LI, "", "l_orderkey") + " SELECT j, r FROM g")
def hll_dense_merge(s, d):
    st = registers.pack(hll_registers(s, d), ["l_returnflag"]).select(F.lit(0).alias("k"), "state")
    return registers.unpack(registers.merge_dense(st, ["k"]), ["k"]).select("j", "r")


@query("hll_dense_merge_many", "WITH " + sql.regs("g", LI, "l_orderkey, l_linenumber", "l_partkey", 8) + " SELECT * FROM g")
def hll_dense_merge_many(s, d):
    """Dense states of very many keys, most of them in two segments: more keys than a task merges at a time."""
    keys = ["l_orderkey", "l_linenumber"]
    r = T(s, d, LI).select(*keys, (F.col("l_suppkey") % 2).alias("segment_id"), F.col("l_partkey").alias("identity"))
    st = registers.pack(registers.build_registers(r, [*keys, "segment_id"], 8), [*keys, "segment_id"], 8)
    return registers.unpack(registers.merge_dense(st, keys), keys, 8)


@query("hll_distinct", "WITH " + sql.regs("g", LI, "", "l_orderkey") + " " + sql.estimate("g", ""))
def hll_distinct(s, d):
    return readouts.read_distinct(registers.build_registers(order_keys(s, d), []), []).select(R4("estimate"))


@query("hll_distinct_compiled_hash", "SELECT l_returnflag, count(DISTINCT l_orderkey) AS exact, TRUE AS near FROM lineitem GROUP BY l_returnflag")
def hll_distinct_compiled(s, d):
    """The fast hash family: no text digest, all in generated code."""
    r = order_keys(s, d, ["l_returnflag"])
    e = readouts.read_distinct(registers.build_registers(r, ["l_returnflag"], family="xx"), ["l_returnflag"])
    x = e.join(exact.exact_distinct(r, ["l_returnflag"]), "l_returnflag")
    return x.select("l_returnflag", "exact", (measures.relerr(F.col("estimate"), F.col("exact")) <= 4 * reference_error(2048)).alias("near"))


@query("hll_grouped", "WITH " + sql.regs("g", "(SELECT event_type, strftime(ts, '%Y-%m-%d') AS day, user_id FROM events)", "day, event_type", "user_id") + " " + sql.estimate("g", "day, event_type"))
def hll_grouped(s, d):
    r = T(s, d, "events").select(F.date_format("ts", "yyyy-MM-dd").alias("day"), "event_type", F.col("user_id").alias("identity"))
    return readouts.read_distinct(registers.build_registers(r, ["day", "event_type"]), ["day", "event_type"]).select("day", "event_type", R4("estimate"))


@query("hll_grouped_requested", "WITH " + sql.regs("g", "events", "event_type", "user_id") + ", e AS (" + sql.estimate("g", "event_type") + ") SELECT w.event_type, coalesce(e.estimate, 0.0) AS estimate FROM (VALUES ('error'), ('never'), ('view')) AS w(event_type) LEFT JOIN e USING (event_type)")
def hll_grouped_requested(s, d):
    g = registers.build_registers(T(s, d, "events").select("event_type", F.col("user_id").alias("identity")), ["event_type"])
    return readouts.read_grouped(g, "event_type", s.createDataFrame([("error",), ("never",), ("view",)], "event_type string")).select("event_type", R4("estimate"))


@query("hll_union2", "WITH " + sql.regs("g", "lineitem WHERE l_returnflag IN ('R', 'A')", "", "l_orderkey") + " " + sql.estimate("g", ""))
def hll_union2(s, d):
    g = registers.build_registers(E.extract(T(s, d, LI), FLAGS), ["stream_id"])
    return readouts.read_union(g, ["R", "A"]).select(R4("estimate"))


@query("hll_union_many", "WITH " + sql.regs("g", "orders WHERE o_orderpriority <> '5-LOW'", "", "o_custkey") + " " + sql.estimate("g", ""))
def hll_union_many(s, d):
    g = registers.build_registers(T(s, d, "orders").select("o_orderpriority", F.col("o_custkey").alias("identity")), ["o_orderpriority"])
    return readouts.read_union(g, ["1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED"], stream="o_orderpriority").select(R4("estimate"))


def _sets(keys):
    return "WITH " + sql.regs("g", LI, "l_returnflag, l_linestatus", "l_orderkey") + f", x AS (SELECT l_returnflag, l_linestatus, j, max(r) AS r FROM g GROUP BY {keys}) " + sql.estimate("x", "l_returnflag, l_linestatus")


def _roll(s, d, how):
    g = registers.build_registers(order_keys(s, d, ["l_returnflag", "l_linestatus"]), ["l_returnflag", "l_linestatus"])
    up = registers.rollup_states(g, ["l_returnflag", "l_linestatus"], how)
    return readouts.read_distinct(up, ["l_returnflag", "l_linestatus"]).select("l_returnflag", "l_linestatus", R4("estimate"))


@query("hll_rollup", _sets("GROUPING SETS ((l_returnflag, l_linestatus, j), (l_returnflag, j), (j))"))
def hll_rollup(s, d):
    return _roll(s, d, "rollup")


@query("hll_cube", _sets("GROUPING SETS ((l_returnflag, l_linestatus, j), (l_returnflag, j), (l_linestatus, j), (j))"))
def hll_cube(s, d):
    return _roll(s, d, "cube")


@query("hll_small_range", "WITH " + sql.regs("g", "events", "event_type", "user_id") + " " + sql.estimate("g", "event_type"))
def hll_small(s, d):
    g = registers.build_registers(T(s, d, "events").select("event_type", F.col("user_id").alias("identity")), ["event_type"])
    return readouts.read_distinct(g, ["event_type"]).select("event_type", R4("estimate"))


@query("hll_raw_range", "WITH " + sql.regs("g", LI, "", "l_orderkey", 8) + " " + sql.estimate("g", "", 8))
def hll_raw(s, d):
    return readouts.read_distinct(registers.build_registers(order_keys(s, d), [], 8), [], 8).select(R4("estimate"))


# ---- merging


def seg_rows(s, d, parts):
    return E.with_segments(order_keys(s, d), parts, "round_robin", F.col("identity"))


@query("hll_merge_segments", "SELECT 16::BIGINT AS segments, 0::BIGINT AS mismatches")
def hll_merge_segments(s, d):
    seg = registers.build_registers(seg_rows(s, d, 16), ["segment_id"])
    once = registers.build_registers(order_keys(s, d), [])
    return registers.register_mismatches(registers.merge_registers(seg, []), once, []).select(F.lit(16).cast("long").alias("segments"), "mismatches")


@query("hll_merge_orders", "SELECT * FROM (VALUES ('left', 0::BIGINT), ('reversed', 0), ('tree', 0)) AS v(merge_order, mismatches)")
def hll_merge_orders(s, d):
    seg = registers.build_registers(seg_rows(s, d, 32), ["segment_id"])
    once = registers.build_registers(order_keys(s, d), [])
    return reduce(lambda a, b: a.unionByName(b), (
        registers.register_mismatches(registers.merge_in_order(seg, [], o), once, []).select(F.lit(o).alias("merge_order"), "mismatches") for o in ("left", "reversed", "tree")))


@query("hll_merge_256", "WITH " + sql.regs("g", LI, "", "l_orderkey") + ", e AS (" + sql.estimate("g", "") + ") SELECT parts::INTEGER AS parts, estimate, 0::BIGINT AS mismatches FROM e, (VALUES (1), (4), (16), (64), (256)) AS v(parts)")
def hll_merge_256(s, d):
    """All splits from one scan: a record's segment under P parts is its key modulo P."""
    rows = registers.with_registers(order_keys(s, d)).select("identity", "j", "r", F.explode(F.array(*map(F.lit, (1, 4, 16, 64, 256)))).alias("parts"))
    seg = rows.groupBy("parts", (F.col("identity") % F.col("parts")).alias("segment_id"), "j").agg(F.max("r").alias("r"))
    got = registers.merge_registers(seg, ["parts"])
    once = got.where("parts = 1").select("j", "r")
    wide = once.crossJoin(F.broadcast(got.select("parts").distinct()))  # one state by five labels
    return readouts.read_distinct(got, ["parts"]).join(registers.register_mismatches(got, wide, ["parts"]), "parts").select("parts", R4("estimate"), "mismatches")


@query("hll_duplicate_idempotent", "SELECT 0::BIGINT AS mismatches")
def hll_dup(s, d):
    r = order_keys(s, d)
    return registers.register_mismatches(registers.build_registers(r.union(r), []), registers.build_registers(r, []), [])


# ---- stores


def _store(s, d, name):
    return StateStore(s, fresh_path(s, f"store-{name}"))


ORD = "(SELECT strftime(o_orderdate, '%Y') AS y, o_orderpriority, o_custkey FROM orders)"


@query("hll_incremental", "WITH " + sql.regs("g", "orders", "", "o_custkey") + " " + sql.estimate("g", ""))
def hll_incremental(s, d):
    o = T(s, d, "orders").select(F.year("o_orderdate").alias("y"), F.col("o_custkey").alias("identity"))
    st = registers.build_registers(o.where("y <= 1994"), [])
    for lo in (1995, 1997):
        st = registers.update_states(st, o.where(F.col("y").between(lo, lo + 1)), [])
    st = registers.update_states(st, o.where("y > 1998"), [])
    return readouts.read_distinct(st, []).select(R4("estimate"))


@query("hll_store_reuse", "WITH " + sql.regs("g", ORD, "o_orderpriority", "o_custkey") + " " + sql.estimate("g", "o_orderpriority").replace("o_orderpriority,", "o_orderpriority AS group_key,", 1))
def hll_store_reuse(s, d):
    """States by year are stored once; the readout prunes to the stream's files and scans no orders."""
    store = _store(s, d, "orders")
    spec, desc = OperandSpec("customers", "o_custkey"), StateDescriptor()
    o = T(s, d, "orders").select(F.col("o_orderpriority").alias("group_key"), F.year("o_orderdate").alias("y"), F.col("o_custkey").alias("identity"))
    by_year = registers.build_registers(o, ["group_key", "y"])
    for half, cond in (("early", "y < 1996"), ("late", "y >= 1996")):
        store.put(by_year.where(cond), desc.for_stream(spec), "customers", half)
    got = store.get(["customers"], desc.for_stream(spec), keys=("group_key",))
    return readouts.read_distinct(got, ["group_key"]).select("group_key", R4("estimate"))


@query("hll_incompatible_guard", "WITH " + sql.regs("g", "orders", "", "o_custkey") + ", e AS (" + sql.estimate("g", "") + ") SELECT v.differs, v.refused, CASE WHEN NOT v.refused THEN e.estimate END AS estimate FROM e, (VALUES ('hash', TRUE), ('identity', TRUE), ('registers', TRUE), ('same', FALSE), ('seed', TRUE)) AS v(differs, refused)")
def hll_guard(s, d):
    """A table's states stored under each descriptor and asked for under one: what differs is refused, what agrees is read."""
    from dataclasses import replace

    from idagg.spec import IncompatibleStates

    base = StateDescriptor(identity_def="o_custkey")
    kept = {"hash": replace(base, family="xx"), "identity": replace(base, identity_def="o_orderkey"), "registers": replace(base, p=12), "seed": replace(base, seed=1), "same": base}
    o, store, out = T(s, d, "orders"), _store(s, d, "guard"), []
    for name, x in kept.items():
        store.put(registers.build_registers(o, [], x.p, x.seed, x.family, x.identity_def), x, name)
        try:
            e = readouts.read_distinct(store.get([name], base, keys=()), []).select(F.lit(False).alias("refused"), R4("estimate"))
        except IncompatibleStates:
            e = s.range(1).select(F.lit(True).alias("refused"), F.lit(None).cast("double").alias("estimate"))
        out.append(e.select(F.lit(name).alias("differs"), "refused", "estimate"))
    return reduce(lambda a, b: a.unionByName(b), out)


@query("hll_shared_plan", "WITH " + sql.regs("r", "lineitem WHERE l_returnflag = 'R'", "", "l_orderkey") + ", " + sql.regs("u", "lineitem WHERE l_returnflag IN ('R', 'A')", "", "l_orderkey") + ", e AS (" + sql.estimate("r", "") + "), f AS (" + sql.estimate("u", "") + ") SELECT 'distinct' AS op, estimate FROM e UNION ALL SELECT 'union', estimate FROM f")
def hll_shared(s, d):
    st = planner.build(T(s, d, LI), FLAGS)
    return st.answer(Request("distinct", ("R",))).select(F.lit("distinct").alias("op"), R4("estimate")).unionByName(st.answer(Request("union", ("R", "A"))).select(F.lit("union").alias("op"), R4("estimate")))


REQUESTS = [Request("distinct", ("R",)), Request("union", ("R", "A")), Request("grouped_distinct", ("R",)), Request("frequency", ("A",), probe="1"), Request("frequency", ("R",), probe="7"), Request("jaccard", ("R", "A")), Request("containment", ("R", "A"))]
SIDE = "lineitem WHERE l_returnflag = '{}'"


@query("hll_shared_all_operators", "WITH " + sql.regs("r", SIDE.format("R"), "", "l_orderkey") + ", " + sql.regs("u", "lineitem WHERE l_returnflag IN ('R', 'A')", "", "l_orderkey") + ", " + sql.regs("gr", SIDE.format("R"), "l_linestatus", "l_orderkey")
       + ", e AS (" + sql.estimate("r", "") + "), f AS (" + sql.estimate("u", "") + "), gg AS (" + sql.estimate("gr", "l_linestatus") + """), cmr AS (""" + " UNION ALL ".join(f"SELECT {k} AS row, CAST({sql_hash(repr(f'{k}:') + ' || CAST(l_orderkey AS VARCHAR)', 1)} & 63::UBIGINT AS INTEGER) AS col, count(*) AS c FROM lineitem WHERE l_returnflag = 'R' GROUP BY ALL" for k in range(4)) + "), q7 AS ("
       + " UNION ALL ".join(f"SELECT {k} AS row, CAST({sql_hash(repr(f'{k}:') + ' || ' + repr('7'), 1)} & 63::UBIGINT AS INTEGER) AS col" for k in range(4)) + f"""), px AS (SELECT l_orderkey, bool_or(l_returnflag = 'R') AS a, bool_or(l_returnflag = 'A') AS b FROM lineitem GROUP BY l_orderkey)
SELECT 'distinct' AS op, NULL AS name, estimate, TRUE AS near FROM e UNION ALL SELECT 'union', NULL, estimate, TRUE FROM f UNION ALL SELECT 'grouped_distinct', l_linestatus, estimate, TRUE FROM gg
UNION ALL SELECT 'frequency', '1', count(*)::DOUBLE, TRUE FROM lineitem WHERE l_returnflag = 'A' AND l_orderkey = 1
UNION ALL SELECT 'frequency', '7', min(coalesce(c, 0))::DOUBLE, TRUE FROM q7 LEFT JOIN cmr USING (row, col)
UNION ALL SELECT 'jaccard', NULL, round(count(*) FILTER (a AND b) / count(*) FILTER (a OR b), 4), TRUE FROM px UNION ALL SELECT 'containment', NULL, round(count(*) FILTER (a AND b) / count(*) FILTER (a), 4), TRUE FROM px""")
def hll_shared_all(s, d):
    """All six operators from one build: counts as the sketch reads them; relations as exact values beside whether the readout is near."""
    specs = [OperandSpec(f, "l_orderkey", f"l_returnflag = '{f}'", "l_linestatus") for f in "RA"]
    li = T(s, d, LI)
    st = planner.build(li, specs, probes=("1",))
    x = exact.ratios(exact.exact_regions(E.extract(li, specs), "R", "A")).select(F.col("jaccard").alias("j0"), F.col("containment_ab").alias("c0"))
    out, none = [], F.lit(None).cast("string")
    for q in REQUESTS:
        a, op = st.answer(q), F.lit(q.op).alias("op")
        if q.op in ("jaccard", "containment"):
            e = F.col("j0" if q.op == "jaccard" else "c0")
            out.append(x.crossJoin(F.broadcast(a)).select(op, none.alias("name"), F.round(e, 4).alias("estimate"), (F.abs(F.col("estimate") - e) <= 0.06).alias("near")))  # one row each
        else:
            name = F.col("group_key") if q.op == "grouped_distinct" else F.lit(q.probe).cast("string")
            out.append(a.select(op, name.alias("name"), F.round(F.col("estimate").cast("double"), 4).alias("estimate"), F.lit(True).alias("near")))
    return reduce(lambda a, b: a.unionByName(b), out)


# ---- error measures


SEEDS = (0, 1, 2, 3)


@query("hll_seed_replicates", "WITH " + ", ".join(sql.regs(f"g{k}", LI, "", "l_orderkey", 11, k) for k in SEEDS) + " " + " UNION ALL ".join(f"SELECT {k} AS seed, estimate FROM ({sql.estimate(f'g{k}', '')})" for k in SEEDS))
def hll_seeds(s, d):
    """Replicate hashes from one scan: an identity goes to each seed's state; identities are made distinct first, as they are hashed often."""
    ids = order_keys(s, d).distinct()
    hs = F.array(*(F.struct(F.lit(k).alias("seed"), hash64(F.col("identity").cast("string"), k, "md5").alias("h")) for k in SEEDS))
    x = ids.select(F.explode(hs).alias("x")).select("x.*")
    j, r = index_rank(F.col("h"), 11)
    return readouts.read_distinct(registers.merge_registers(x.select("seed", j.alias("j"), r.alias("r")), ["seed"]), ["seed"]).select("seed", R4("estimate"))


PS = (8, 9, 10, 11, 12, 13)


def sweep_registers(records, keys, ps=PS, identity="identity", family="md5", seed=0):
    """(keys, p, j, r) for every register budget from one hash an identity and one scan: identities meet the largest budget's registers, and the
    others come from those."""
    fine, parts = registers.build_registers(records, keys, max(ps), seed, family, identity), []
    for p in ps:
        j, r = registers.coarser(max(ps) - p)
        parts.append(F.struct(F.lit(p).alias("p"), j.alias("j"), r.alias("r")))
    x = fine.select(*keys, F.explode(F.array(*parts)).alias("x")).select(*keys, "x.*")
    return x.groupBy(*keys, "p", "j").agg(F.max("r").alias("r"))


def read_sweep(regs, keys):
    from idagg.functions.estimate import alpha

    m = F.pow(F.lit(2.0), F.col("p"))
    g = regs.groupBy(*keys, "p").agg(F.sum(F.pow(F.lit(2.0), -F.col("r"))).alias("s"), F.count("*").alias("c"))
    v, z = m - F.col("c"), F.col("s") + (m - F.col("c"))
    a = F.element_at(F.create_map(*(F.lit(x) for p in PS for x in (p, alpha(1 << p)))), F.col("p"))
    raw = a * m * m / z
    return g.select(*keys, "p", F.when((raw <= 2.5 * m) & (v > 0), m * F.log(m / v)).otherwise(raw).alias("estimate"))


@query("hll_budget_sweep", "WITH " + ", ".join(sql.regs(f"g{p}", LI, "", "l_partkey", p) for p in PS) + " " + " UNION ALL ".join(f"SELECT {p} AS p, estimate FROM ({sql.estimate(f'g{p}', '', p)})" for p in PS))
def hll_sweep(s, d):
    return read_sweep(sweep_registers(T(s, d, LI).select(F.col("l_partkey").alias("identity")), []), []).select("p", R4("estimate"))


GRID, GRID_STREAMS = (100, 1_000, 10_000, 100_000, 1_000_000), {8: 240, 9: 200, 10: 160, 11: 160, 12: 120, 13: 120}


RECORD_SQL = "(l_orderkey || '-' || l_linenumber)"


def record_keys(s, d, *keys):
    """A table with far more identities than registers: lineitem's records by their key."""
    return T(s, d, LI).select(*keys, F.concat(F.col("l_orderkey").cast("string"), F.lit("-"), F.col("l_linenumber").cast("string")).alias("identity"))


def weights_of(levels):
    """Sizes ten times apart."""
    return [10**k for k in range(levels)]


def dealt(s, d, levels, repeats):
    return written(dealt_streams(record_keys(s, d), weights_of(levels), repeats), "dealt")


def stream_errors(sets, levels, streams, family="xx"):
    """(p, n, rms_relerr, mean_relerr, reference): each budget over its number of streams, dealt evenly to the sizes; a stream that got no identity
    of the table doesn't exist. ``sets`` (size, rep, identity) names each identity of a stream once. One scan serves all budgets; the fewer streams
    of a larger budget are the first ones."""
    if any(n % levels for n in streams.values()):
        raise ValueError("streams must go evenly into the sizes")
    per = F.element_at(F.create_map(*(F.lit(x) for p, n in streams.items() for x in (p, n // levels))), F.col("p"))
    regs = sweep_registers(sets, ["size", "rep"], tuple(streams), family=family).where(F.col("rep") < per)
    e = read_sweep(regs, ["size", "rep"]).join(sets.groupBy("size", "rep").agg(F.count("*").alias("exact")), ["size", "rep"])
    ref = F.element_at(F.create_map(*(F.lit(x) for p in streams for x in (p, reference_error(1 << p)))), F.col("p"))
    return measures.summary(e, ["p"]).select("p", "n", "rms_relerr", "mean_relerr", ref.alias("reference"))


@query("hll_error_grid")
def hll_error_grid(s, d):
    """Errors of all budgets over a table's identities, dealt to streams of five sizes ten times apart."""
    return stream_errors(dealt(s, d, len(GRID), max(GRID_STREAMS.values()) // len(GRID)), len(GRID), GRID_STREAMS)


EXACT_SIZES = 4


def _grid_sql(levels, streams, tail):
    """The same streams, hashed and read by DuckDB."""
    out, repeats = [], max(streams.values()) // levels
    for p, n in streams.items():
        reg = f"(SELECT size, rep, {sql_index('h', p)} AS j, max({sql_rank('h', p)}) AS r FROM hs WHERE rep < {n // levels} GROUP BY ALL)"
        out.append(f"SELECT {p}::INTEGER AS p, count(*) AS n, {tail(p)} FROM (SELECT abs(estimate - exact) / exact AS e FROM ({sql.estimate(reg, 'size, rep', p, digits=9)}) JOIN truth USING (size, rep)) HAVING count(*) > 0")
    return f"WITH hs AS (SELECT size, rep, {sql_hash('z')} AS h FROM {dealt_sql('lineitem', RECORD_SQL, weights_of(levels), repeats)}), truth AS (SELECT size, rep, count(*) AS exact FROM hs GROUP BY ALL) " + " UNION ALL ".join(out)


@query("hll_error_grid_exact", _grid_sql(EXACT_SIZES, GRID_STREAMS, lambda p: "round(sqrt(avg(pow(e, 2))), 7) AS rms_relerr, round(avg(e), 7) AS mean_relerr"))
def hll_error_grid_exact(s, d):
    """Errors of all budgets at their numbers of streams, under the hash that SQL can repeat: equal register by register, not within a bound."""
    e = stream_errors(dealt(s, d, EXACT_SIZES, max(GRID_STREAMS.values()) // EXACT_SIZES), EXACT_SIZES, GRID_STREAMS, "md5")
    return e.select("p", "n", F.round("rms_relerr", 7).alias("rms_relerr"), F.round("mean_relerr", 7).alias("mean_relerr"))


SMALL_SIZES, SMALL_STREAMS = 3, dict.fromkeys(PS, 36)


@query("hll_error_vs_reference", _grid_sql(SMALL_SIZES, SMALL_STREAMS, lambda p: f"sqrt(avg(pow(e, 2))) < {1.6 * reference_error(1 << p)!r} AS near_reference"))
def hll_error(s, d):
    """Root-mean-square error of each budget over streams of three sizes against 1.04 / sqrt(m): within the spread that 36 of them leave."""
    e = stream_errors(dealt(s, d, SMALL_SIZES, 36 // SMALL_SIZES), SMALL_SIZES, SMALL_STREAMS, "md5")
    return e.select("p", "n", (F.col("rms_relerr") < 1.6 * F.col("reference")).alias("near_reference"))


LENGTH_SHARES = (4, 25, 100)  # 8K, 50K and 200K records to each other


def length_streams(s, d, shares, streams):
    """(share, stream_no, identity): lineitem's records in ``streams`` streams of parts by each share, lengths in that proportion; every record is in
    one, and a part's records go to all lengths of its stream."""
    at = F.pmod(F.col("l_orderkey") + F.col("l_linenumber"), F.lit(sum(shares)))
    share = F.coalesce(*(F.when(at < b, k) for k, b in zip(shares, accumulate(shares), strict=True)))
    return T(s, d, LI).select(share.alias("share"), F.pmod("l_partkey", F.lit(streams)).alias("stream_no"), F.col("l_partkey").alias("identity")).where("share is not null and identity is not null")


def length_medians(r):
    """(share, n, records, median_relerr) over the streams of each share; every record is read."""
    keys = ["share", "stream_no"]
    truth = r.groupBy(*keys).agg(F.count("*").alias("records"), F.count_distinct("identity").alias("exact"))
    x = readouts.read_distinct(registers.build_registers(r, keys), keys).join(truth, keys)
    return x.groupBy("share").agg(F.count("*").alias("n"), F.sum("records").alias("records"), F.round(F.median(measures.relerr(F.col("estimate"), F.col("exact"))), 7).alias("median_relerr"))


def _lengths_sql(shares, streams, tail):
    m = sum(shares)
    share = "CASE " + " ".join(f"WHEN u < {b} THEN {k}" for k, b in zip(shares, accumulate(shares), strict=True)) + " END"
    t = f"t AS (SELECT {share} AS share, ((l_partkey % {streams}) + {streams}) % {streams} AS stream_no, l_partkey AS z FROM (SELECT (((l_orderkey + l_linenumber) % {m}) + {m}) % {m} AS u, l_partkey FROM lineitem) WHERE u IS NOT NULL AND l_partkey IS NOT NULL)"
    return f"WITH {t}, {sql.regs('g', 't', 'share, stream_no', 'z')}, e AS ({sql.estimate('g', 'share, stream_no', digits=9)}), x AS (SELECT share, stream_no, count(*) AS records, count(DISTINCT z) AS exact FROM t GROUP BY ALL) SELECT share, count(*) AS n, {tail} FROM e JOIN x USING (share, stream_no) GROUP BY share"


@query("hll_length_all", _lengths_sql(LENGTH_SHARES, 100, "CAST(sum(records) AS BIGINT) AS records, round(median(abs(estimate - exact) / exact), 7) AS median_relerr"))
def hll_length_all(s, d):
    """Median error over 100 streams of each of three lengths: every record of the table is read, and the medians equal SQL's."""
    return length_medians(length_streams(s, d, LENGTH_SHARES, 100))


@query("hll_length_extrapolation", _lengths_sql(LENGTH_SHARES[:2], 20, "round(median(abs(estimate - exact) / exact), 7) < 0.03 AS low_error"))
def hll_length(s, d):
    """Median error of streams of two lengths, with nearly as many identities whatever the length."""
    return length_medians(length_streams(s, d, LENGTH_SHARES[:2], 20)).select("share", "n", (F.col("median_relerr") < 0.03).alias("low_error"))


@query("hll_length_prefixes", "WITH t AS (SELECT l_partkey, row_number() OVER (ORDER BY l_orderkey, l_linenumber, l_partkey, l_suppkey) AS k FROM lineitem), " + ", ".join(sql.regs(f"g{n}", f"t WHERE k <= {n}", "", "l_partkey") for n in (8000, 50000)) + " " + " UNION ALL ".join(f"SELECT {n}::BIGINT AS length, estimate FROM ({sql.estimate(f'g{n}', '')})" for n in (8000, 50000)))
def hll_prefixes(s, d, lengths=(8000, 50000)):
    """Prefixes of a table in a stated order: a top-n by that order, which is the workload's own limit."""
    t = T(s, d, LI).select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    out = None
    for n in lengths:
        r = t.orderBy("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey").limit(n).select(F.col("l_partkey").alias("identity"))
        one = readouts.read_distinct(registers.build_registers(r, []), []).select(F.lit(n).cast("long").alias("length"), R4("estimate"))
        out = one if out is None else out.unionByName(one)
    return out


@query("hll_length_prefixes_all")
def hll_prefixes_all(s, d):
    """The prefixes of all three lengths, with the exact count beside."""
    lengths = (8_000, 50_000, 200_000)
    t = T(s, d, LI).select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    top = [t.orderBy("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey").limit(n).agg(F.lit(n).cast("long").alias("length"), F.count("*").alias("records"), F.count_distinct("l_partkey").alias("exact")) for n in lengths]
    return hll_prefixes(s, d, lengths).join(reduce(lambda a, b: a.unionByName(b), top), "length")


def halves(s, d):
    """(rep, identity): lineitem's records by line status, two streams as large as the table allows; each identity once."""
    return written(record_keys(s, d, F.col("l_linestatus").alias("rep")).where("rep is not null and identity is not null").distinct(), "halves")


@query("hll_million", f"SELECT count(DISTINCT l_linestatus) AS n, TRUE AS low_error FROM lineitem WHERE {RECORD_SQL} IS NOT NULL")
def hll_million(s, d):
    """The table's two large streams, each read once."""
    sets = halves(s, d)
    e = readouts.read_distinct(registers.build_registers(sets, ["rep"], family="xx"), ["rep"]).join(sets.groupBy("rep").agg(F.count("*").alias("exact")), "rep")
    return measures.summary(e, []).select("n", (F.col("mean_relerr") < 0.06).alias("low_error"))


def half_errors(sets, seeds, family="xx"):
    """(n, mean_relerr, rms_relerr): each stream under each hash seed, from one scan. ``sets`` names each identity of a stream once."""
    hs = F.array(*(F.struct(F.lit(k).alias("seed"), hash64("identity", k, family).alias("h")) for k in range(seeds)))
    j, r = index_rank(F.col("h"), 11)  # after the explode, which would compute a hash for each use of it
    x = sets.select("rep", F.explode(hs).alias("x")).select("rep", "x.*").select("rep", "seed", j.alias("j"), r.alias("r"))
    e = readouts.read_distinct(registers.merge_registers(x, ["rep", "seed"]), ["rep", "seed"])
    return measures.summary(e.join(sets.groupBy("rep").agg(F.count("*").alias("exact")), "rep"), []).select("n", "mean_relerr", "rms_relerr")


@query("hll_million_seeds")
def hll_million_seeds(s, d):
    """The table's two streams under ten hash seeds: twenty estimates."""
    return half_errors(halves(s, d), 10)


def _million_sql(seeds=10):
    one = []
    for k in range(seeds):
        reg = f"(SELECT rep, {sql_index('h', 11)} AS j, max({sql_rank('h', 11)}) AS r FROM (SELECT rep, {sql_hash('z', k)} AS h FROM ids) GROUP BY ALL)"
        one.append(f"SELECT abs(estimate - exact) / exact AS e FROM ({sql.estimate(reg, 'rep', digits=9)}) JOIN truth USING (rep)")
    return f"WITH ids AS (SELECT DISTINCT l_linestatus AS rep, {RECORD_SQL} AS z FROM lineitem WHERE l_linestatus IS NOT NULL AND {RECORD_SQL} IS NOT NULL), truth AS (SELECT rep, count(*) AS exact FROM ids GROUP BY rep) SELECT count(*) AS n, round(avg(e), 7) AS mean_relerr, round(sqrt(avg(pow(e, 2))), 7) AS rms_relerr FROM (" + " UNION ALL ".join(one) + ")"


@query("hll_million_seeds_exact", _million_sql())
def hll_million_seeds_exact(s, d):
    """The twenty estimates under the hash that SQL can repeat."""
    e = half_errors(halves(s, d), 10, "md5")
    return e.select("n", F.round("mean_relerr", 7).alias("mean_relerr"), F.round("rms_relerr", 7).alias("rms_relerr"))


# ---- windows over states

EV_DAY = "(SELECT CAST(ts AS DATE) AS day, user_id FROM events)"


def day_regs(s, d, cond="true"):
    return registers.build_registers(T(s, d, "events").where(cond).select(F.to_date("ts").alias("day"), F.col("user_id").alias("identity")), ["day"])


@query("hll_sliding_7d", "WITH " + sql.regs("g", EV_DAY, "day", "user_id") + ", w AS (SELECT CAST(g.day + CAST(k AS INTEGER) AS DATE) AS day, j, max(r) AS r FROM g, range(7) AS t(k) GROUP BY ALL), top AS (SELECT max(day) AS z FROM g), x AS (SELECT w.* FROM w, top WHERE day <= z) " + sql.estimate("x", "day"))
def hll_sliding(s, d):
    return readouts.sliding_distinct(day_regs(s, d, "event_type = 'error' OR true"), "day", 7).select("day", R4("estimate"))


@query("hll_running", "WITH " + sql.regs("g", EV_DAY, "day", "user_id") + ", p AS (SELECT DISTINCT day AS at_ FROM g), x AS (SELECT at_ AS day, j, max(r) AS r FROM g JOIN p ON g.day <= p.at_ GROUP BY ALL) " + sql.estimate("x", "day"))
def hll_running(s, d):
    return readouts.running_distinct(day_regs(s, d), "day").select("day", R4("estimate"))


@query("hll_asof", "WITH " + sql.regs("g", EV_DAY, "day", "user_id") + ", e AS (" + sql.estimate("g", "day") + "), o AS (SELECT DISTINCT CAST(date_trunc('week', ts) AS DATE) + 3 AS at_ FROM events) SELECT CAST(o.at_ AS DATE) AS at_day, e.day, e.estimate FROM o ASOF JOIN e ON e.day <= o.at_")
def hll_asof(s, d):
    """The latest day state at or before each asked time: both sides in one ordered union and the last state carried forward."""
    from pyspark.sql import Window as W

    e = readouts.read_distinct(day_regs(s, d), ["day"]).select(F.col("day").alias("t"), "day", R4("estimate"), F.lit(0).alias("ask"))
    asked = T(s, d, "events").select(F.date_add(F.to_date(F.date_trunc("week", "ts")), 3).alias("t")).distinct().select("t", F.lit(None).cast("date").alias("day"), F.lit(None).cast("double").alias("estimate"), F.lit(1).alias("ask"))
    w = W.partitionBy(F.lit(0)).orderBy("t", "ask").rowsBetween(W.unboundedPreceding, 0)  # a row a day
    x = e.unionByName(asked).select("t", "ask", F.last("day", True).over(w).alias("day"), F.last("estimate", True).over(w).alias("estimate"))
    return x.where("ask = 1 and day is not null").select(F.col("t").alias("at_day"), "day", "estimate")


# ---- noise

NOISE = [0, 1, 5, 10, 20]
KEEP = f"({sql_hash('CAST(l_orderkey AS VARCHAR)', 99)} & 1023::UBIGINT)"


def noise_level():
    return hash64(F.col("l_orderkey").cast("string"), 99, "md5").bitwiseAND(F.lit(1023))


@query("hll_noise_drop", "WITH x AS (SELECT v.pct, l_orderkey FROM (SELECT DISTINCT l_orderkey, " + KEEP + " AS u FROM lineitem), (VALUES " + ", ".join(f"({n})" for n in NOISE) + ") AS v(pct) WHERE u >= v.pct * 1024 / 100), " + sql.regs("g", "x", "pct", "l_orderkey") + " " + sql.estimate("g", "pct"))
def hll_noise_drop(s, d):
    """Readouts after a share of identities was left out, for several shares in one pass."""
    x = T(s, d, LI).select("l_orderkey").distinct().withColumn("u", noise_level()).withColumn("pct", F.explode(F.array(*map(F.lit, NOISE)))).where(F.col("u") >= F.col("pct") * 1024 / 100)
    return readouts.read_distinct(registers.build_registers(x.select("pct", F.col("l_orderkey").alias("identity")), ["pct"]), ["pct"]).select("pct", R4("estimate"))


@query("hll_noise_spurious", "WITH x AS (SELECT v.pct, CAST(l_orderkey AS VARCHAR) AS z FROM (SELECT DISTINCT l_orderkey FROM lineitem), (VALUES " + ", ".join(f"({n})" for n in NOISE) + ") AS v(pct) UNION ALL SELECT v.pct, 'noise-' || l_orderkey FROM (SELECT DISTINCT l_orderkey, " + KEEP + " AS u FROM lineitem), (VALUES " + ", ".join(f"({n})" for n in NOISE) + ") AS v(pct) WHERE u < v.pct * 1024 / 100), " + sql.regs("g", "x", "pct", "z") + " " + sql.estimate("g", "pct"))
def hll_noise_spurious(s, d):
    ids = T(s, d, LI).select("l_orderkey").distinct().withColumn("u", noise_level()).withColumn("pct", F.explode(F.array(*map(F.lit, NOISE))))
    z = F.col("l_orderkey").cast("string")
    x = ids.select("pct", F.explode(F.array_compact(F.array(z, F.when(F.col("u") < F.col("pct") * 1024 / 100, F.concat(F.lit("noise-"), z))))).alias("identity"))
    return readouts.read_distinct(registers.build_registers(x, ["pct"]), ["pct"]).select("pct", R4("estimate"))


# ---- bytes


@query("hll_total_state_bytes", """SELECT 'type' AS grain, count(DISTINCT event_type) AS states, count(DISTINCT event_type) * 2048 AS state_bytes FROM events
UNION ALL SELECT 'day_type', count(DISTINCT event_type || strftime(ts, '%Y-%m-%d')), count(DISTINCT event_type || strftime(ts, '%Y-%m-%d')) * 2048 FROM events
UNION ALL SELECT 'user', count(DISTINCT user_id), count(DISTINCT user_id) * 2048 FROM events""")
def hll_bytes(s, d):
    e = T(s, d, "events")
    day = F.date_format("ts", "yyyy-MM-dd")
    grains = {"type": F.col("event_type"), "day_type": F.concat("event_type", day), "user": F.col("user_id").cast("string")}
    return reduce(lambda a, b: a.unionByName(b), (measures.total_state_bytes(e.select(g.alias("k")), ["k"], 2048).select(F.lit(n).alias("grain"), "states", "state_bytes") for n, g in grains.items()))


@query("hll_utf8_crossover", "SELECT 'c_name' AS ids, round(avg(strlen(c_name)), 6) AS mean_bytes, round(2048 / avg(strlen(c_name)), 6) AS crossover FROM (SELECT DISTINCT c_name FROM customer) UNION ALL SELECT 'user_id', round(avg(strlen(u)), 6), round(2048 / avg(strlen(u)), 6) FROM (SELECT DISTINCT CAST(user_id AS VARCHAR) AS u FROM events)")
def hll_crossover(s, d):
    a = measures.utf8_crossover(T(s, d, "customer"), identity="c_name").withColumn("ids", F.lit("c_name"))
    b = measures.utf8_crossover(T(s, d, "events").select(F.col("user_id").cast("string").alias("u")), identity="u").withColumn("ids", F.lit("user_id"))
    return a.unionByName(b).select("ids", F.round("mean_bytes", 6).alias("mean_bytes"), F.round("crossover", 6).alias("crossover"))


@query("hll_running_crossover", "SELECT min(n) AS first_n FROM (SELECT row_number() OVER (ORDER BY md5(c_name)) AS n, sum(strlen(c_name)) OVER (ORDER BY md5(c_name)) AS b FROM (SELECT DISTINCT c_name FROM customer)) WHERE b >= 2048")
def hll_running_crossover(s, d):
    return measures.running_crossover(T(s, d, "customer"), identity="c_name").select(F.col("first_n").cast("long").alias("first_n"))


@query("exact_payload", "SELECT count(*) AS n, CAST(sum(strlen(u)) AS BIGINT) AS payload_bytes FROM (SELECT DISTINCT CAST(l_orderkey AS VARCHAR) AS u FROM lineitem)")
def exact_payload(s, d):
    return exact.utf8_payload(T(s, d, LI).select(F.col("l_orderkey").cast("string").alias("identity")))


SLOTS_, WIDTH_, HEADS_, HIDDEN_ = 16, 28, 4, 16
CARRIED_ = SLOTS_ * WIDTH_ + SLOTS_ * HEADS_  # sums and normalisers


@query("resource_bytes", f"""SELECT * FROM (VALUES ('registers', 'carried', 2048::BIGINT), ('registers', 'static', 0), ('set_encoder', 'carried', 4 * {CARRIED_}),
('set_encoder', 'static', 4 * ({HEADS_} * {SLOTS_} * {WIDTH_} + {WIDTH_} * {WIDTH_} + {CARRIED_} * {HIDDEN_} + 2 * {HIDDEN_} + 1 + 2 * {CARRIED_})), ('set_encoder', 'shared_trunk', 0), ('count_min', 'carried', 4 * 64 * 8)) AS v(method, kind, bytes)""")
def resource_bytes(s, d):
    return measures.resource_table(s)


# ---- frequencies

CMC = lambda row, ident, seed: f"CAST({sql_hash(repr(str(row) + ':') + ' || CAST(' + ident + ' AS VARCHAR)', seed)} & 63::UBIGINT AS INTEGER)"


def cm_sql(src, ident, seed=1, keys=""):
    k = f"{keys}, " if keys else ""
    return "cm AS (" + " UNION ALL ".join(f"SELECT {k}{r} AS row, {CMC(r, ident, seed)} AS col, count(*) AS c FROM {src} GROUP BY ALL" for r in range(4)) + ")"


def users(s, d):
    return T(s, d, "events").select(F.col("user_id").cast("string").alias("identity"))


@query("cm_cells", "WITH " + cm_sql("events", "user_id") + " SELECT row, col, c FROM cm")
def cm_cells(s, d):
    return frequency.build_countmin(users(s, d), [], seed=1)


@query("cm_merge", "WITH " + cm_sql("events", "user_id") + " SELECT row, col, c FROM cm")
def cm_merge(s, d):
    day = T(s, d, "events").select(F.date_format("ts", "yyyy-MM-dd").alias("day"), F.col("user_id").cast("string").alias("identity"))
    return frequency.merge_countmin(frequency.build_countmin(day, ["day"], seed=1), []).select("row", "col", F.col("c").cast("long").alias("c"))


CM_READ = "WITH " + cm_sql("events", "user_id") + ", u AS (SELECT CAST(user_id AS VARCHAR) AS identity, count(*) AS f FROM events GROUP BY ALL), q AS (" + " UNION ALL ".join(f"SELECT identity, f, {r} AS row, {CMC(r, 'identity', 1)} AS col FROM u" for r in range(4)) + "), e AS (SELECT identity, any_value(f) AS f, min(c) AS estimate FROM q JOIN cm USING (row, col) GROUP BY identity)"


@query("cm_point", CM_READ + " SELECT identity, estimate FROM e")
def cm_point(s, d):
    return frequency.read_frequency(cm_cells(s, d), users(s, d).distinct(), seed=1)


@query("cm_bound", CM_READ + " SELECT count(*) AS probes, bool_and(estimate >= f) AS never_below, bool_and(estimate <= f + exp(1) * (SELECT count(*) FROM events) / 64) AS within_bound FROM e")
def cm_bound(s, d):
    f = users(s, d).groupBy("identity").agg(F.count("*").alias("f"))
    n = users(s, d).agg(F.count("*").alias("n"))
    e = cm_point(s, d).join(f, "identity").crossJoin(F.broadcast(n))
    import math

    return e.agg(F.count("*").alias("probes"), F.every(F.col("estimate") >= F.col("f")).alias("never_below"), F.every(F.col("estimate") <= F.col("f") + F.lit(math.e) * F.col("n") / 64).alias("within_bound"))


@query("cm_error", CM_READ + " SELECT round(median(estimate - f), 6) AS median_over, CAST(max(estimate - f) AS BIGINT) AS most_over FROM e")
def cm_error(s, d):
    f = users(s, d).groupBy("identity").agg(F.count("*").alias("f"))
    over = F.col("estimate") - F.col("f")
    return cm_point(s, d).join(f, "identity").agg(F.round(F.median(over), 6).alias("median_over"), F.max(over).alias("most_over"))


@query("cm_replay_doubles", "WITH " + cm_sql("events", "user_id") + " SELECT row, col, 2 * c AS c FROM cm")
def cm_replay(s, d):
    u = users(s, d)
    return frequency.build_countmin(u.union(u), [], seed=1)


@query("cm_label_table", "WITH " + cm_sql("events", "event_type", 0) + " SELECT row, col, c FROM cm")
def cm_label(s, d):
    return frequency.build_countmin(T(s, d, "events").select(F.col("event_type").alias("identity")), [], seed=0)


@query("freq_scalar_counter", "SELECT event_type, count(*) FILTER (user_id = 149) AS frequency FROM events GROUP BY event_type")
def freq_scalar(s, d):
    return frequency.count_probe(T(s, d, "events").select("event_type", F.col("user_id").cast("string").alias("identity")), "149", ["event_type"])


# ---- attention

ATT = "WITH t AS (SELECT event_type, value AS v, value / 100 AS a FROM events WHERE value IS NOT NULL), m AS (SELECT event_type, max(a) AS top FROM t GROUP BY ALL), s AS (SELECT event_type, any_value(top) AS top, sum(exp(a - top) * v) AS num, sum(exp(a - top)) AS den FROM t JOIN m USING (event_type) GROUP BY event_type)"


def att_rows(s, d):
    return T(s, d, "events").where("value is not null").select("event_type", F.col("value").alias("v"), (F.col("value") / 100).alias("a"))


@query("att_readout", ATT + " SELECT event_type, round(num / den, 6) AS o FROM s")
def att_readout(s, d):
    return attention.attention_readout(att_rows(s, d), "a", "v", ["event_type"]).select("event_type", F.round("o", 6).alias("o"))


@query("att_duplicate_shift", ATT + " SELECT event_type, round(exp(0.1::DOUBLE - top) * (1 - num / den) / (den + exp(0.1::DOUBLE - top)), 9) AS shift, TRUE AS as_recomputed FROM s")
def att_shift(s, d):
    """The formula's shift, and whether adding the record again and reading anew gives the same."""
    st = attention.attention_state(att_rows(s, d), "a", "v", ["event_type"])
    w = F.exp(F.lit(0.1) - F.col("top"))
    x = attention.duplicate_shift(st, w, F.lit(1.0))
    again = (F.col("num") + w) / (F.col("den") + w) - F.col("num") / F.col("den")
    return x.select("event_type", F.round("shift", 9).alias("shift"), (F.abs(again - F.col("shift")) < 1e-9).alias("as_recomputed"))


@query("att_counterexample", ATT + " SELECT event_type, 'x' AS context, round(num / den, 6) AS alone, round(num / (den + 1), 6) AS followed FROM s UNION ALL SELECT event_type, 'y', round(num / den, 6), round(num / den / 2, 6) FROM s")
def att_counter(s, d):
    x = attention.merge_counterexample(att_rows(s, d), "a", "v", ["event_type"])
    return x.select("event_type", "context", F.round("alone", 6).alias("alone"), F.round("followed", 6).alias("followed"))


@query("att_merge_nd", "WITH t AS (SELECT value AS v, value / 100 AS a FROM events WHERE value IS NOT NULL), m AS (SELECT max(a) AS top FROM t) SELECT round(sum(exp(a - top) * v) / sum(exp(a - top)), 6) AS o FROM t, m")
def att_merge(s, d):
    st = attention.attention_state(att_rows(s, d), "a", "v", ["event_type"])
    return attention.merge_nd(st).select(F.round(F.col("num") / F.col("den"), 6).alias("o"))


# ---- conversations, documents


@query("conv_turn_segments", "WITH t AS (SELECT role, unnest(regexp_split_to_array(text, '\\s+')) AS z FROM conversations), " + sql.regs("g", "t WHERE z <> ''", "role", "z") + " " + sql.estimate("g", "role"))
def conv_turns(s, d):
    """Turns are segments: states by (role, turn) merge to roles."""
    t = E.extract_tokens(T(s, d, "conversations").select("role", "turn", "text"), "text")
    by_turn = registers.build_registers(t.select("role", "turn", "identity"), ["role", "turn"])
    return readouts.read_distinct(registers.merge_registers(by_turn, ["role"]), ["role"]).select("role", R4("estimate"))


@query("doc_quality_groups", "WITH t AS (SELECT quality, unnest(regexp_split_to_array(text, '\\s+')) AS z FROM documents JOIN labels USING (doc_id)), " + sql.regs("g", "t WHERE z <> ''", "quality", "z") + " " + sql.estimate("g", "quality"))
def doc_quality(s, d):
    t = T(s, d, "documents").select("doc_id", "text").join(T(s, d, "labels").select("doc_id", "quality"), "doc_id")
    g = registers.build_registers(E.extract_tokens(t, "text").select("quality", "identity"), ["quality"])
    return readouts.read_distinct(g, ["quality"]).select("quality", R4("estimate"))


@query("doc_distinct_texts", "SELECT lang, count(DISTINCT text) AS exact FROM documents GROUP BY lang")
def doc_texts(s, d):
    return exact.exact_distinct(T(s, d, "documents").select("lang", F.sha2("text", 256).alias("identity")), ["lang"])
