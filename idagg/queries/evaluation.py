"""Relations, tasks, arms, statistics, learned and built-in baselines."""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import functions as F

from idagg.functions.hashing import sql_hash  # noqa: F401
from idagg.operators import builtin, exact, learned, registers, relation
from idagg.operators import extract as E
from idagg.operators.readouts import read_distinct
from idagg.plans import arms, measures, stats, tasks
from idagg.queries import query, sql
from idagg.queries.core import DAY, DAY_SQL, FLAG_REG, FLAGS, FULFIL, R4, read_sweep, sweep_registers  # noqa: F401
from idagg.sources.shared import written
from idagg.sources.tables import load_table as T
from idagg.spec import OperandSpec

# ---- relations: exact values, and whether the readouts are within their bounds

J_BOUND, C_BOUND, D_BOUND = 0.05, 0.06, 4 * 1.04 / 2048**0.5


def pair_sql(table, a, b, ident):
    return f"""WITH p AS (SELECT {ident}, bool_or({a}) AS a, bool_or({b}) AS b FROM {table} GROUP BY {ident}),
g AS (SELECT count(*) FILTER (a AND NOT b) AS n10, count(*) FILTER (b AND NOT a) AS n01, count(*) FILTER (a AND b) AS n11 FROM p)"""


RATIOS = "round(CASE WHEN n10 + n01 + n11 = 0 THEN 0.0 ELSE n11 / (n10 + n01 + n11) END, 9) AS jaccard, round(CASE WHEN n10 + n11 = 0 THEN 0.0 ELSE n11 / (n10 + n11) END, 9) AS containment"


def related(records, a, b, keys=(), **fit):
    keys = list(keys)
    regs = registers.build_registers(records, [*keys, "stream_id"])
    got = relation.relate(regs, a, b, keys, **fit)
    truth = exact.exact_regions(records, a, b, keys)
    x = exact.ratios(truth, keys).select(*keys, F.col("jaccard").alias("j0"), F.col("containment_ab").alias("c0"), "union_n")
    if keys:
        return x.join(got, keys)
    return x.crossJoin(F.broadcast(got))  # one row each


def within(d, *keys):
    return d.select(
        *keys, F.round("j0", 9).alias("jaccard"), F.round("c0", 9).alias("containment"), (F.abs(F.col("jaccard") - F.col("j0")) <= J_BOUND).alias("jaccard_near"),
        (F.abs(F.col("containment_ab") - F.col("c0")) <= C_BOUND).alias("containment_near"), "valid")


FLAG_HIST = "WITH " + sql.regs("a", "lineitem WHERE l_returnflag = 'R'", "", "l_orderkey") + ", " + sql.regs("b", "lineitem WHERE l_returnflag = 'A'", "", "l_orderkey") + """
SELECT u, v, count(*) AS h FROM (SELECT coalesce(a.r, 0)::INTEGER AS u, coalesce(b.r, 0)::INTEGER AS v FROM range(2048) AS t(j) LEFT JOIN a ON a.j = t.j LEFT JOIN b ON b.j = t.j) GROUP BY ALL"""


@query("rel_pair_histogram", FLAG_HIST)
def rel_hist(s, d):
    g = registers.build_registers(E.extract(T(s, d, "lineitem"), FLAGS), ["stream_id"])
    a, b = (g.where(F.col("stream_id") == k).select("j", "r") for k in "RA")
    return relation.pair_histogram(a, b, []).select("u", "v", "h")


TRUE3 = ", TRUE AS jaccard_near, TRUE AS containment_near, TRUE AS valid"


@query("rel_jaccard", FLAG_REG + f" SELECT {RATIOS}{TRUE3} FROM g")
def rel_jaccard(s, d):
    return within(related(E.extract(T(s, d, "lineitem"), FLAGS), "R", "A"))


PARTS = [OperandSpec("y6", "l_partkey", "l_shipdate >= '1996-01-01' AND l_shipdate < '1996-04-01'"), OperandSpec("y7", "l_partkey", "l_shipdate >= '1997-01-01' AND l_shipdate < '1997-04-01'")]


@query("rel_containment", pair_sql("lineitem", PARTS[0].where, PARTS[1].where, "l_partkey") + f" SELECT {RATIOS}{TRUE3} FROM g")
def rel_containment(s, d):
    return within(related(E.extract(T(s, d, "lineitem"), PARTS), "y6", "y7"))


@query("rel_overlap", FLAG_REG + " SELECT n10, n01, n11, TRUE AS near FROM g")
def rel_overlap(s, d):
    r = E.extract(T(s, d, "lineitem"), FLAGS)
    got = relation.relate(registers.build_registers(r, ["stream_id"]), "R", "A")
    x = exact.exact_regions(r, "R", "A").crossJoin(F.broadcast(got))
    size = F.col("n10") + F.col("n01") + F.col("n11")
    near = reduce(lambda a, b: a & b, (F.abs(F.col(e) - F.col(n)) <= 0.15 * size for e, n in (("only_a", "n10"), ("only_b", "n01"), ("overlap", "n11"))))
    return x.select("n10", "n01", "n11", near.alias("near"))


@query("rel_grouped", f"""WITH p AS (SELECT strftime(ts, '%Y-%m-%d') AS group_key, user_id, bool_or(event_type = 'error') AS a, bool_or(event_type = 'view') AS b FROM events GROUP BY ALL),
g AS (SELECT group_key, count(*) FILTER (a AND NOT b) AS n10, count(*) FILTER (b AND NOT a) AS n01, count(*) FILTER (a AND b) AS n11 FROM p GROUP BY group_key)
SELECT group_key, {RATIOS}, TRUE AS near, TRUE AS valid FROM g""")
def rel_grouped(s, d):
    """Bounds of small sets are wider: a few tens of users a day."""
    specs = [OperandSpec(t, "user_id", f"event_type = '{t}'", "date_format(ts, 'yyyy-MM-dd')") for t in ("error", "view")]
    x = related(E.extract(T(s, d, "events"), specs), "error", "view", ["group_key"])
    near = (F.abs(F.col("jaccard") - F.col("j0")) <= 0.12) & (F.abs(F.col("containment_ab") - F.col("c0")) <= 0.15)
    return x.select("group_key", F.round("j0", 9).alias("jaccard"), F.round("c0", 9).alias("containment"), near.alias("near"), "valid")


@query("rel_matrix", """WITH i AS (SELECT DISTINCT o_orderpriority AS k, o_custkey FROM orders WHERE o_orderstatus = 'F'), n AS (SELECT k, count(*) AS n FROM i GROUP BY k),
x AS (SELECT p.k AS a, q.k AS b, count(*) AS c FROM i p JOIN i q ON p.o_custkey = q.o_custkey AND p.k < q.k GROUP BY ALL)
SELECT a, b, round(c / (na.n + nb.n - c), 9) AS jaccard, TRUE AS near FROM x JOIN n na ON na.k = a JOIN n nb ON nb.k = b""")
def rel_matrix(s, d):
    """All pairs of priorities: pairs of states for the readouts; the exact side counts co-occurrence from each customer's short list."""
    o = T(s, d, "orders").where("o_orderstatus = 'F'").select(F.col("o_orderpriority").alias("stream_id"), F.col("o_custkey").alias("identity"))
    m = relation.relation_matrix(registers.build_registers(o, ["stream_id"]))
    lists = o.groupBy("identity").agg(F.array_sort(F.collect_set("stream_id")).alias("ks"))  # at most five priorities
    pairs = F.flatten(F.transform("ks", lambda a: F.transform(F.filter("ks", lambda b: a < b), lambda b: F.struct(a.alias("a"), b.alias("b")))))
    c = lists.select(F.explode(pairs).alias("p")).groupBy("p.a", "p.b").agg(F.count("*").alias("c"))
    n = o.groupBy("stream_id").agg(F.count_distinct("identity").alias("n"))
    x = c.join(n.withColumnsRenamed({"stream_id": "a", "n": "na"}), "a").join(n.withColumnsRenamed({"stream_id": "b", "n": "nb"}), "b")
    j = F.col("c") / (F.col("na") + F.col("nb") - F.col("c"))
    return x.withColumn("j0", j).join(m, ["a", "b"]).select("a", "b", F.round("j0", 9).alias("jaccard"), (F.abs(F.col("jaccard") - F.col("j0")) <= J_BOUND + 0.01).alias("near"))


@query("rel_nested_boundary", pair_sql("orders", FULFIL[0].where, FULFIL[1].where, "o_custkey") + f" SELECT {RATIOS}, TRUE AS jaccard_near, TRUE AS containment_near, TRUE AS at_zero, TRUE AS valid FROM g")
def rel_nested(s, d):
    x = related(E.extract(T(s, d, "orders"), FULFIL), "urgent", "all")
    return within(x.withColumn("at_zero", F.col("only_a") == 0), "at_zero").select("jaccard", "containment", "jaccard_near", "containment_near", "at_zero", "valid")


@query("rel_identical", "SELECT 1.0::DOUBLE AS jaccard, TRUE AS at_zero, TRUE AS valid")
def rel_identical(s, d):
    specs = [OperandSpec(t, "user_id", f"event_type = '{t}'") for t in ("click", "click2")]
    specs[1] = OperandSpec("click2", "user_id", "event_type = 'click'")
    g = registers.build_registers(E.extract(T(s, d, "events"), specs), ["stream_id"])
    return relation.relate(g, "click", "click2").select(F.round("jaccard", 6).alias("jaccard"), ((F.col("only_a") == 0) & (F.col("only_b") == 0)).alias("at_zero"), "valid")


@query("rel_disjoint", "SELECT TRUE AS no_overlap, TRUE AS valid")
def rel_disjoint(s, d):
    specs = [OperandSpec("even", "l_orderkey", "l_orderkey % 2 = 0"), OperandSpec("odd", "l_orderkey", "l_orderkey % 2 = 1")]
    g = registers.build_registers(E.extract(T(s, d, "lineitem"), specs), ["stream_id"])
    return relation.relate(g, "even", "odd").select((F.col("jaccard") <= 0.03).alias("no_overlap"), "valid")


@query("rel_diagnostics", "SELECT 10::BIGINT AS pairs, 10::BIGINT AS valid_fits, TRUE AS few_sweeps, TRUE AS small_residual")
def rel_diagnostics(s, d):
    o = T(s, d, "orders").select(F.col("o_orderpriority").alias("stream_id"), F.col("o_custkey").alias("identity"))
    g = registers.build_registers(o, ["stream_id"])
    a = g.withColumnRenamed("stream_id", "a")
    p = g.select(F.col("stream_id").alias("b")).distinct()
    x = a.join(p, F.col("a") < F.col("b"))
    y = a.withColumnsRenamed({"a": "b"}).join(p.withColumnRenamed("b", "a"), F.col("a") < F.col("b"))
    f = relation.fit_pairs(relation.pair_histogram(x, y, ["a", "b"]), ["a", "b"])
    return f.agg(F.count("*").alias("pairs"), F.count_if("valid").alias("valid_fits"), (F.max("iterations") <= 24).alias("few_sweeps"), (F.max("residual") <= 5e-4).alias("small_residual"))


@query("rel_invalid_stays_null", "SELECT NULL::DOUBLE AS jaccard, NULL::DOUBLE AS containment_ab, FALSE AS valid")
def rel_invalid(s, d):
    g = registers.build_registers(E.extract(T(s, d, "lineitem"), FLAGS), ["stream_id"])
    return relation.relate(g, "R", "A", sweeps=0).select("jaccard", "containment_ab", "valid")


@query("rel_inclusion_exclusion", "WITH " + ", ".join(sql.regs(n, f"lineitem WHERE l_returnflag IN ({f})", "", "l_orderkey") for n, f in (("a", "'R'"), ("b", "'A'"), ("c", "'R', 'A'"))) + ", " + ", ".join(f"e{n} AS ({sql.estimate(n, '', digits=8)})" for n in "abc") + " SELECT round(ea.estimate + eb.estimate - ec.estimate, 4) AS overlap FROM ea, eb, ec")
def rel_ie(s, d):
    """A comparator that no readout uses."""
    g = registers.build_registers(E.extract(T(s, d, "lineitem"), FLAGS), ["stream_id"])
    one = read_distinct(g, ["stream_id"]).agg(F.sum("estimate").alias("n"))
    u = read_distinct(registers.merge_registers(g, []), []).withColumnRenamed("estimate", "u")
    return one.crossJoin(u).select(F.round(relation.inclusion_exclusion(F.col("n"), F.lit(0.0), F.col("u")), 4).alias("overlap"))


@query("doc_vocab_similarity", """WITH t AS (SELECT DISTINCT source, unnest(regexp_split_to_array(text, '\\s+')) AS z FROM documents WHERE source IN ('src0', 'src1', 'src2', 'src3')),
n AS (SELECT source, count(*) AS n FROM t WHERE z <> '' GROUP BY source), x AS (SELECT p.source AS a, q.source AS b, count(*) AS c FROM t p JOIN t q ON p.z = q.z AND p.source < q.source WHERE p.z <> '' GROUP BY ALL)
SELECT a, b, round(c / (na.n + nb.n - c), 9) AS jaccard, TRUE AS near FROM x JOIN n na ON na.source = a JOIN n nb ON nb.source = b""")
def doc_vocab(s, d):
    t = E.extract_tokens(T(s, d, "documents").where(F.col("source").isin("src0", "src1", "src2", "src3")).select(F.col("source").alias("stream_id"), "text"), "text").select("stream_id", "identity")
    m = relation.relation_matrix(registers.build_registers(t, ["stream_id"]))
    lists = t.groupBy("identity").agg(F.array_sort(F.collect_set("stream_id")).alias("ks"))
    pairs = F.flatten(F.transform("ks", lambda a: F.transform(F.filter("ks", lambda b: a < b), lambda b: F.struct(a.alias("a"), b.alias("b")))))
    c = lists.select(F.explode(pairs).alias("p")).groupBy("p.a", "p.b").agg(F.count("*").alias("c"))
    n = t.groupBy("stream_id").agg(F.count_distinct("identity").alias("n"))
    x = c.join(n.withColumnsRenamed({"stream_id": "a", "n": "na"}), "a").join(n.withColumnsRenamed({"stream_id": "b", "n": "nb"}), "b")
    return x.withColumn("j0", F.col("c") / (F.col("na") + F.col("nb") - F.col("c"))).join(m, ["a", "b"]).select("a", "b", F.round("j0", 9).alias("jaccard"), (F.abs(F.col("jaccard") - F.col("j0")) <= J_BOUND).alias("near"))


# ---- tasks

W = "WITH " + tasks.WINDOW_SQL
TK = "WITH " + tasks.TASK_SQL
WIN = f", win AS (SELECT window_id, count(*) AS n_records, count(DISTINCT identity) AS n_items, CAST(ceil(sum(chars) / 4) AS BIGINT) AS token_proxy FROM wr GROUP BY window_id)"
LIM = ", lim AS (SELECT CAST(floor(quantile_cont(token_proxy::DOUBLE, 0.54)) AS BIGINT) AS limit_tokens FROM win)"


def rec(s, d):
    return tasks.window_records(s, d)


def all_tasks(s, d):
    return tasks.generate(tasks.targets(rec(s, d)))


def unit_sql(expr):
    return tasks._sql_unit(expr)


@query("task_windows", W + WIN + f" SELECT window_id, n_records, n_items, token_proxy, CASE WHEN {unit_sql('window_id')} < 0.15 THEN 'validation' ELSE 'test' END AS split FROM win")
def task_windows(s, d):
    return tasks.windows(rec(s, d))


HM = lambda e: f"CAST(({sql_hash(e, tasks.GENERATOR_SEED)})::HUGEINT - CASE WHEN {sql_hash(e, tasks.GENERATOR_SEED)} > 9223372036854775807::UBIGINT THEN 18446744073709551616::HUGEINT ELSE 0 END AS BIGINT)"  # noqa: E731  as a signed number


@query("task_candidates", W + f", it AS (SELECT DISTINCT window_id, identity FROM wr), n AS (SELECT window_id, count(*) AS n FROM it GROUP BY ALL), rk AS (SELECT window_id, identity, CAST(row_number() OVER (PARTITION BY window_id ORDER BY {HM(chr(34) + 'window_id' + chr(34) + chr(32) + '|| ' + chr(39) + '/' + chr(39) + ' || identity')}, identity) AS INTEGER) AS rank FROM it) SELECT rk.* FROM rk JOIN n USING (window_id) WHERE rank <= {tasks.MAX_CANDIDATES} AND n >= {tasks.MIN_ITEMS}")
def task_candidates(s, d):
    return tasks.candidates(rec(s, d))


@query("task_generate", TK + " SELECT task_id, window_id, operator, group_key, probe, variant, threshold, round(exact, 9) AS exact, gold FROM tasks")
def task_generate(s, d):
    return all_tasks(s, d).withColumn("exact", F.round("exact", 9))


MATCH = f", mt AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY window_id ORDER BY {HM(repr('match:') + ' || task_id')}, task_id) AS k FROM tasks) WHERE k = 1)"


@query("task_matched_one_per_window", TK + MATCH + " SELECT window_id, task_id, operator FROM mt")
def task_matched(s, d):
    return tasks.matched(all_tasks(s, d)).select("window_id", "task_id", "operator")


@query("task_context_split", W + WIN + LIM + " SELECT token_proxy <= limit_tokens AS fits, count(*) AS windows FROM win, lim GROUP BY ALL")
def task_split(s, d):
    w = tasks.windows(rec(s, d))
    return w.crossJoin(F.broadcast(tasks.context_limit(w))).groupBy((F.col("token_proxy") <= F.col("limit_tokens")).alias("fits")).agg(F.count("*").alias("windows"))


@query("task_joint_eligible", TK + WIN + LIM + MATCH + " SELECT task_id, window_id FROM mt JOIN win USING (window_id), lim WHERE token_proxy <= limit_tokens AND ceil(token_proxy * 1.1) <= limit_tokens * 1.2")
def task_joint(s, d):
    """Matched tasks that fit the plain prompt's limit and the longer one of chain of thought (a tenth more text, a fifth more room)."""
    r = rec(s, d)
    w = tasks.windows(r)
    m = tasks.matched(tasks.generate(tasks.targets(r))).join(w.select("window_id", "token_proxy"), "window_id").crossJoin(F.broadcast(tasks.context_limit(w)))
    return m.where((F.col("token_proxy") <= F.col("limit_tokens")) & (F.ceil(F.col("token_proxy") * 1.1) <= F.col("limit_tokens") * 1.2)).select("task_id", "window_id")


# ---- arms

SCORE = "CAST(CASE WHEN answer = gold THEN 1 ELSE 0 END AS INTEGER) AS score"


def rows_of(a):
    return a.select("task_id", "answer", "status", "score")


@query("arm_exact", TK + f", a AS (SELECT task_id, gold, CASE WHEN exact > threshold THEN 'act' ELSE 'watch' END AS answer FROM tasks) SELECT task_id, answer, 'ok' AS status, {SCORE} FROM a")
def arm_exact(s, d):
    return rows_of(arms.exact_arm(all_tasks(s, d)))


@query("arm_counterfactual", TK + " SELECT task_id, CASE WHEN gold = 'act' THEN 'watch' ELSE 'act' END AS answer, 'ok' AS status, 1::INTEGER AS score FROM tasks")
def arm_counterfactual(s, d):
    return rows_of(arms.counterfactual_arm(all_tasks(s, d)))


@query("arm_aggregate_only", TK + f", a AS (SELECT task_id, gold, CASE WHEN {unit_sql(repr('aggregate:') + ' || task_id')} < 0.5 THEN 'act' ELSE 'watch' END AS answer FROM tasks) SELECT task_id, answer, 'ok' AS status, {SCORE} FROM a")
def arm_aggregate_only(s, d):
    return rows_of(arms.aggregate_only_arm(all_tasks(s, d)))


@query("arm_policy_only", TK + f", a AS (SELECT task_id, gold, {unit_sql(repr('parse:') + ' || task_id')} >= 0.4 AS ok, CASE WHEN {unit_sql(repr('policy:') + ' || task_id')} < 0.5 THEN 'act' ELSE 'watch' END AS w FROM tasks), b AS (SELECT task_id, gold, CASE WHEN ok THEN w END AS answer, CASE WHEN ok THEN 'ok' ELSE 'failed' END AS status FROM a) SELECT task_id, answer, status, {SCORE} FROM b")
def arm_policy_only(s, d):
    return rows_of(arms.policy_only_arm(all_tasks(s, d), 0.4))


def ctx_sql(how):
    return TK + WIN + LIM + ", " + arms.context_sql(how) + f""", a AS (SELECT task_id, gold, token_proxy <= limit_tokens AS ok, CASE WHEN estimate > threshold THEN 'act' ELSE 'watch' END AS w
FROM tasks JOIN ce USING (window_id, operator) JOIN win USING (window_id), lim), b AS (SELECT task_id, gold, CASE WHEN ok THEN w END AS answer, CASE WHEN ok THEN 'ok' ELSE 'failed' END AS status FROM a)
SELECT task_id, answer, status, {SCORE} FROM b"""


def ctx(s, d, how):
    r = rec(s, d)
    return arms.context_arm(tasks.generate(tasks.targets(r)), r, tasks.windows(r), how)


@query("arm_context_direct", ctx_sql("direct"))
def arm_direct(s, d):
    return rows_of(ctx(s, d, "direct"))


@query("arm_context_cot", ctx_sql("cot"))
def arm_cot(s, d):
    return rows_of(ctx(s, d, "cot"))


@query("arm_context_guided", ctx_sql("guided"))
def arm_guided(s, d):
    return rows_of(ctx(s, d, "guided"))


ST = ", st AS (SELECT window_id, 'a' AS stream_id, identity FROM wr WHERE in_a UNION ALL SELECT window_id, 'b', identity FROM wr WHERE in_b)"
CM = ", cmw AS (" + " UNION ALL ".join(f"SELECT window_id, {r} AS row, ({sql_hash(repr(str(r) + ':') + ' || identity', 1)} & 63::UBIGINT)::INTEGER AS col, count(*) AS c FROM wr GROUP BY ALL" for r in range(4)) + "), zq AS (" + " UNION ALL ".join(f"SELECT window_id, {r} AS row, ({sql_hash(repr(str(r) + ':') + ' || z', 1)} & 63::UBIGINT)::INTEGER AS col FROM picks" for r in range(4)) + "), zf AS (SELECT window_id, min(c)::DOUBLE AS estimate FROM zq JOIN cmw USING (window_id, row, col) GROUP BY window_id)"
EVID = (
    TK + ST + ", " + sql.regs("ra", "st WHERE stream_id = 'a'", "window_id", "identity") + ", " + sql.regs("ru", "st", "window_id", "identity") + ", "
    + sql.regs("rg", "(SELECT wr.window_id, identity FROM wr JOIN picks ON wr.window_id = picks.window_id AND group_key = g)", "window_id", "identity") + CM
    + ", ev AS (SELECT window_id, 'distinct' AS operator, estimate FROM (" + sql.estimate("ra", "window_id", digits=9) + ") UNION ALL SELECT window_id, 'union', estimate FROM (" + sql.estimate("ru", "window_id", digits=9)
    + ") UNION ALL SELECT window_id, 'grouped_distinct', estimate FROM (" + sql.estimate("rg", "window_id", digits=9) + ") UNION ALL SELECT window_id, 'frequency', estimate FROM zf)")


@query("arm_budgeted", EVID + f", a AS (SELECT task_id, gold, CASE WHEN coalesce(estimate, 0.0) > threshold THEN 'act' ELSE 'watch' END AS answer FROM tasks LEFT JOIN ev USING (window_id, operator) WHERE operator NOT IN ('jaccard', 'containment')) SELECT task_id, answer, 'ok' AS status, {SCORE} FROM a")
def arm_budgeted(s, d):
    r = rec(s, d)
    t = tasks.generate(tasks.targets(r)).where("operator not in ('jaccard', 'containment')")
    return rows_of(arms.budgeted_arm(t, arms.budgeted_evidence(r, relations=False)))


@query("arm_budgeted_relations", TK + " SELECT operator, count(*) AS n, TRUE AS mostly_right FROM tasks WHERE operator IN ('jaccard', 'containment') GROUP BY operator")
def arm_budgeted_rel(s, d):
    r = rec(s, d)
    t = tasks.generate(tasks.targets(r)).where("operator in ('jaccard', 'containment')")
    return arms.budgeted_arm(t, arms.budgeted_evidence(r)).groupBy("operator").agg(F.count("*").alias("n"), (F.avg("score") > 0.75).alias("mostly_right"))


@query("arm_code_bulk", TK + " SELECT task_id, gold AS answer, 'ok' AS status, 1::INTEGER AS score FROM tasks")
def arm_code_bulk(s, d):
    r = rec(s, d)
    return rows_of(arms.code_arm_bulk(tasks.generate(tasks.targets(r)), r))


CODE_N = 12
CODE = f", cs AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY window_id, operator ORDER BY {HM(repr('code:') + ' || task_id')}, task_id) AS k FROM tasks) ORDER BY k, {HM(repr('code:') + ' || task_id')} LIMIT {CODE_N})"


@query("arm_code_generated_sql", TK + CODE + " SELECT task_id, gold AS answer, 'ok' AS status, 1::INTEGER AS score FROM cs")
def arm_code(s, d):
    """One generated program and job a task, over the first few of the fixed subset."""
    r = written(rec(s, d), "records")
    return rows_of(arms.code_arm(s, tasks.code_subset(tasks.generate(tasks.targets(r)), CODE_N), r))


CODE_ALL = CODE.replace(f"LIMIT {CODE_N}", f"LIMIT {tasks.CODE_TASKS}")


@query("arm_code_all_tasks", TK + CODE_ALL + " SELECT task_id, gold AS answer, 'ok' AS status, 1::INTEGER AS score FROM cs")
def arm_code_all(s, d):
    """One generated program and job a task, over the whole fixed subset. Records are written by window, so that a program reads its window's only."""
    r = written(rec(s, d).repartitionByRange("window_id").sortWithinPartitions("window_id"), "records")
    t = written(tasks.code_subset(tasks.generate(tasks.targets(r))), "code-tasks")
    return rows_of(arms.code_arm(s, t, r))


def arm_rows(s, d):
    """Rows of six arms that need no fit, over all tasks."""
    r = rec(s, d)
    t = tasks.generate(tasks.targets(r))
    w = tasks.windows(r)
    got = [arms.exact_arm(t), arms.counterfactual_arm(t), arms.aggregate_only_arm(t), arms.policy_only_arm(t, 0.4), arms.context_arm(t, r, w, "direct"), arms.context_arm(t, r, w, "cot")]
    return reduce(lambda a, b: a.unionByName(b), got)


ARMS = (
    TK + WIN + LIM + ", " + arms.context_sql("direct") + ", " + arms.context_sql("cot").replace("per AS", "per2 AS").replace("FROM per ", "FROM per2 ").replace("cs AS", "cs2 AS").replace("FROM cs", "FROM cs2").replace("ce AS", "ce2 AS")
    + f""", ar AS (
SELECT task_id, window_id, 'exact' AS arm, 'ok' AS status, NULL AS failure_stage, 1::INTEGER AS score, 1 AS tok FROM tasks
UNION ALL SELECT task_id, window_id, 'counterfactual', 'ok', NULL, 1, 1 FROM tasks
UNION ALL SELECT task_id, window_id, 'aggregate_only', 'ok', NULL, CAST((CASE WHEN {unit_sql(repr('aggregate:') + ' || task_id')} < 0.5 THEN 'act' ELSE 'watch' END) = gold AS INTEGER), 1 FROM tasks
UNION ALL SELECT task_id, window_id, 'policy_only', CASE WHEN {unit_sql(repr('parse:') + ' || task_id')} >= 0.4 THEN 'ok' ELSE 'failed' END, CASE WHEN {unit_sql(repr('parse:') + ' || task_id')} >= 0.4 THEN NULL ELSE 'parsing' END,
  CAST({unit_sql(repr('parse:') + ' || task_id')} >= 0.4 AND (CASE WHEN {unit_sql(repr('policy:') + ' || task_id')} < 0.5 THEN 'act' ELSE 'watch' END) = gold AS INTEGER), 1 FROM tasks
UNION ALL SELECT task_id, window_id, 'ctx_direct', CASE WHEN token_proxy <= limit_tokens THEN 'ok' ELSE 'failed' END, CASE WHEN token_proxy <= limit_tokens THEN NULL ELSE 'context_packing' END,
  CAST(token_proxy <= limit_tokens AND (CASE WHEN estimate > threshold THEN 'act' ELSE 'watch' END) = gold AS INTEGER), 1 FROM tasks JOIN ce USING (window_id, operator) JOIN win USING (window_id), lim
UNION ALL SELECT task_id, window_id, 'ctx_cot', CASE WHEN token_proxy <= limit_tokens THEN 'ok' ELSE 'failed' END, CASE WHEN token_proxy <= limit_tokens THEN NULL ELSE 'context_packing' END,
  CAST(token_proxy <= limit_tokens AND (CASE WHEN estimate > threshold THEN 'act' ELSE 'watch' END) = gold AS INTEGER), 60 FROM tasks JOIN ce2 USING (window_id, operator) JOIN win USING (window_id), lim)""")


@query("arm_cost_per_task", ARMS + " SELECT arm, count(*) AS n, 1.0::DOUBLE AS calls, avg(tok)::DOUBLE AS out_tokens FROM ar GROUP BY arm")
def arm_cost(s, d):
    return arms.cost_per_task(arm_rows(s, d))


@query("stat_accuracy", ARMS + " SELECT arm, count(*) AS n, round(avg(score), 9) AS accuracy FROM ar GROUP BY arm")
def stat_accuracy(s, d):
    return stats.accuracy(arm_rows(s, d)).withColumn("accuracy", F.round("accuracy", 9))


@query("stat_failures", ARMS + " SELECT arm, failure_stage, count(*) AS n FROM ar WHERE status = 'failed' GROUP BY ALL")
def stat_failures(s, d):
    return stats.failures(arm_rows(s, d))


@query("stat_paired_diff", ARMS + " SELECT round(100 * avg(a.score - b.score), 6) AS diff_pp FROM ar a JOIN ar b USING (task_id) WHERE a.arm = 'ctx_cot' AND b.arm = 'ctx_direct'")
def stat_paired(s, d):
    return stats.paired(arm_rows(s, d), "ctx_cot", "ctx_direct").agg(F.round(100 * F.avg("diff"), 6).alias("diff_pp"))


@query("stat_flips", EVID + ", a AS (SELECT operator, (exact > threshold) <> (coalesce(estimate, 0.0) > threshold) AS flip FROM tasks LEFT JOIN ev USING (window_id, operator) WHERE operator NOT IN ('jaccard', 'containment')) SELECT operator, count(*) AS n, count(*) FILTER (flip) AS flips FROM a GROUP BY operator")
def stat_flips(s, d):
    """Decisions that the sketch's error turns: exact and budgeted evidence fall on different sides of the threshold."""
    r = rec(s, d)
    t = tasks.generate(tasks.targets(r)).where("operator not in ('jaccard', 'containment')")
    e = t.join(arms.budgeted_evidence(r, relations=False), ["window_id", "operator"])
    return e.groupBy("operator").agg(F.count("*").alias("n"), F.count_if((F.col("exact") > F.col("threshold")) != (F.col("estimate") > F.col("threshold"))).alias("flips"))


@query("stat_window_sums", ARMS + " SELECT arm, window_id, sum(score)::DOUBLE AS s, count(*) AS n FROM ar GROUP BY ALL")
def stat_sums(s, d):
    return stats.window_sums(arm_rows(s, d))


@query("stat_guards", "SELECT * FROM (VALUES ('clean', FALSE), ('duplicate', TRUE), ('missing', TRUE), ('not_terminal', TRUE)) AS v(rows_are, refused)")
def stat_guards(s, d):
    good = [("t1", "w", "a", "ok"), ("t1", "w", "b", "ok"), ("t2", "w", "a", "failed"), ("t2", "w", "b", "ok")]
    cases = {"clean": good, "duplicate": [*good, good[0]], "missing": good[:3], "not_terminal": [*good[:3], ("t2", "w", "b", "running")]}
    out = []
    for name, rows in cases.items():
        try:
            stats.validate(s.createDataFrame(rows, "task_id string, window_id string, arm string, status string"))
            out.append((name, False))
        except stats.IntegrityError:
            out.append((name, True))
    return s.createDataFrame(out, "rows_are string, refused boolean")


PV = [("c1", 0.0001), ("c2", 0.04), ("c3", 0.03), ("c4", 0.005), ("c5", 0.5), ("c6", 0.04), ("c7", 0.0002), ("c8", 0.9)]


@query("stat_holm", "WITH v AS (SELECT * FROM (VALUES " + ", ".join(f"('{c}', {p}::DOUBLE)" for c, p in PV) + ") AS v(contrast, p)), s AS (SELECT contrast, p, p * (count(*) OVER () - row_number() OVER (ORDER BY p, contrast) + 1) AS x FROM v) SELECT contrast, p, round(least(1.0, max(x) OVER (ORDER BY p, contrast ROWS UNBOUNDED PRECEDING)), 9) AS p_holm FROM s")
def stat_holm(s, d):
    return stats.holm(s.createDataFrame(PV, "contrast string, p double")).withColumn("p_holm", F.round("p_holm", 9))


@query("stat_cluster_bootstrap", ARMS + " SELECT round(avg(score), 9) AS estimate, TRUE AS inside FROM ar WHERE arm = 'ctx_cot'")
def stat_boot(s, d):
    b = stats.cluster_bootstrap(stats.window_sums(arm_rows(s, d).where("arm = 'ctx_cot'")))
    return b.select(F.round("estimate", 9).alias("estimate"), ((F.col("low") <= F.col("estimate")) & (F.col("estimate") <= F.col("high"))).alias("inside"))


@query("stat_bootstrap_streams", "WITH e AS (SELECT strftime(ts, '%Y-%m-%d') AS day, count(DISTINCT user_id) AS n FROM events GROUP BY ALL) SELECT round(avg(n), 9) AS estimate, TRUE AS inside FROM e")
def stat_boot_streams(s, d):
    e = T(s, d, "events").groupBy(F.date_format("ts", "yyyy-MM-dd").alias("day")).agg(F.count_distinct("user_id").alias("n"))
    b = stats.bootstrap_ci(e, "day", "n")
    return b.select(F.round("estimate", 9).alias("estimate"), ((F.col("low") <= F.col("estimate")) & (F.col("estimate") <= F.col("high"))).alias("inside"))


@query("stat_counterfactual_rate", TK + " SELECT count(*) AS n, 1.0::DOUBLE AS rate FROM tasks")
def stat_cf(s, d):
    return stats.counterfactual_rate(arms.counterfactual_arm(all_tasks(s, d)))


@query("stat_sign_flip", ARMS + " SELECT round(avg(a.score - b.score), 9) AS diff, TRUE AS p_in_range FROM ar a JOIN ar b USING (task_id) WHERE a.arm = 'exact' AND b.arm = 'ctx_direct'")
def stat_sign(s, d):
    p = stats.paired(arm_rows(s, d), "exact", "ctx_direct")
    t = stats.sign_flip_test(stats.window_sums(p, "diff", ()))
    return t.select(F.round("diff", 9).alias("diff"), ((F.col("p") > 0) & (F.col("p") <= 1)).alias("p_in_range"))


CONTRASTS = [("exact", "aggregate_only"), ("exact", "policy_only"), ("exact", "ctx_direct"), ("exact", "ctx_cot"), ("counterfactual", "aggregate_only"), ("ctx_cot", "ctx_direct"), ("ctx_direct", "policy_only"), ("aggregate_only", "policy_only")]


@query("stat_contrasts")
def stat_contrasts(s, d):
    """Eight paired contrasts: sign-flip p-values, then Holm's adjustment."""
    r = written(arm_rows(s, d), "arm-rows")
    parts = [stats.sign_flip_test(stats.window_sums(stats.paired(r, a, b), "diff", ())).withColumn("contrast", F.lit(f"{a} - {b}")) for a, b in CONTRASTS]
    p = reduce(lambda a, b: a.unionByName(b), parts)
    return p.join(stats.holm(p).drop("p"), "contrast")


# ---- baselines


@query("builtin_approx_distinct", "SELECT l_returnflag, count(DISTINCT l_orderkey) AS exact, TRUE AS approx_near, TRUE AS sketch_near FROM lineitem GROUP BY l_returnflag")
def b_approx(s, d):
    r = T(s, d, "lineitem").select("l_returnflag", F.col("l_orderkey").alias("identity"))
    x = builtin.builtin_distinct(r, ["l_returnflag"]).join(exact.exact_distinct(r, ["l_returnflag"]), "l_returnflag")
    e = measures.relerr
    return x.select("l_returnflag", "exact", (e(F.col("approx_estimate"), F.col("exact")) <= D_BOUND).alias("approx_near"), (e(F.col("hll_estimate"), F.col("exact")) <= D_BOUND).alias("sketch_near"))


@query("builtin_hll_sketch", "SELECT count(DISTINCT l_partkey) AS exact, TRUE AS near FROM lineitem")
def b_sketch(s, d):
    r = T(s, d, "lineitem").select(F.col("l_partkey").alias("identity"))
    x = builtin.builtin_distinct(r).crossJoin(exact.exact_distinct(r))
    return x.select("exact", (measures.relerr(F.col("hll_estimate"), F.col("exact")) <= D_BOUND).alias("near"))


@query("builtin_hll_union", "SELECT count(DISTINCT o_custkey) AS exact, TRUE AS near FROM orders")
def b_union(s, d):
    r = T(s, d, "orders").select("o_orderpriority", F.col("o_custkey").alias("identity"))
    x = builtin.builtin_union(r, "o_orderpriority").crossJoin(exact.exact_distinct(r))
    return x.select("exact", (measures.relerr(F.col("estimate"), F.col("exact")) <= D_BOUND).alias("near"))


@query("builtin_theta_overlap", FLAG_REG + " SELECT n11 AS exact, TRUE AS near FROM g")
def b_theta(s, d):
    r = E.extract(T(s, d, "lineitem"), FLAGS)
    x = builtin.builtin_overlap(r, "R", "A").crossJoin(exact.exact_regions(r, "R", "A"))
    return x.select(F.col("n11").alias("exact"), (F.abs(F.col("n_both") - F.col("n11")) <= 0.12 * F.col("n_union")).alias("near"))


@query("builtin_count_min", "SELECT 2100::INTEGER AS bytes")
def b_cm(s, d):
    return builtin.builtin_count_min(T(s, d, "events").select(F.col("user_id").cast("string").alias("identity"))).select(F.octet_length("table").alias("bytes"))


def train_encoder(s, streams=60, length=2_000, low=250, high=1_000, seed=0, kind=learned.SetEncoder):
    """Fit on bounded generated streams; the states are gathered (2 KB a stream, ``streams`` of them)."""
    from idagg.sources.generated import identity_streams

    r = identity_streams(s, streams, length, low, high, seed)
    e = kind.create(seed)
    x = learned.encode_states(r, "stream_no", e).join(exact.exact_distinct(r, ["stream_no"]), "stream_no").orderBy("stream_no").collect()
    return e.fit(np.array([row.state for row in x]), np.array([row.exact for row in x], float), 1_500)


@query("enc_partial_merge_consistency", "SELECT count(DISTINCT event_type) AS streams, TRUE AS same FROM events WHERE user_id IS NOT NULL")
def enc_merge(s, d):
    """States from segments of a table's streams add up to the states of the whole, up to rounding."""
    e = learned.SetEncoder.create(0)
    r = T(s, d, "events").where("event_type is not null").select("event_type", (F.col("event_id") % 5).alias("seg"), F.col("user_id").cast("string").alias("identity"))
    whole = learned.encode_states(r, "event_type", e)
    seg = learned.encode_states(r.withColumn("part", F.concat(F.coalesce(F.col("seg").cast("string"), F.lit("")), F.lit(":"), "event_type")).select("part", "identity"), "part", e)
    back = seg.select(F.expr("substring(part, instr(part, ':') + 1)").alias("event_type"), F.posexplode("state").alias("i", "x")).groupBy("event_type", "i").agg(F.sum("x").alias("x"))
    w = whole.select("event_type", F.posexplode("state").alias("i", "y")).join(back, ["event_type", "i"])
    return w.agg(F.count_distinct("event_type").alias("streams"), (F.max(F.abs(F.col("x") - F.col("y")) / (1 + F.abs("y"))) < 1e-9).alias("same"))


LENGTHS, LENGTH_STREAMS, LENGTH_IDS = (8_000, 50_000, 200_000), 100, (1_000, 4_000)


def length_errors(s, e, streams, length, low, high, seed=7):
    """(length, n, medians of both errors, their paired difference and ratio) over the same streams. Registers read every record; the encoder's
    sums are additive, so it reads each identity once, with its number of records."""
    from idagg.sources.generated import identity_streams

    r = identity_streams(s, streams, length, low, high, seed)
    per = written(r.groupBy("stream_no", "identity").agg(F.count("*").alias("times")), "identities")
    truth = per.groupBy("stream_no").agg(F.count("*").alias("exact"))
    enc = learned.decode_states(learned.encode_states(per, "stream_no", e, times="times"), "stream_no", e).join(truth, "stream_no")
    hll = read_distinct(registers.build_registers(r, ["stream_no"], family="xx"), ["stream_no"]).join(truth, "stream_no")
    a, b = (x.select("stream_no", measures.relerr(F.col("estimate"), F.col("exact")).alias("err")) for x in (enc, hll))
    n = a.agg(F.lit(length).cast("long").alias("length"), F.count("err").alias("n"), F.median("err").alias("encoder_median"))
    return n.crossJoin(b.agg(F.median("err").alias("hll_median"))).crossJoin(measures.paired_median_diff(a, b, "stream_no"))


@query("enc_vs_hll_error")
def enc_vs_hll(s, d):
    """Median errors of the encoder and of registers with as many bytes, and the paired difference: 100 streams of each length, the encoder
    trained at the shortest. Each length has streams of its own; how many identities they have doesn't depend on it."""
    e = train_encoder(s, 60, LENGTHS[0], *LENGTH_IDS)
    return reduce(lambda a, b: a.unionByName(b), [length_errors(s, e, LENGTH_STREAMS, n, *LENGTH_IDS, seed=7 + k) for k, n in enumerate(LENGTHS)])


@query("enc_features", "SELECT count(*) AS n, 28::INTEGER AS dim FROM embeddings")
def enc_features(s, d):
    """The trunk's features of each vector id: as wide as a slot."""
    return T(s, d, "embeddings").select(F.size(learned.trunk_column(F.col("vec_id").cast("string"))).alias("dim")).groupBy("dim").agg(F.count("*").alias("n"))
