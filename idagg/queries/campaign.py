"""The whole evaluation as queries: tasks by the generator's settings, every arm with budgeted states and generated programs, and their statistics.

Relations are fitted, which SQL can't express: queries with SQL leave budgeted answers about relations out, the others have them."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import functions as F

from idagg.plans import campaign as C
from idagg.plans import stats, tasks
from idagg.queries import query, sql
from idagg.queries.core import CMC
from idagg.queries.evaluation import CODE_ALL, HM, ST, rec, unit_sql

RELATIONS = ("jaccard", "containment")


def _u(prefix: str) -> str:
    return unit_sql(f"'{prefix}' || task_id")


def _h(prefix: str, key: str = "task_id") -> str:
    return HM(f"'{prefix}' || {key}")


def _r(x: str, y: str) -> str:
    return f"CASE WHEN {y} = 0 THEN 0.0 ELSE {x} / ({y}) END"


_CASE = {
    "distinct": ("n10 + n11", "na", "xa"), "union": ("n10 + n01 + n11", "na + nb - nab", "xa + xb - xab"),
    "jaccard": (_r("n11", "n10 + n01 + n11"), _r("nab", "na + nb - nab"), _r("xab", "xa + xb - xab")), "containment": (_r("n11", "n10 + n11"), _r("nab", "na"), _r("xab", "xa")),
    "grouped_distinct": ("gd", "gn", "gx"), "frequency": ("n::DOUBLE", "n::DOUBLE", "n::DOUBLE")}
_VALUES = ", ".join("CASE operator " + " ".join(f"WHEN '{o}' THEN {v[k]}" for o, v in _CASE.items()) + f" END::DOUBLE AS {name}" for k, name in enumerate(("exact", "direct", "cot")))

GENERATED = "WITH " + tasks.WINDOW_SQL + f""",
pa AS (SELECT window_id, identity, bool_or(in_a) AS a, bool_or(in_b) AS b, count(*) AS n FROM wr GROUP BY ALL),
w0 AS (SELECT window_id, count(*) AS n_items, count(*) FILTER (a AND NOT b)::DOUBLE AS n10, count(*) FILTER (b AND NOT a)::DOUBLE AS n01, count(*) FILTER (a AND b)::DOUBLE AS n11 FROM pa GROUP BY ALL),
w1 AS (SELECT window_id, CAST(ceil(sum(chars) / 4) AS BIGINT) AS token_proxy, count(*) FILTER (in_a)::DOUBLE AS na, count(*) FILTER (in_b)::DOUBLE AS nb, count(*) FILTER (in_a AND in_b)::DOUBLE AS nab FROM wr GROUP BY ALL),
ch AS (SELECT window_id, identity, chunk, bool_or(in_a) AS a, bool_or(in_b) AS b FROM wr GROUP BY ALL),
w2 AS (SELECT window_id, count(*) FILTER (a)::DOUBLE AS xa, count(*) FILTER (b)::DOUBLE AS xb, count(*) FILTER (a AND b)::DOUBLE AS xab FROM ch GROUP BY ALL),
g1 AS (SELECT window_id, group_key, count(DISTINCT identity)::DOUBLE AS gd, count(*)::DOUBLE AS gn, count(DISTINCT identity || '/' || chunk)::DOUBLE AS gx FROM wr GROUP BY ALL),
gs AS (SELECT *, row_number() OVER (PARTITION BY window_id ORDER BY group_key) - 1 AS gi FROM g1),
gc AS (SELECT window_id, count(*) AS ng FROM g1 GROUP BY ALL),
cd AS (SELECT window_id, identity, n, row_number() OVER (PARTITION BY window_id ORDER BY {HM("window_id || '/' || identity")}, identity) - 1 AS ci FROM pa),
ws AS (SELECT window_id, row_number() OVER (ORDER BY {_h('window:', 'window_id')}, window_id) AS k FROM w0 WHERE n_items >= {tasks.MIN_ITEMS}),
wn AS (SELECT *, least({tasks.MAX_CANDIDATES}, n_items) AS nc, CASE WHEN k <= {tasks.VALIDATION_WINDOWS} THEN 'validation' WHEN k <= {tasks.VALIDATION_WINDOWS + tasks.MATCHED_WINDOWS} THEN 'test' ELSE 'unused' END AS split
  FROM w0 JOIN w1 USING (window_id) JOIN w2 USING (window_id) JOIN gc USING (window_id) JOIN ws USING (window_id)),
at_ AS (SELECT wn.*, operator, CAST(attempt AS INTEGER) AS attempt, window_id || '/' || operator || '/' || attempt AS task_id FROM wn, (VALUES {", ".join(f"('{o}')" for o in tasks.OPERATORS)}) AS o(operator), range({tasks.ATTEMPTS}) AS r(attempt)),
ix AS (SELECT *, floor({_u('group:')} * ng)::BIGINT AS gi, floor({_u('probe:')} * nc)::BIGINT AS ci FROM at_),
ax AS (SELECT task_id, window_id, split, token_proxy, operator, attempt, CASE WHEN operator = 'grouped_distinct' THEN group_key END AS group_key, CASE WHEN operator = 'frequency' THEN identity END AS probe, {_VALUES}
  FROM ix JOIN gs USING (window_id, gi) JOIN cd USING (window_id, ci)),
th AS (SELECT *, round(exact * (1 + (CASE WHEN {_u('side:')} < 0.5 THEN -1.0 ELSE 1.0 END)::DOUBLE * (0.03::DOUBLE + 0.5::DOUBLE * {_u('off:')})), 6) AS threshold FROM ax WHERE exact > 0),
ag AS (SELECT *, row_number() OVER (PARTITION BY window_id, operator, group_key, probe, threshold ORDER BY attempt) AS again FROM th),
tn AS (SELECT *, row_number() OVER (PARTITION BY window_id, operator ORDER BY attempt) AS turn, operator = 'frequency' AS adds FROM ag WHERE again = 1),
pl AS (SELECT *, row_number() OVER (PARTITION BY window_id, adds ORDER BY turn, {_h('pick:')}, task_id) AS place FROM tn),
every AS (SELECT task_id, window_id, split, token_proxy, operator, attempt, group_key, probe, threshold, exact, CASE WHEN exact > threshold THEN 'act' ELSE 'watch' END AS gold, direct, cot
  FROM pl WHERE place <= CASE WHEN adds THEN {C.ADDITIVE} ELSE {C.NON_ADDITIVE} END)"""


@query("task_generate_settings", GENERATED + " SELECT task_id, window_id, split, operator, attempt, group_key, probe, threshold, round(exact, 9) AS exact, gold, round(direct, 9) AS direct, round(cot, 9) AS cot FROM every")
def generate_settings(s, d):
    """All windows' tasks by the generator's settings: candidates, least items, attempts, shares, target and split."""
    t = C.generate(C.cohort(C.profile(rec(s, d))))
    return t.drop("token_proxy").withColumns({c: F.round(c, 9) for c in ("exact", "direct", "cot")})


EVIDENCE = (
    GENERATED + ", tasks AS (SELECT * FROM every WHERE split = 'test')" + CODE_ALL + ST + ", " + sql.regs("ra", "st WHERE stream_id = 'a'", "window_id", "identity") + ", " + sql.regs("ru", "st", "window_id", "identity") + ", "
    + sql.regs("rg", "wr", "window_id, group_key", "identity") + ", ea AS (" + sql.estimate("ra", "window_id", digits=9) + "), eu AS (" + sql.estimate("ru", "window_id", digits=9) + "), eg AS (" + sql.estimate("rg", "window_id, group_key", digits=9) + "), cm AS ("
    + " UNION ALL ".join(f"SELECT window_id, {r} AS row, {CMC(r, 'identity', 1)} AS col, count(*) AS c FROM wr GROUP BY ALL" for r in range(4)) + "), zq AS ("
    + " UNION ALL ".join(f"SELECT task_id, window_id, {r} AS row, {CMC(r, 'probe', 1)} AS col FROM tasks WHERE operator = 'frequency'" for r in range(4)) + f"""),
ez AS (SELECT task_id, min(c)::DOUBLE AS estimate FROM zq JOIN cm USING (window_id, row, col) GROUP BY ALL),
lim AS (SELECT CAST(floor(quantile_cont(token_proxy::DOUBLE, {C.LIMIT_SHARE})) AS BIGINT) AS limit_tokens FROM (SELECT DISTINCT window_id, token_proxy FROM tasks)),
mt AS (SELECT task_id FROM (SELECT task_id, row_number() OVER (PARTITION BY window_id ORDER BY {_h('match:')}, task_id) AS k FROM tasks) WHERE k = 1),
ev AS (SELECT t.*, CASE t.operator WHEN 'distinct' THEN coalesce(ea.estimate, 0.0) WHEN 'union' THEN coalesce(eu.estimate, 0.0) WHEN 'grouped_distinct' THEN coalesce(eg.estimate, 0.0) WHEN 'frequency' THEN coalesce(ez.estimate, 0.0) END AS estimate,
  mt.task_id IS NOT NULL AS matched, cs.task_id IS NOT NULL AS in_code, """ + ", ".join(f"ceil(t.token_proxy * {x}::DOUBLE) <= limit_tokens AS fits_{h}" for h, x in C.PROMPT.items()) + """
  FROM tasks t CROSS JOIN lim LEFT JOIN ea ON ea.window_id = t.window_id LEFT JOIN eu ON eu.window_id = t.window_id LEFT JOIN eg ON eg.window_id = t.window_id AND eg.group_key = t.group_key
  LEFT JOIN ez ON ez.task_id = t.task_id LEFT JOIN mt ON mt.task_id = t.task_id LEFT JOIN cs ON cs.task_id = t.task_id)""")


def _arm_sql() -> str:
    out = []

    def add(who, arm, act, ok, stage, right="gold", where="TRUE"):
        out.append(f"""SELECT '{who}' AS reasoner, '{arm}' AS arm, task_id, window_id, operator, matched, in_code, fits_direct, fits_cot, fits_guided, CASE WHEN {ok} THEN 'ok' ELSE 'failed' END AS status,
  CASE WHEN NOT ({ok}) THEN {stage} END AS failure_stage, CAST(({ok}) AND (CASE WHEN {act} THEN 'act' ELSE 'watch' END) = {right} AS INTEGER) AS score FROM ev WHERE {where}""")

    for who, (reasoner, unparsed) in C.REASONERS.items():
        def said(arm, value):
            over = f"{value} > threshold"
            eps = getattr(reasoner, "eps", None)  # noqa: B023
            return over if eps is None else f"CASE WHEN {_u(f'noise:{arm}:')} < {eps} THEN NOT ({over}) ELSE {over} END"

        add(who, "exact", said("exact", "exact"), "TRUE", "'none'")
        add(who, "budgeted", said("budgeted", "estimate"), "TRUE", "'readout'", where=f"operator NOT IN {RELATIONS}")
        add(who, "counterfactual", said("counterfactual", "(CASE WHEN gold = 'act' THEN threshold - 1 ELSE threshold + 1 END)"), "TRUE", "'none'", "CASE WHEN gold = 'act' THEN 'watch' ELSE 'act' END")
        add(who, "aggregate_only", f"{_u('aggregate:')} < 0.5", "TRUE", "'none'")
        add(who, "policy_only", f"{_u('policy:')} < 0.5", f"{_u('parse:')} >= {unparsed}", "'parsing'")
        for how in C.PROMPT:
            arm = f"ctx_{how}"
            add(who, arm, said(arm, "cot" if how == "cot" else "direct"), f"fits_{how} AND {_u(f'parse_{arm}:')} >= {C.UNPARSED.get(arm, 0.0)}", f"CASE WHEN fits_{how} THEN 'parsing' ELSE 'context_packing' END", where="matched")
        add(who, "code_exec", "exact > threshold", "TRUE", "'execution'", where="in_code")
    return " UNION ALL ".join(out)


ROWS = EVIDENCE + ", ar AS (" + _arm_sql() + ")"
COUNTED = f"(arm <> 'budgeted' OR operator NOT IN {RELATIONS})"
TALLY = "count(*) AS n, count(*) FILTER (status = 'failed') AS failed, round(avg(score), 9) AS accuracy"


def arm_rows(s, d, code=False, relations=False):
    return C.rows(C.evidence(rec(s, d), code=code, relations=relations))


def tally(r, *keys):
    return r.where(COUNTED).groupBy("reasoner", "arm", *keys).agg(F.count("*").alias("n"), F.count_if(F.col("status") == "failed").alias("failed"), F.round(F.avg(F.col("score").cast("double")), 9).alias("accuracy"))


@query("stat_full_scale", ROWS + f" SELECT reasoner, arm, {TALLY} FROM ar WHERE arm IN {C.SCALE_ARMS} GROUP BY ALL")
def full_scale(s, d):
    """All test tasks in the five described conditions."""
    return tally(arm_rows(s, d).where(F.col("arm").isin(*C.SCALE_ARMS)))


MATCHED = ("budgeted", *C.CONTEXT_ARMS)


@query("stat_matched", ROWS + f" SELECT reasoner, arm, {TALLY} FROM ar WHERE matched AND arm IN {MATCHED} GROUP BY ALL")
def matched(s, d):
    """One task a window: states against readers of the raw records; what doesn't fit its prompt scores 0."""
    return tally(arm_rows(s, d).where(F.col("matched") & F.col("arm").isin(*MATCHED)))


@query("stat_split", ROWS + f" SELECT reasoner, arm, fits_direct AS within_limit, {TALLY} FROM ar WHERE matched AND arm IN {MATCHED} GROUP BY ALL")
def split(s, d):
    """The matched tasks within and over the token limit."""
    return tally(arm_rows(s, d).where(F.col("matched") & F.col("arm").isin(*MATCHED)).withColumnRenamed("fits_direct", "within_limit"), "within_limit")


JOINT = "fits_direct AND fits_cot AND fits_guided"


@query("stat_joint", ROWS + f" SELECT reasoner, arm, {TALLY} FROM ar WHERE matched AND {JOINT} AND arm IN {MATCHED} GROUP BY ALL")
def joint(s, d):
    """The matched tasks that fit all three prompts."""
    return tally(arm_rows(s, d).where(F.col("matched") & F.col("arm").isin(*MATCHED)).where(JOINT))


CODED = ("code_exec", "exact", "budgeted", "aggregate_only", "policy_only")


@query("stat_code", ROWS + f" SELECT reasoner, arm, {TALLY} FROM ar WHERE in_code AND arm IN {CODED} GROUP BY ALL")
def code(s, d):
    """The code subset: generated programs, run in bulk by operator, against the other conditions on the same tasks."""
    return tally(arm_rows(s, d, code=True).where(F.col("in_code") & F.col("arm").isin(*CODED)))


@query("stat_failure_stages", ROWS + f" SELECT reasoner, arm, failure_stage, count(*) AS n FROM ar WHERE status = 'failed' AND {COUNTED} GROUP BY ALL")
def failure_stages(s, d):
    return arm_rows(s, d, code=True).where(COUNTED).where("status = 'failed'").groupBy("reasoner", "arm", "failure_stage").agg(F.count("*").alias("n"))


@query("stat_guards_on_rows", GENERATED + f" SELECT {len(C.REASONERS) * len(C.SCALE_ARMS)}::BIGINT AS arms, count(*) AS tasks, count(DISTINCT window_id) AS windows, 64::INTEGER AS digest_length FROM every WHERE split = 'test'")
def guards_on_rows(s, d):
    """The real arm rows pass the integrity checks; the digest of what was checked goes with the result."""
    r = arm_rows(s, d, relations=True).where(F.col("arm").isin(*C.SCALE_ARMS)).withColumn("arm", F.concat_ws("/", "reasoner", "arm"))
    stats.validate(r)
    return r.agg(F.count_distinct("arm").alias("arms"), F.count_distinct("task_id").alias("tasks"), F.count_distinct("window_id").alias("windows")).withColumn("digest_length", F.lit(len(stats.digest(r))))


@query("stat_relations_flips", GENERATED + f" SELECT operator, count(*) AS n, TRUE AS few_invalid, TRUE AS few_flips FROM every WHERE split = 'test' AND operator IN {RELATIONS} GROUP BY ALL")
def relation_flips(s, d):
    """Relations: how many fits are unsound, and how many decisions the sketch turns; thresholds stand 3 to 53 percent off."""
    e = C.evidence(rec(s, d), code=False).where(F.col("operator").isin(*RELATIONS))
    flip = (F.col("exact") > F.col("threshold")) != (F.col("estimate") > F.col("threshold"))
    return e.groupBy("operator").agg(F.count("*").alias("n"), (F.count_if(~F.col("valid")) <= 0.02 * F.count("*")).alias("few_invalid"), (F.count_if(flip) <= 0.2 * F.count("*")).alias("few_flips"))


@query("stat_campaign")
def campaign(s, d):
    """Accuracy of every arm with relations, and the window bootstrap's interval: all tasks, the matched ones, the jointly eligible and the code subset."""
    r = C.written(arm_rows(s, d, True, True), "arm-rows")
    scale, ctx = F.col("arm").isin(*C.SCALE_ARMS), F.col("arm").isin(*MATCHED)
    parts = {"all": r.where(scale), "matched": r.where(F.col("matched") & ctx), "joint": r.where(F.col("matched") & ctx).where(JOINT), "code": r.where(F.col("in_code") & F.col("arm").isin(*CODED))}
    return reduce(lambda a, b: a.unionByName(b), (C.intervals(x).withColumn("tasks", F.lit(n)) for n, x in parts.items()))


@query("stat_campaign_contrasts")
def campaign_contrasts(s, d):
    """The eight contrasts of budgeted states, at 100,000 sign flips and 10,000 resamples."""
    return C.contrasts(arm_rows(s, d, True, True))
