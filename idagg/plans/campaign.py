"""The whole evaluation: tasks by the generator's settings, evidence for every arm, arm rows under two reasoners, and their statistics.

Evidence has one row a task and comes from three passes, one scan of each source table in each: exact and context values from one profile of
(window, identity, group); register and counter states built from the records themselves; and the generated programs. Each pass writes a small
table to the shared folder, so statistics read tables of a row a task, never records.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from idagg.functions.hashing import hash64, index_rank
from idagg.operators.frequency import DEPTH, WIDTH, column_of
from idagg.operators.readouts import read_distinct
from idagg.operators.registers import merge_registers
from idagg.operators.relation import fit_pairs, pair_cells, readouts
from idagg.plans import stats
from idagg.plans import tasks as T
from idagg.plans.arms import NoisyReasoner, RuleReasoner, program_for
from idagg.plans.tasks import unit
from idagg.sources.shared import written
from idagg.spec import DEFAULT_P

NON_ADDITIVE = round(T.NON_ADDITIVE_SHARE * T.TARGET_TASKS)
ADDITIVE = T.TARGET_TASKS - NON_ADDITIVE
#: A prompt's length by its records': guided prompts list the choices, chain of thought has instructions and room for its steps.
PROMPT = {"direct": 1.0, "guided": 1.01, "cot": 1.05}
LIMIT_SHARE = 0.54  # of windows that the token limit lets through
UNPARSED = {"ctx_direct": 0.02, "ctx_cot": 0.02}  # share of free texts without a readable choice; guided answers always have one
#: Stand-ins for two reasoners: (rule, share of policy-only answers that don't parse).
REASONERS = {"noisy": (NoisyReasoner(0.07), 0.0), "rule": (RuleReasoner(), 0.45)}
SCALE_ARMS = ("exact", "budgeted", "counterfactual", "aggregate_only", "policy_only")
CONTEXT_ARMS = ("ctx_direct", "ctx_cot", "ctx_guided")
CONTRASTS = [("exact", "full"), ("ctx_direct", "matched"), ("ctx_cot", "matched"), ("code_exec", "code")]


def _order(prefix: str, key: str) -> Column:
    return hash64(F.concat(F.lit(prefix), F.col(key)), T.GENERATOR_SEED, "md5")


def profile(records: DataFrame) -> DataFrame:
    """(window_id, identity, group_key, n, na, nb, nab, ca, cb, cg, chars): records by identity and group, and the chunks (bits) that hold them."""
    def bits(c):
        return F.bit_or(F.when(c, F.call_function("shiftleft", F.lit(1), F.col("chunk"))).otherwise(0))

    a, b = F.col("in_a"), F.col("in_b")
    return records.groupBy("window_id", "identity", "group_key").agg(
        F.count("*").alias("n"), F.count_if(a).alias("na"), F.count_if(b).alias("nb"), F.count_if(a & b).alias("nab"),
        bits(a).alias("ca"), bits(b).alias("cb"), bits(F.lit(True)).alias("cg"), F.sum("chars").alias("chars"))


def cohort(fine: DataFrame) -> DataFrame:
    """One row a window of MIN_ITEMS items or more: sizes, values of its operands, groups, candidates and split. Windows go to validation and test in
    hash order."""
    per = fine.groupBy("window_id", "identity").agg(*(F.sum(c).alias(c) for c in ("n", "na", "nb", "nab", "chars")), F.bit_or("ca").alias("ca"), F.bit_or("cb").alias("cb"))
    both, bit = F.col("ca").bitwiseAND(F.col("cb")), lambda c: F.bit_count(c).cast("double")
    a, b = F.col("na") > 0, F.col("nb") > 0
    w = per.groupBy("window_id").agg(
        F.sum("n").alias("n_records"), F.count("*").alias("n_items"), F.ceil(F.sum("chars") / 4).cast("long").alias("token_proxy"),
        *(F.count_if(c).cast("double").alias(n) for n, c in (("n10", a & ~b), ("n01", b & ~a), ("n11", a & b))),
        *(F.sum(c).cast("double").alias(c) for c in ("na", "nb", "nab")),
        F.sum(bit("ca")).alias("xa"), F.sum(bit("cb")).alias("xb"), F.sum(bit(both)).alias("xab"))
    g = fine.groupBy("window_id", "group_key").agg(F.count("*").cast("double").alias("gd"), F.sum("n").cast("double").alias("gn"), F.sum(bit("cg")).alias("gx"))
    g = g.groupBy("window_id").agg(F.array_sort(F.collect_list(F.struct("group_key", "gd", "gn", "gx"))).alias("groups"))  # a window's groups are a few
    o = hash64(F.concat("window_id", F.lit("/"), "identity"), T.GENERATOR_SEED, "md5")
    c = per.select("window_id", "identity", "n", F.row_number().over(W.partitionBy("window_id").orderBy(o, "identity")).alias("rank")).where(F.col("rank") <= T.MAX_CANDIDATES)
    c = c.groupBy("window_id").agg(F.array_sort(F.collect_list(F.struct("rank", "identity", "n"))).alias("items"))  # MAX_CANDIDATES at most
    w = w.where(F.col("n_items") >= T.MIN_ITEMS).join(g, "window_id").join(c, "window_id")
    k = F.row_number().over(W.orderBy(_order("window:", "window_id"), "window_id"))  # a row a window
    split = F.when(F.col("k") <= T.VALIDATION_WINDOWS, "validation").when(F.col("k") <= T.VALIDATION_WINDOWS + T.MATCHED_WINDOWS, "test").otherwise("unused")
    return w.withColumn("k", k).withColumn("split", split).drop("k")


def _ratio(x, y):
    return F.when(y == 0, F.lit(0.0)).otherwise(x / y)


def generate(wins: DataFrame) -> DataFrame:
    """Tasks of each window: ATTEMPTS attempts an operator, each with an operand, a threshold and its side by hash; an attempt whose value is zero or
    that repeats an earlier one is dropped. NON_ADDITIVE tasks of operators whose values don't add up over segments and ADDITIVE frequencies are
    kept, operators taking turns. direct and cot are what readers of the raw records would count."""
    a, b, ab, xa, xb, xab = (F.col(c) for c in ("na", "nb", "nab", "xa", "xb", "xab"))
    n10, n01, n11 = (F.col(c) for c in ("n10", "n01", "n11"))
    none, key = F.lit(None).cast("string"), F.concat_ws("/", "window_id", "operator", F.col("attempt").cast("string"))
    d = wins.crossJoin(F.broadcast(wins.sparkSession.createDataFrame([(o, i) for o in T.OPERATORS for i in range(T.ATTEMPTS)], "operator string, attempt int")))
    d = d.withColumn("task_id", key)
    d = d.withColumn("grp", F.get("groups", F.floor(unit(F.concat(F.lit("group:"), "task_id")) * F.size("groups")).cast("int")))
    d = d.withColumn("item", F.get("items", F.floor(unit(F.concat(F.lit("probe:"), "task_id")) * F.size("items")).cast("int")))
    f = F.col("item.n").cast("double")
    values = {
        "distinct": (n10 + n11, a, xa), "union": (n10 + n01 + n11, a + b - ab, xa + xb - xab),
        "jaccard": (_ratio(n11, n10 + n01 + n11), _ratio(ab, a + b - ab), _ratio(xab, xa + xb - xab)), "containment": (_ratio(n11, n10 + n11), _ratio(ab, a), _ratio(xab, xa)),
        "grouped_distinct": (F.col("grp.gd"), F.col("grp.gn"), F.col("grp.gx")), "frequency": (f, f, f)}
    of = [reduce(lambda c, o: c.when(F.col("operator") == o, values[o][k]), T.OPERATORS, F) for k in range(3)]  # noqa: B023
    d = d.select(
        "task_id", "window_id", "split", "token_proxy", "operator", "attempt", F.when(F.col("operator") == "grouped_distinct", F.col("grp.group_key")).otherwise(none).alias("group_key"),
        F.when(F.col("operator") == "frequency", F.col("item.identity")).otherwise(none).alias("probe"), *(c.alias(n) for c, n in zip(of, ("exact", "direct", "cot"), strict=True)))
    side = F.when(unit(F.concat(F.lit("side:"), "task_id")) < 0.5, -1.0).otherwise(1.0)
    d = d.withColumn("threshold", F.round(F.col("exact") * (1 + side * (0.03 + 0.5 * unit(F.concat(F.lit("off:"), "task_id")))), 6))
    again = F.row_number().over(W.partitionBy("window_id", "operator", "group_key", "probe", "threshold").orderBy("attempt"))
    d = d.withColumn("again", again).where("exact > 0 and again = 1")
    d = d.withColumn("turn", F.row_number().over(W.partitionBy("window_id", "operator").orderBy("attempt"))).withColumn("adds", F.col("operator") == "frequency")
    d = d.withColumn("place", F.row_number().over(W.partitionBy("window_id", "adds").orderBy("turn", _order("pick:", "task_id"), "task_id")))
    return d.where(F.col("place") <= F.when(F.col("adds"), ADDITIVE).otherwise(NON_ADDITIVE)).select(
        "task_id", "window_id", "split", "token_proxy", "operator", "attempt", "group_key", "probe", "threshold", "exact",
        F.when(F.col("exact") > F.col("threshold"), "act").otherwise("watch").alias("gold"), "direct", "cot")


def states(records: DataFrame, p: int = DEFAULT_P) -> DataFrame:
    """(window_id, state, slot, r, c): registers of operands a and b and of each group, and the counters of a Count-Min table, from one scan. Registers
    take the largest rank, counters the number of records; both are aggregated before anything is shuffled."""
    z = F.col("identity")
    j, r = index_rank(F.col("h"), p)
    zero, one = F.lit(0), F.lit(1)

    def reg(name, when):
        return F.when(when, F.struct(name.alias("state"), j.alias("slot"), r.alias("r"), zero.alias("c")))

    cells = [F.struct(F.lit("#").alias("state"), (column_of(z, k, WIDTH, 1, "md5") + k * WIDTH).alias("slot"), zero.alias("r"), one.alias("c")) for k in range(DEPTH)]
    up = F.array_compact(F.array(reg(F.lit("a"), F.col("in_a")), reg(F.lit("b"), F.col("in_b")), reg(F.concat(F.lit("g:"), "group_key"), F.col("group_key").isNotNull()), *cells))
    d = records.where(z.isNotNull()).withColumn("h", hash64(z, 0, "md5")).select("window_id", F.explode(up).alias("x")).select("window_id", "x.*")
    return d.groupBy("window_id", "state", "slot").agg(F.max("r").alias("r"), F.sum("c").alias("c"))


def budgeted(made: DataFrame, tasks: DataFrame, p: int = DEFAULT_P, relations: bool = True) -> DataFrame:
    """(task_id, estimate, valid) for each task, from states alone. An empty state reads 0; an unsound fit has no estimate. Without ``relations``
    nothing is fitted and tasks about relations are left out."""
    regs = made.where("state <> '#'").select("window_id", "state", F.col("slot").alias("j"), "r")
    ab = regs.where("state in ('a', 'b')")
    of = read_distinct(regs.where("state <> 'b'"), ["window_id", "state"], p)  # a, and each group
    union = read_distinct(merge_registers(ab, ["window_id"]), ["window_id"], p).withColumn("state", F.lit("union"))
    known = of.unionByName(union.select(*of.columns)).withColumn("valid", F.lit(True))
    fit = readouts(fit_pairs(pair_cells(ab, "a", "b", ["window_id"], "state"), ["window_id"], p), ["window_id"])
    both = F.array(*(F.struct(F.lit(o).alias("state"), F.col(c).alias("estimate")) for o, c in (("jaccard", "jaccard"), ("containment", "containment_ab"))))
    rel = fit.select("window_id", F.explode(both).alias("x"), "valid").select("window_id", "x.state", "x.estimate", "valid")  # a fit is read twice, made once
    known = known.unionByName(rel) if relations else known
    state = F.when(F.col("operator") == "distinct", "a").when(F.col("operator") == "grouped_distinct", F.concat(F.lit("g:"), "group_key")).otherwise(F.col("operator"))
    t = tasks.select("task_id", "window_id", "operator", "probe", state.alias("state"))
    t = t if relations else t.where("operator not in ('jaccard', 'containment')")
    sets = t.where("operator <> 'frequency'").join(known, ["window_id", "state"], "left").select(
        "task_id", F.when(F.coalesce("valid", F.lit(True)), F.coalesce("estimate", F.lit(0.0))).alias("estimate"), F.coalesce("valid", F.lit(True)).alias("valid"))
    at = F.array(*((column_of(F.col("probe"), k, WIDTH, 1, "md5") + k * WIDTH) for k in range(DEPTH)))
    cells = made.where("state = '#'").select("window_id", "slot", "c")
    asked = t.where("operator = 'frequency'").select("task_id", "window_id", F.explode(at).alias("slot")).join(cells, ["window_id", "slot"], "left")
    return sets.unionByName(asked.groupBy("task_id").agg(F.min(F.coalesce("c", F.lit(0))).cast("double").alias("estimate")).withColumn("valid", F.lit(True)))


def run_programs(records: DataFrame, tasks: DataFrame) -> DataFrame:
    """(task_id, code): what the generated programs compute, those of an operator as one statement over its tasks: a program's constants become
    columns of the task list, which is joined to the records of its windows."""
    spark = records.sparkSession
    records.createOrReplaceTempView("window_records")
    tasks.select("task_id", "window_id", "operator", "group_key", "probe").createOrReplaceTempView("code_tasks")
    out = []
    for o in T.OPERATORS:
        text = program_for({"operator": o, "window_id": "@", "group_key": "@", "probe": "@"})
        # one statement for all: the constants of a single program are the columns of its task
        text = text.replace("window_id = '@'", f"operator = '{o}'").replace("group_key = '@'", "r.group_key = t.group_key").replace("identity = '@'", "identity = t.probe")
        text = text.replace("SELECT identity,", "SELECT task_id, identity,").replace("GROUP BY identity", "GROUP BY task_id, identity")
        text = text.replace("window_records", "window_records r JOIN code_tasks t ON r.window_id = t.window_id")
        out.append(spark.sql(f"SELECT task_id, {text.removeprefix('SELECT ')} GROUP BY task_id").withColumnRenamed("x", "code"))
    return reduce(lambda a, b: a.unionByName(b), out)


def evidence(records: DataFrame, p: int = DEFAULT_P, code: bool = True, relations: bool = True) -> DataFrame:
    """One row a test task with all evidence and the subsets it belongs to, as a written table. What a statistic doesn't read, programs or fits, may be
    left out."""
    fine = written(profile(records), "profile")
    tasks = written(generate(cohort(fine)).where("split = 'test'"), "tasks")
    made = written(states(records, p), "states")
    got = tasks.join(budgeted(made, tasks, p, relations), "task_id", "left")
    first = F.row_number().over(W.partitionBy("window_id").orderBy(_order("match:", "task_id"), "task_id"))
    wins = tasks.groupBy("window_id").agg(F.first("token_proxy").alias("token_proxy"))
    got = got.withColumn("matched", first == 1).crossJoin(F.broadcast(T.context_limit(wins, LIMIT_SHARE)))  # one row
    got = got.withColumns({f"fits_{h}": F.ceil(F.col("token_proxy") * x) <= F.col("limit_tokens") for h, x in PROMPT.items()})
    sub = T.code_subset(tasks)
    ran = run_programs(records, sub).withColumn("in_code", F.lit(True)) if code else sub.select("task_id", F.lit(None).cast("double").alias("code"), F.lit(True).alias("in_code"))
    return written(got.join(ran, "task_id", "left").withColumn("in_code", F.coalesce("in_code", F.lit(False))), "evidence")


def rows(ev: DataFrame) -> DataFrame:
    """Terminal rows (reasoner, arm, task_id, window_id, operator, status, failure_stage, score, and the task's subsets): every arm of every task under
    both reasoners from one scan of the evidence. Failures score 0."""
    gold, thr = F.col("gold"), F.col("threshold")

    def coin(name):
        return F.when(unit(F.concat(F.lit(name), "task_id")) < 0.5, "act").otherwise("watch")

    def row(who, arm, answer, ok, stage, right=gold):
        good = F.coalesce(ok, F.lit(False))
        return F.struct(
            F.lit(who).alias("reasoner"), F.lit(arm).alias("arm"), F.when(good, "ok").otherwise("failed").alias("status"), F.when(~good, stage).alias("failure_stage"),
            F.when(good & (answer == right), 1).otherwise(0).alias("score"))

    every = []
    yes = F.lit(True)
    for who, (reasoner, unparsed) in REASONERS.items():
        def said(arm, value):
            return reasoner.answer(value, thr, F.concat(F.lit(f"{arm}:"), "task_id"))  # noqa: B023

        implied = F.when(gold == "act", "watch").otherwise("act")
        every += [
            row(who, "exact", said("exact", F.col("exact")), yes, "none"),
            row(who, "budgeted", said("budgeted", F.col("estimate")), F.col("valid") & F.col("estimate").isNotNull(), "readout"),
            row(who, "counterfactual", said("counterfactual", F.when(gold == "act", thr - 1).otherwise(thr + 1)), yes, "none", implied),
            row(who, "aggregate_only", coin("aggregate:"), yes, "none"),
            row(who, "policy_only", coin("policy:"), unit(F.concat(F.lit("parse:"), "task_id")) >= unparsed, "parsing")]
        for how in PROMPT:
            arm = f"ctx_{how}"
            fits, read = F.col(f"fits_{how}"), unit(F.concat(F.lit(f"parse_{arm}:"), "task_id")) >= UNPARSED.get(arm, 0.0)
            x = row(who, arm, said(arm, F.col("cot" if how == "cot" else "direct")), fits & read, F.when(~fits, "context_packing").otherwise("parsing"))
            every.append(F.when(F.col("matched"), x))
        every.append(F.when(F.col("in_code"), row(who, "code_exec", F.when(F.col("code") > thr, "act").otherwise("watch"), F.col("code").isNotNull(), "execution")))
    kept = ["task_id", "window_id", "operator", "matched", "in_code", "fits_direct", "fits_cot", "fits_guided"]
    return ev.select(*kept, F.explode(F.array_compact(F.array(*every))).alias("x")).select(*kept, "x.*")


def subset(r: DataFrame, which: str) -> DataFrame:
    return r if which == "full" else r.where("matched" if which == "matched" else "in_code")


def intervals(r: DataFrame, draws: int = 10_000) -> DataFrame:
    """(reasoner, arm, n, failed, accuracy, low, high): task-weighted accuracy with the window bootstrap's interval, all arms from one gathering of window
    sums."""
    sums = r.groupBy("reasoner", "arm", "window_id").agg(F.sum(F.col("score").cast("double")).alias("s"), F.count("*").alias("n"), F.count_if(F.col("status") == "failed").alias("failed"))
    sums = written(sums, "window-sums")
    of = sums.groupBy("reasoner", "arm").agg(F.sum("n").alias("n"), F.sum("failed").alias("failed"))
    arms = [(x.reasoner, x.arm) for x in sums.select("reasoner", "arm").distinct().collect()]  # a few
    got = [stats.cluster_bootstrap(sums.where((F.col("reasoner") == w) & (F.col("arm") == a)), draws).select(F.lit(w).alias("reasoner"), F.lit(a).alias("arm"), F.col("estimate").alias("accuracy"), "low", "high") for w, a in sorted(arms)]
    return of.join(reduce(lambda a, b: a.unionByName(b), got), ["reasoner", "arm"])


def contrasts(r: DataFrame, flips: int = 100_000, draws: int = 10_000) -> DataFrame:
    """(contrast, n, diff_pp, low, high, p, p_holm): budgeted against exact, direct and chain-of-thought context, and code against budgeted, under both
    reasoners: sign flips by window, Holm's adjustment over the eight."""
    got = []
    r = written(r, "arm-rows")
    for who in REASONERS:
        for other, which in CONTRASTS:
            a, b = ("code_exec", "budgeted") if other == "code_exec" else ("budgeted", other)
            sums = written(stats.window_sums(stats.paired(subset(r, which).where(F.col("reasoner") == who), a, b), "diff", ()), "paired")
            ci = stats.cluster_bootstrap(sums, draws)
            one = stats.sign_flip_test(sums, flips).crossJoin(ci).crossJoin(sums.agg(F.sum("n").alias("n")))  # a row each
            got.append(one.select(F.lit(f"{who}: {a} - {b}").alias("contrast"), "n", (100 * F.col("diff")).alias("diff_pp"), (100 * F.col("low")).alias("low"), (100 * F.col("high")).alias("high"), "p"))
    x = written(reduce(lambda a, b: a.unionByName(b), got), "contrasts")
    return x.join(stats.holm(x.select("contrast", "p")).drop("p"), "contrast")
