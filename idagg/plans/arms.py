"""Arms of the evaluation: the same tasks answered on different evidence.

No language model is called. A Reasoner is an interface; what stands in for it here is a rule (compare the evidence with the threshold), a
hash-driven noisy rule, or a hash coin where evidence is withheld. Their scores describe the evidence, and are no model's.
"""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass
from typing import Protocol

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from idagg.operators.frequency import build_countmin, read_frequency
from idagg.operators.readouts import read_distinct
from idagg.operators.registers import build_registers, merge_registers
from idagg.operators.relation import fit_pairs, pair_cells, readouts
from idagg.plans import tasks as T
from idagg.plans.tasks import unit
from idagg.spec import DEFAULT_P

COLUMNS = ("task_id", "window_id", "operator", "arm", "answer", "status", "failure_stage", "score", "calls", "out_tokens")


class Reasoner(Protocol):
    def answer(self, evidence: Column, threshold: Column, key: Column) -> Column: ...


@dataclass(frozen=True)
class RuleReasoner:
    def answer(self, evidence: Column, threshold: Column, key: Column) -> Column:
        return F.when(evidence > threshold, "act").otherwise("watch")


@dataclass(frozen=True)
class NoisyReasoner:
    """The rule, but wrong on a share of tasks that a hash of the task picks."""

    eps: float = 0.07

    def answer(self, evidence: Column, threshold: Column, key: Column) -> Column:
        right = evidence > threshold
        return F.when(F.when(unit(F.concat(F.lit("noise:"), key)) < self.eps, ~right).otherwise(right), "act").otherwise("watch")


def terminal(df: DataFrame, arm: str, answer: Column, ok: Column | None = None, stage: str = "readout", calls: int = 1, tokens: Column | None = None, gold: Column | None = None) -> DataFrame:
    """df's tasks as arm rows. A task that isn't ok has failed and scores 0."""
    ok = F.lit(True) if ok is None else ok
    a = F.when(ok, answer)
    return df.select(
        "task_id", "window_id", "operator", F.lit(arm).alias("arm"), a.alias("answer"), F.when(ok, "ok").otherwise("failed").alias("status"),
        F.when(~ok, stage).alias("failure_stage"), F.when(ok & (answer == (F.col("gold") if gold is None else gold)), 1).otherwise(0).alias("score"),
        F.lit(calls).alias("calls"), (F.lit(1) if tokens is None else tokens).cast("int").alias("out_tokens"))


def exact_arm(tasks: DataFrame, reasoner: Reasoner | None = None) -> DataFrame:
    return terminal(tasks, "exact", (reasoner or RuleReasoner()).answer(F.col("exact"), F.col("threshold"), F.col("task_id")))


def counterfactual_arm(tasks: DataFrame, reasoner: Reasoner | None = None) -> DataFrame:
    """Evidence moved to the other side of the threshold; right is what that evidence implies."""
    other = F.when(F.col("gold") == "act", F.col("threshold") - 1).otherwise(F.col("threshold") + 1)
    implied = F.when(F.col("gold") == "act", "watch").otherwise("act")
    return terminal(tasks, "counterfactual", (reasoner or RuleReasoner()).answer(other, F.col("threshold"), F.col("task_id")), gold=implied)


def aggregate_only_arm(tasks: DataFrame) -> DataFrame:
    """The condition is withheld, so the choice is a coin."""
    return terminal(tasks, "aggregate_only", F.when(unit(F.concat(F.lit("aggregate:"), "task_id")) < 0.5, "act").otherwise("watch"))


def policy_only_arm(tasks: DataFrame, parse_failures: float = 0.0) -> DataFrame:
    """The aggregate is withheld; a share of answers may not parse."""
    ok = unit(F.concat(F.lit("parse:"), "task_id")) >= parse_failures
    return terminal(tasks, "policy_only", F.when(unit(F.concat(F.lit("policy:"), "task_id")) < 0.5, "act").otherwise("watch"), ok, "parsing")


def budgeted_evidence(records: DataFrame, p: int = DEFAULT_P, relations: bool = True) -> DataFrame:
    """(window_id, operator, estimate, valid): readouts of register states and Count-Min tables, all windows at once.

    Each readout is a branch of the plan that builds its states from the records; ``plans.campaign`` builds all of them in one scan and writes
    them once."""
    regs = build_registers(T.streams(records), ["window_id", "stream_id"], p)
    allof = build_registers(records.select("window_id", "group_key", "identity"), ["window_id", "group_key"], p)
    ok = F.lit(True).alias("valid")
    every = records.select("window_id").distinct()

    def of(op, got):
        """An operand without records has an empty state, which reads 0."""
        return every.join(got, "window_id", "left").select("window_id", F.lit(op).alias("operator"), F.coalesce("estimate", F.lit(0.0)).alias("estimate"), ok)

    out = of("distinct", read_distinct(regs.where("stream_id = 'a'"), ["window_id"], p))
    out = out.unionByName(of("union", read_distinct(merge_registers(regs, ["window_id"]), ["window_id"], p)))
    first = records.groupBy("window_id").agg(F.min("group_key").alias("group_key"), F.max("identity").alias("identity"))
    grouped = read_distinct(allof, ["window_id", "group_key"], p).join(first.select("window_id", "group_key"), ["window_id", "group_key"])
    out = out.unionByName(grouped.select("window_id", F.lit("grouped_distinct").alias("operator"), "estimate", ok))
    cells = build_countmin(records.select("window_id", "identity"), ["window_id"], seed=1)
    freq = read_frequency(cells, first.select("window_id", "identity"), ["window_id"], seed=1)
    out = out.unionByName(freq.select("window_id", F.lit("frequency").alias("operator"), F.col("estimate").cast("double").alias("estimate"), ok))
    if relations:
        r = readouts(fit_pairs(pair_cells(regs, "a", "b", ["window_id"]), ["window_id"], p), ["window_id"])
        both = F.array(*(F.struct(F.lit(op).alias("operator"), F.col(c).alias("estimate")) for op, c in (("jaccard", "jaccard"), ("containment", "containment_ab"))))
        out = out.unionByName(r.select("window_id", F.explode(both).alias("x"), "valid").select("window_id", "x.operator", "x.estimate", "valid"))
    return out


def budgeted_arm(tasks: DataFrame, evidence: DataFrame, reasoner: Reasoner | None = None) -> DataFrame:
    """Sketch readouts as evidence; an invalid one is a failure."""
    d = tasks.join(evidence, ["window_id", "operator"], "left")
    return terminal(d, "budgeted", (reasoner or RuleReasoner()).answer(F.col("estimate"), F.col("threshold"), F.col("task_id")), F.coalesce(F.col("valid") & F.col("estimate").isNotNull(), F.lit(False)))


def context_evidence(records: DataFrame, how: str) -> DataFrame:
    """(window_id, operator, estimate) as a reader of raw records may get it: direct and guided add up records; chain of thought counts
    identities chunk by chunk and adds the chunks, so what spans chunks counts again."""
    a, b = F.col("in_a"), F.col("in_b")
    picks = records.groupBy("window_id").agg(F.min("group_key").alias("g"), F.max("identity").alias("z"))
    d = records.join(picks, "window_id")
    if how == "cot":
        per = d.groupBy("window_id", "chunk", "identity").agg(
            F.max(a.cast("int")).alias("a"), F.max(b.cast("int")).alias("b"), F.max((F.col("group_key") == F.col("g")).cast("int")).alias("g"), F.count_if(F.col("identity") == F.col("z")).alias("z"))
    else:
        per = d.select("window_id", a.cast("int").alias("a"), b.cast("int").alias("b"), (F.col("group_key") == F.col("g")).cast("int").alias("g"), (F.col("identity") == F.col("z")).cast("int").alias("z"))
    s = per.groupBy("window_id").agg(
        F.sum("a").cast("double").alias("na"), F.sum("b").cast("double").alias("nb"), F.sum(F.col("a") * F.col("b")).cast("double").alias("nab"), F.sum("g").cast("double").alias("ng"), F.sum("z").cast("double").alias("nz"))
    both = F.col("na") + F.col("nb") - F.col("nab")

    def row(op, x):
        return F.struct(F.lit(op).alias("operator"), x.alias("estimate"))

    def ratio(y):
        return F.when(y == 0, F.lit(0.0)).otherwise(F.col("nab") / y)

    return s.select("window_id", F.explode(F.array(
        row("distinct", F.col("na")), row("union", both), row("jaccard", ratio(both)), row("containment", ratio(F.col("na"))), row("grouped_distinct", F.col("ng")), row("frequency", F.col("nz")))).alias("x")).select("window_id", "x.*")


CONTEXT_SQL = {
    "direct": "per AS (SELECT wr.window_id, in_a::INT AS a, in_b::INT AS b, (group_key = g)::INT AS g, (identity = z)::INT AS z FROM wr JOIN picks USING (window_id))",
    "cot": "per AS (SELECT wr.window_id, max(in_a::INT) AS a, max(in_b::INT) AS b, max((group_key = g)::INT) AS g, sum((identity = z)::INT) AS z FROM wr JOIN picks USING (window_id) GROUP BY wr.window_id, chunk, identity)",
}


def context_sql(how: str) -> str:
    return CONTEXT_SQL["cot" if how == "cot" else "direct"] + """,
cs AS (SELECT window_id, sum(a)::DOUBLE AS na, sum(b)::DOUBLE AS nb, sum(a * b)::DOUBLE AS nab, sum(g)::DOUBLE AS ng, sum(z)::DOUBLE AS nz FROM per GROUP BY window_id),
ce AS (SELECT window_id, 'distinct' AS operator, na AS estimate FROM cs UNION ALL SELECT window_id, 'union', na + nb - nab FROM cs
  UNION ALL SELECT window_id, 'jaccard', CASE WHEN na + nb - nab = 0 THEN 0.0 ELSE nab / (na + nb - nab) END FROM cs
  UNION ALL SELECT window_id, 'containment', CASE WHEN na = 0 THEN 0.0 ELSE nab / na END FROM cs
  UNION ALL SELECT window_id, 'grouped_distinct', ng FROM cs UNION ALL SELECT window_id, 'frequency', nz FROM cs)"""


def context_arm(tasks: DataFrame, records: DataFrame, wins: DataFrame, how: str, share: float = 0.54) -> DataFrame:
    """how: direct, cot or guided. Windows above the token limit fail at packing. Direct and guided read alike here; ``plans.campaign`` tells them
    apart by prompt length and by answers that don't parse."""
    limit = T.context_limit(wins, share)
    d = tasks.join(context_evidence(records, how), ["window_id", "operator"]).join(wins.select("window_id", "token_proxy"), "window_id").crossJoin(F.broadcast(limit))
    fits = F.col("token_proxy") <= F.col("limit_tokens")
    return terminal(d, f"ctx_{how}", F.when(F.col("estimate") > F.col("threshold"), "act").otherwise("watch"), fits, "context_packing", tokens=F.lit(60 if how == "cot" else 1))


def program_for(task) -> str:
    """SQL text that computes a task's aggregate from view window_records."""
    w = f"window_id = '{task['window_id']}'"
    g = (task.get("group_key") or "").replace("'", "''")
    z = (task.get("probe") or "").replace("'", "''")
    per = f"(SELECT identity, max(in_a) AS a, max(in_b) AS b FROM window_records WHERE {w} GROUP BY identity)"
    return {
        "distinct": f"SELECT CAST(count(DISTINCT identity) AS DOUBLE) AS x FROM window_records WHERE {w} AND in_a",
        "union": f"SELECT CAST(count(DISTINCT identity) AS DOUBLE) AS x FROM window_records WHERE {w} AND (in_a OR in_b)",
        "jaccard": f"SELECT coalesce(count_if(a AND b) / nullif(count_if(a OR b), 0), 0.0) AS x FROM {per}",
        "containment": f"SELECT coalesce(count_if(a AND b) / nullif(count_if(a), 0), 0.0) AS x FROM {per}",
        "grouped_distinct": f"SELECT CAST(count(DISTINCT identity) AS DOUBLE) AS x FROM window_records WHERE {w} AND group_key = '{g}'",
        "frequency": f"SELECT CAST(count_if(identity = '{z}') AS DOUBLE) AS x FROM window_records WHERE {w}",
    }[task["operator"]]


def code_arm(spark: SparkSession, tasks: DataFrame, records: DataFrame, rounds: int = 3, most: int = 2_000, at_once: int = 8) -> DataFrame:
    """A program is generated and run for each task, up to ``rounds`` times if it fails: one job a task, which is this arm's cost.

    Tasks are a stated, bounded list (``most``); windows' records are read by each program from the view. ``at_once`` jobs run side by side."""
    if (n := tasks.count()) > most:
        raise ValueError(f"{n} programs: give a smaller task list")
    records.createOrReplaceTempView("window_records")

    def run(t):
        text, x, used = program_for(t.asDict()), None, 0
        for used in range(1, rounds + 1):
            try:
                x = spark.sql(text).first()[0]
                break
            except Exception:  # noqa: BLE001  whatever a generated program raises costs a round
                continue
        return t.task_id, x, used, len(text.split())

    with ThreadPoolExecutor(at_once) as pool:
        rows = list(pool.map(run, tasks.collect()))
    got = spark.createDataFrame(rows, "task_id string, estimate double, used int, tokens int")
    d = tasks.join(got, "task_id")
    out = terminal(d, "code_exec", F.when(F.col("estimate") > F.col("threshold"), "act").otherwise("watch"), F.col("estimate").isNotNull(), "execution", tokens=F.col("tokens"))
    return out.drop("calls").join(got.select("task_id", F.col("used").alias("calls")), "task_id").select(*COLUMNS)


def code_arm_bulk(tasks: DataFrame, records: DataFrame) -> DataFrame:
    """The programs of all tasks run as one plan by operator template: same answers, one job."""
    return terminal(tasks.drop("exact").join(T.targets(records).select("window_id", "operator", F.col("exact").alias("estimate")), ["window_id", "operator"]), "code_exec",
                    F.when(F.col("estimate") > F.col("threshold"), "act").otherwise("watch"), tokens=F.lit(24))


def cost_per_task(rows: DataFrame) -> DataFrame:
    return rows.groupBy("arm").agg(F.count("*").alias("n"), F.avg(F.col("calls").cast("double")).alias("calls"), F.avg(F.col("out_tokens").cast("double")).alias("out_tokens"))
