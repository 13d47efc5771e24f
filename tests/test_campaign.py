"""The whole evaluation: shares and counts of the generator, evidence against plain Python, arms and statistics."""

import collections
import re

import pytest
from pyspark.sql import functions as F

from idagg import workloads
from idagg.functions.estimate import estimate_registers
from idagg.plans import campaign, stats, tasks
from idagg.plans.planner import scans


@pytest.fixture(scope="module")
def records(spark, sf):
    return tasks.window_records(spark, sf)


@pytest.fixture(scope="module")
def ev(records):
    return campaign.evidence(records)


def test_generator_settings(records):
    """Candidates, least items, attempts, shares, target and split are what the settings say."""
    assert (campaign.NON_ADDITIVE, campaign.ADDITIVE) == (16, 10) and campaign.NON_ADDITIVE / tasks.TARGET_TASKS == pytest.approx(tasks.NON_ADDITIVE_SHARE, abs=0.02)
    wins = campaign.cohort(campaign.profile(records))
    w = {r.window_id: r for r in wins.collect()}
    assert w and min(r.n_items for r in w.values()) >= tasks.MIN_ITEMS and max(len(r["items"]) for r in w.values()) <= tasks.MAX_CANDIDATES
    assert collections.Counter(r.split for r in w.values())["validation"] == tasks.VALIDATION_WINDOWS
    t = campaign.generate(wins).collect()
    per = collections.Counter((r.window_id, r.operator == "frequency") for r in t)
    assert max(v for (_, adds), v in per.items() if adds) == campaign.ADDITIVE and max(v for (_, adds), v in per.items() if not adds) == campaign.NON_ADDITIVE
    assert max(r.attempt for r in t) < tasks.ATTEMPTS and len({r.task_id for r in t}) == len(t) and all(r.exact > 0 for r in t)
    assert len({(r.window_id, r.operator, r.group_key, r.probe, r.threshold) for r in t}) == len(t)


def test_evidence_brute_force(records, ev):
    """Exact, context, program and state values of each task from the records in plain Python."""
    import hashlib

    by = collections.defaultdict(list)
    for r in records.collect():
        by[r.window_id].append(r)

    def h(text, seed=0):
        return int(hashlib.md5(f"{seed}:{text}".encode()).hexdigest()[:16], 16)

    def read(ids):
        m = [0] * 2048
        for z in ids:
            x = h(z)
            low = x & ((1 << 53) - 1)
            m[x >> 53] = max(m[x >> 53], 54 - low.bit_length())
        return estimate_registers(m, 2048)

    def div(x, y):
        return x / y if y else 0.0

    rows = ev.collect()
    assert len(rows) > 1000 and {r.operator for r in rows} == set(tasks.OPERATORS)
    for t in rows[::7]:
        rs = by[t.window_id]
        a, b = {r.identity for r in rs if r.in_a}, {r.identity for r in rs if r.in_b}
        na, nb, nab = sum(r.in_a for r in rs), sum(r.in_b for r in rs), sum(r.in_a and r.in_b for r in rs)
        ca, cb = {(r.chunk, r.identity) for r in rs if r.in_a}, {(r.chunk, r.identity) for r in rs if r.in_b}
        g, f = [r for r in rs if r.group_key == t.group_key], sum(r.identity == t.probe for r in rs)
        want = {
            "distinct": (len(a), na, len(ca)), "union": (len(a | b), na + nb - nab, len(ca | cb)), "jaccard": (div(len(a & b), len(a | b)), div(nab, na + nb - nab), div(len(ca & cb), len(ca | cb))),
            "containment": (div(len(a & b), len(a)), div(nab, na), div(len(ca & cb), len(ca))), "grouped_distinct": (len({r.identity for r in g}), len(g), len({(r.chunk, r.identity) for r in g})),
            "frequency": (f, f, f)}[t.operator]
        assert (t.exact, t.direct, t.cot) == pytest.approx(want)
        assert t.code is None or t.code == pytest.approx(want[0])
        assert t.in_code == (t.code is not None)
        if t.operator == "frequency":
            c = collections.Counter((k, h(f"{k}:{r.identity}", 1) & 63) for r in rs for k in range(4))
            assert t.estimate == min(c[k, h(f"{k}:{t.probe}", 1) & 63] for k in range(4)) >= f
        elif t.operator in ("distinct", "union", "grouped_distinct"):
            assert t.estimate == pytest.approx(read({"distinct": a, "union": a | b, "grouped_distinct": {r.identity for r in g}}[t.operator]))
        else:
            assert not t.valid or abs(t.estimate - t.exact) < 0.15


def test_one_scan_a_table_and_pass(records, ev):
    for made in (campaign.profile(records), campaign.states(records)):
        files = re.findall(r"/(\w+)\.parquet", made._jdf.queryExecution().executedPlan().toString())
        assert collections.Counter(files) == {"events": 1, "lineitem": 1, "orders": 1}
    assert scans(campaign.rows(ev)) == 1


def test_rows_pass_the_guards(ev):
    r = campaign.rows(ev)
    scale = r.where(F.col("arm").isin(*campaign.SCALE_ARMS)).withColumn("arm", F.concat_ws("/", "reasoner", "arm"))
    stats.validate(scale)
    with pytest.raises(stats.IntegrityError):
        stats.validate(scale.union(scale.limit(1)))
    got = {(x.reasoner, x.arm): x for x in stats.accuracy(r.withColumn("arm", F.concat_ws("/", "reasoner", "arm"))).select(F.split("arm", "/")[0].alias("reasoner"), F.split("arm", "/")[1].alias("arm"), "n", "accuracy").collect()}
    assert got["rule", "exact"].accuracy == 1 == got["rule", "code_exec"].accuracy and got["noisy", "exact"].accuracy == pytest.approx(0.93, abs=0.03)
    assert got["rule", "budgeted"].accuracy > got["rule", "ctx_direct"].accuracy and got["rule", "policy_only"].accuracy < got["rule", "aggregate_only"].accuracy
    guided, direct = (r.where(f"arm = 'ctx_{h}' and reasoner = 'rule' and failure_stage = 'parsing'").count() for h in ("guided", "direct"))
    assert guided == 0 < direct


def test_contrasts(spark, ev):
    """Each contrast's difference is that of the two arms' mean scores on its tasks; p is between the floor and 1, Holm's not below p."""
    r = campaign.rows(ev)
    got = {x.contrast: x for x in campaign.contrasts(r, 2_000, 500).collect()}
    assert len(got) == 8
    rows = r.collect()
    for name, x in got.items():
        who, a, b = re.match(r"(\w+): (\w+) - (\w+)", name).groups()
        which = {"exact": "full", "ctx_direct": "matched", "ctx_cot": "matched", "budgeted": "code"}[b]
        own = [y for y in rows if y.reasoner == who and (which == "full" or (y.matched if which == "matched" else y.in_code))]
        mean = {arm: [y.score for y in own if y.arm == arm] for arm in (a, b)}
        assert len(mean[a]) == len(mean[b]) == x.n
        assert x.diff_pp == pytest.approx(100 * (sum(mean[a]) - sum(mean[b])) / x.n) and 1 / 2_001 <= x.p <= x.p_holm <= 1 and x.low <= x.diff_pp <= x.high


def test_registered(spark, sf):
    assert {"stat_full_scale", "stat_matched", "stat_split", "stat_joint", "stat_code", "task_generate_settings"} <= set(workloads.oracle_sql())
