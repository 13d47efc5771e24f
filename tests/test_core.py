"""States, readouts, relations, frequencies: laws, edge cases, worked numbers."""

import math
import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from idagg.functions.canon import canonical
from idagg.functions.estimate import alpha, estimate_registers, reference_error
from idagg.functions.hashing import hash64, index_rank
from idagg.operators import attention, exact, extract, frequency, learned, readouts, registers, relation
from idagg.plans import measures, planner, stats
from idagg.plans.store import StateStore
from idagg.queries import core
from idagg.sources import generated, tables
from idagg.spec import IncompatibleStates, OperandSpec, Request, StateDescriptor, assert_compatible


def recs(spark, pairs):
    return spark.createDataFrame(pairs, "stream_id string, identity string")


def states(spark, **streams):
    return registers.build_registers(recs(spark, [(k, str(x)) for k, v in streams.items() for x in v]), ["stream_id"])


def as_set(df):
    return {tuple(r) for r in df.collect()}


def test_rank_edges(spark):
    for p in (8, 11, 13):
        q = 64 - p
        hs = [0, -1, 1 << 62, 1, (1 << q) - 1, 1 << (q - 1), (1 << q), (3 << q) + 1, (1 << 53) - 1 & ((1 << q) - 1)]
        df = spark.createDataFrame([(h,) for h in hs], "h long")
        j, r = index_rank(F.col("h"), p)
        for h, a, b in zip(hs, *zip(*df.select(j, r).collect(), strict=True), strict=True):
            u = h & ((1 << 64) - 1)
            w = u & ((1 << q) - 1)
            assert a == u >> q and b == (q + 1 if w == 0 else q - w.bit_length() + 1)


def test_hash_families(spark):
    import hashlib

    got = spark.range(50).select(F.col("id").cast("string").alias("z"), hash64(F.col("id").cast("string"), 3, "md5").alias("h")).collect()
    for r in got:
        assert r.h & ((1 << 64) - 1) == int(hashlib.md5(f"3:{r.z}".encode()).hexdigest()[:16], 16)
    a, b = (spark.range(100).select(hash64(F.col("id").cast("string"), k)).collect() for k in (0, 1))
    assert a != b
    with pytest.raises(ValueError):
        hash64("x", 0, "other")


def test_canonical(spark):
    df = spark.createDataFrame([("a", "bc"), ("ab", "c"), ("a", None)], "x string, y string")
    got = [r[0] for r in df.select(canonical("x", "y")).collect()]
    assert got[0] != got[1] and got[2] is None
    assert spark.createDataFrame([(" A ",)], "x string").select(canonical("x", lower=True, trim=True)).first()[0] == "a"


def test_merge_is_one_pass(spark):
    rng = random.Random(4)
    ids = [str(rng.randrange(500)) for _ in range(2_000)]
    rows = spark.createDataFrame([(k % 7, z) for k, z in enumerate(ids)], "segment_id int, identity string")
    once = registers.build_registers(rows, [])
    seg = registers.build_registers(rows, ["segment_id"])
    for order in ("left", "reversed", "tree"):
        assert registers.register_mismatches(registers.merge_in_order(seg, [], order), once, []).first().mismatches == 0
    parts = [seg.where(F.col("segment_id") == k).drop("segment_id") for k in range(7)]
    assert as_set(registers.fold_states(parts, []).select("j", "r")) == as_set(once.select("j", "r"))
    assert as_set(registers.update_states(parts[0], rows.where("segment_id > 0"), []).select("j", "r")) == as_set(once.select("j", "r"))


@settings(max_examples=30, deadline=None)
@given(st.lists(st.integers(0, 60), max_size=60), st.integers(1, 6), st.randoms())
def test_merge_law_in_numbers(ids, parts, rnd):
    """The law itself, on plain arrays: any split, any order, any repeats."""
    import hashlib

    def build(xs):
        out = np.zeros(256, np.uint8)
        for x in xs:
            h = int(hashlib.md5(str(x).encode()).hexdigest()[:16], 16)
            w = h & ((1 << 56) - 1)
            out[h >> 56] = max(out[h >> 56], 57 - w.bit_length())
        return out

    cut = [ids[k::parts] for k in range(parts)]
    rnd.shuffle(cut)
    merged = np.zeros(256, np.uint8)
    for c in [*cut, *cut[:1]]:
        merged = np.maximum(merged, build(c))
    assert (merged == build(ids)).all()


def test_repeats_groups_nulls(spark):
    df = spark.createDataFrame([("g", "a")] * 10_000 + [("h", "a"), (None, "b"), ("", "b"), ("g", None)], "group_key string, identity string")
    g = registers.build_registers(df, ["group_key"])
    est = {r.group_key: r.estimate for r in readouts.read_distinct(g, ["group_key"]).collect()}
    assert set(est) == {"g", "h", None, ""} and all(abs(x - 1) < 0.01 for x in est.values())


def test_empty_readouts(spark):
    none = recs(spark, []).where("false")
    g = registers.build_registers(none, [])
    assert readouts.read_distinct(g, []).first().estimate == 0
    asked = spark.createDataFrame([("never",)], "stream_id string")
    assert readouts.read_grouped(registers.build_registers(none, ["stream_id"]), "stream_id", asked).first().estimate == 0
    assert tuple(exact.ratios(exact.exact_regions(none, "a", "b")).first()) == (0, 0.0, 0.0, 0.0)


def test_estimator_branches():
    assert estimate_registers([0] * 2048, 2048) == 0
    assert abs(estimate_registers([1] + [0] * 2047, 2048) - 2048 * math.log(2048 / 2047)) < 1e-9
    full = [8] * 2048
    assert abs(estimate_registers(full, 2048) - alpha(2048) * 2048 * 256) < 1e-6
    assert abs(reference_error(2048) - 0.02298) < 1e-4
    with pytest.raises(ValueError):
        alpha(64)


@pytest.mark.parametrize("held", [1, 7, 4_096])
def test_dense_merge_of_many_keys(spark, held, monkeypatch):
    """More keys than a task holds, three states each, null keys too: one row a key, the byte-wise maximum."""
    monkeypatch.setattr(registers, "PARTIAL_KEYS", held)
    r = random.Random(3)
    rows = [(k if k % 50 else None, str(k % 7), bytes(r.randrange(5) for _ in range(4))) for k in range(300) for _ in range(3)]
    want: dict = {}
    for a, b, v in rows:
        want[a, b] = bytes(map(max, want.get((a, b), v), v))
    r.shuffle(rows)
    df = spark.createDataFrame(rows, "a long, b string, state binary").repartition(5)
    got = [(x.a, x.b, bytes(x.state)) for x in registers.merge_dense(df, ["a", "b"]).collect()]
    assert len(got) == len(want) and {(a, b): v for a, b, v in got} == want
    assert len(registers.merge_dense(df, []).collect()) == 1


def test_pack_unpack_dense_merge(spark):
    g = states(spark, a=range(300), b=range(200, 500))
    d = registers.pack(g, ["stream_id"])
    assert [len(r.state) for r in d.collect()] == [2048, 2048]
    assert as_set(registers.unpack(d, ["stream_id"])) == as_set(g.select("stream_id", "j", "r"))
    m = registers.merge_dense(d.select(F.lit(1).alias("k"), "state"), ["k"])
    assert as_set(registers.unpack(m, ["k"]).select("j", "r")) == as_set(registers.merge_registers(g, []).select("j", "r"))


def test_pack_in_bytes(spark):
    g = spark.createDataFrame([("a", 0, 1), ("a", 3, 54), ("a", 255, 2), ("b", 254, 9), ("c", 1, 16)], "k string, j int, r int")
    want = {"a": {0: 1, 3: 54, 255: 2}, "b": {254: 9}, "c": {1: 16}}
    got = {r.k: bytes(r.state) for r in registers.pack(g, ["k"], 8).collect()}
    assert got == {k: bytes(v.get(j, 0) for j in range(256)) for k, v in want.items()}


def test_running_equals_each_prefix(spark):
    rows = [(d, str(x)) for d in range(6) for x in range(d * 40, d * 40 + 100)] + [(None, "late")]
    rec = spark.createDataFrame(rows, "day int, identity string")
    got = {r.day: r.estimate for r in readouts.running_distinct(registers.build_registers(rec, ["day"]), "day").collect()}
    for d in range(6):
        whole = registers.build_registers(rec.where(F.col("day") <= d).select("identity"), [])
        assert got[d] == readouts.read_distinct(whole, []).first().estimate
    assert len(got) == 6


def test_matrix_of_given_pairs(spark, monkeypatch):
    g = states(spark, a=range(400), b=range(200, 600), c=range(1000, 1100))
    every = {(r.a, r.b): r for r in relation.relation_matrix(g).collect()}
    assert set(every) == {("a", "b"), ("a", "c"), ("b", "c")}
    for (a, b), r in every.items():
        assert relation.relate(g, a, b).first().jaccard == pytest.approx(r.jaccard, rel=1e-3, abs=1e-6)
    wanted = spark.createDataFrame([("a", "b"), ("a", "unseen")], "a string, b string")
    monkeypatch.setattr(relation, "MATRIX_STREAMS", 2)
    some = {r.b: r for r in relation.relation_matrix(g, pairs=wanted).collect()}
    assert some["b"] == every["a", "b"] and some["unseen"].overlap == 0 and len(some) == 2
    with pytest.raises(ValueError, match="pairs"):
        relation.relation_matrix(g)


def test_rollup_of_states(spark):
    df = spark.createDataFrame([(x % 2, x % 3, str(x)) for x in range(400)], "a int, b int, identity string")
    g = registers.build_registers(df, ["a", "b"])
    up = readouts.read_distinct(registers.rollup_states(g, ["a", "b"], "cube"), ["a", "b", "gid"])
    assert up.count() == 6 + 3 + 2 + 1
    total = [r.estimate for r in up.collect() if r.a is None and r.b is None][0]
    direct = readouts.read_distinct(registers.build_registers(df, []), []).first().estimate
    assert abs(total - direct) < 1e-9


def test_union_leaves_states(spark):
    g = states(spark, a=range(100), b=range(50, 150), c=range(1000, 1100))
    before = as_set(g)
    u = readouts.read_union(g, ["a", "b", "c"]).first().estimate
    assert abs(u - 250) / 250 < 0.05 and as_set(g) == before


def test_incompatible():
    a = StateDescriptor(identity_def="x", stream_def="s")
    for b in (StateDescriptor(p=12, identity_def="x"), StateDescriptor(seed=1, identity_def="x"), StateDescriptor(family="xx", identity_def="x"), StateDescriptor(identity_def="y")):
        with pytest.raises(IncompatibleStates):
            assert_compatible(a, b)
    assert_compatible(a, StateDescriptor(identity_def="x", stream_def="t"))
    with pytest.raises(IncompatibleStates):
        assert_compatible(a, StateDescriptor(identity_def="x", stream_def="t"), same_stream=True)


def test_store(spark, tmp_path):
    store = StateStore(spark, f"file://{tmp_path}/s")
    spec, d = OperandSpec("u", "identity"), StateDescriptor()
    rows = recs(spark, [("u", str(k)) for k in range(400)])
    for seg, cond in (("s1", "cast(identity as int) < 200"), ("s2", "cast(identity as int) >= 200")):
        store.put(registers.build_registers(rows.where(cond), []), d.for_stream(spec), "u", seg)
        store.put(registers.build_registers(rows.where(cond), []), d.for_stream(spec), "u", seg)  # a repeated put changes nothing
    got = store.get(["u"], d.for_stream(spec), keys=())
    assert as_set(got) == as_set(registers.build_registers(rows, []))
    assert store.covered("u") == {"s1", "s2"}
    half = readouts.read_distinct(store.get(["u"], d.for_stream(spec), ["s1"], keys=()), []).first().estimate
    assert abs(half - 200) < 15
    with pytest.raises(IncompatibleStates):
        store.get(["u"], StateDescriptor(seed=5, identity_def="identity"))


def test_planner_scans_once(spark, sf):
    li = tables.load_table(spark, sf, "lineitem")
    s = planner.build(li, [OperandSpec("R", "l_orderkey", "l_returnflag = 'R'", "l_linestatus"), OperandSpec("A", "l_orderkey", "l_returnflag = 'A'", "l_linestatus")])
    assert planner.scans(planner.all_distinct(s)) == 1
    truth = li.where("l_returnflag = 'R'").select("l_orderkey").distinct().count()
    assert abs(s.answer(Request("distinct", ("R",))).first().estimate - truth) / truth < 0.1
    j = s.answer(Request("jaccard", ("R", "A"))).first()
    assert j.valid and 0 < j.estimate < 1
    assert s.answer(Request("grouped_distinct", ("R",), ("F", "zzz"))).where("group_key = 'zzz'").first().estimate == 0
    assert s.answer(Request("frequency", ("R",), probe="1")).first().estimate >= 0
    with pytest.raises(ValueError):
        s.answer(Request("other", ("R",)))


def test_six_operators_from_one_scan(spark, sf):
    """Records are read once, when states are built; no answer reads them again, and answers merge with any probe."""
    li = tables.load_table(spark, sf, "lineitem")
    specs = [OperandSpec(f, "l_orderkey", f"l_returnflag = '{f}'", "l_linestatus") for f in "RA"]
    s = planner.build(li, specs, probes=("1",))
    asked = core.REQUESTS
    assert {q.op for q in asked} == {"distinct", "union", "grouped_distinct", "frequency", "jaccard", "containment"}
    for q in asked:
        plan = s.answer(q)._jdf.queryExecution().optimizedPlan().toString()
        assert "l_orderkey" not in plan and "l_returnflag" not in plan
    exact_n = li.where("l_returnflag = 'A' and l_orderkey = 1").count()
    assert s.answer(Request("frequency", ("A",), probe="1")).first().estimate == exact_n
    for probe in ("7", "33", "none"):
        assert s.answer(Request("frequency", ("R",), probe=probe)).first().estimate >= li.where(f"l_returnflag = 'R' and cast(l_orderkey as string) = '{probe}'").count()


# ---- relations


def cells(a, b, p=11):
    import hashlib

    def arr(xs):
        out = np.zeros(1 << p, np.int64)
        for x in xs:
            h = int(hashlib.md5(f"0:{x}".encode()).hexdigest()[:16], 16)
            w = h & ((1 << (64 - p)) - 1)
            out[h >> (64 - p)] = max(out[h >> (64 - p)], 65 - p - w.bit_length())
        return out

    u, v = arr(a), arr(b)
    pairs, h = np.unique(np.stack([u, v]), axis=1, return_counts=True)
    return pairs[0], pairs[1], h


def test_cell_probabilities_sum_to_one():
    m, q = 256, 56
    for n in ([300.0, 200.0, 500.0], [0.0, 200.0, 500.0], [5.0, 0.0, 0.0], [1e5, 1e3, 10.0]):
        u, v = (x.ravel() for x in np.meshgrid(np.arange(q + 2), np.arange(q + 2)))
        with np.errstate(all="ignore"):
            total = np.exp(relation.log_cells(np.array(n), u, v, m, q))
        assert abs(np.nansum(total) - 1) < 1e-9


@pytest.mark.parametrize(("a", "b"), [
    (range(1000), range(500, 1500)), (range(800), range(5000, 5900)), (range(300), range(3000)), (range(700), range(700)), (range(20), range(10, 30)),
    (range(60_000), range(59_000, 90_000)), ([], range(50)), ([], [])])
def test_fits(a, b):
    u, v, h = cells(a, b)
    got = relation.fit_regions(u, v, h, 2048)
    assert got["valid"], got
    A, B = set(a), set(b)
    size = max(1, len(A | B))
    for name, truth in (("n10", len(A - B)), ("n01", len(B - A)), ("n11", len(A & B))):
        assert abs(got[name] - truth) <= 0.1 * size + 3, (name, got)
    if A == B or A <= B:
        assert got["n10"] == 0 or got["n10"] < 0.02 * size
    back = relation.fit_regions(v, u, h, 2048)
    assert abs(back["n11"] - got["n11"]) < 0.01 * size + 1
    if A and B:
        best = relation.log_likelihood(np.array([got["n10"], got["n01"], got["n11"]]), u, v, h, 2048, 53)
        for k in range(3):
            for f in (0.99, 1.01):
                n = np.array([got["n10"], got["n01"], got["n11"]])
                n[k] *= f
                assert relation.log_likelihood(n, u, v, h, 2048, 53) <= best + 1e-6


def test_saturated_and_unconverged():
    got = relation.fit_regions([54, 0], [54, 0], [1, 2047], 2048)
    assert set(got) >= {"reason", "valid"}
    none = relation.fit_regions(*cells(range(500), range(250, 750)), 2048, sweeps=0)
    assert not none["valid"] and none["reason"] == "sweeps"


def test_invalid_is_null(spark):
    g = states(spark, a=range(500), b=range(250, 750))
    bad = relation.relate(g, "a", "b", sweeps=0).first()
    assert bad.jaccard is None and bad.containment_ab is None and bad.overlap is None and not bad.valid
    good = relation.relate(g, "a", "b").first()
    assert good.valid and abs(good.jaccard - 1 / 3) < 0.05 and abs(good.containment_ab - 0.5) < 0.06


def test_histogram_counts_m(spark):
    g = states(spark, a=range(30), b=range(20, 50))
    h = relation.pair_histogram(*(g.where(F.col("stream_id") == k).select("j", "r") for k in "ab"), [])
    assert h.agg(F.sum("h")).first()[0] == 2048 and h.where("u = 0 and v = 0").count() == 1
    assert as_set(relation.pair_cells(g, "a", "b", [])) == as_set(h.where("u > 0 or v > 0"))
    assert planner.scans(relation.pair_cells(g, "a", "b", [])) <= 1


# ---- frequencies


def test_count_min(spark):
    rng = random.Random(2)
    ids = [str(int(rng.paretovariate(1)) % 200) for _ in range(3_000)]
    df = spark.createDataFrame([(z,) for z in ids], "identity string")
    c = frequency.build_countmin(df, [])
    assert c.agg(F.sum("c")).first()[0] == 4 * 3_000
    est = {r.identity: r.estimate for r in frequency.read_frequency(c, df.distinct()).collect()}
    most, _ = frequency.bound(3_000)
    assert all(ids.count(z) <= e <= ids.count(z) + 3 * most for z, e in est.items())
    assert frequency.read_frequency(c, spark.createDataFrame([("never",)], "identity string")).first().estimate >= 0
    with pytest.raises(ValueError):
        frequency.build_countmin(df, [], w=60)


# ---- attention


def test_attention_numbers(spark):
    same = spark.createDataFrame([(0.0, 0.0), (0.0, 2.0)], "a double, v double")
    got = {r.context: (r.alone, r.followed) for r in attention.merge_counterexample(same, "a", "v").collect()}
    assert got["x"] == (1.0, pytest.approx(2 / 3)) and got["y"] == (1.0, 0.5)
    df = spark.createDataFrame([(900.0, 1.0), (901.0, 3.0)], "a double, v double")
    o = attention.attention_readout(df, "a", "v").first().o
    assert o == pytest.approx((1 + 3 * math.e) / (1 + math.e))
    same = attention.duplicate_shift(attention.attention_state(df, "a", "v"), F.lit(1.0), F.lit(o)).first()["shift"]
    assert abs(same) < 1e-12


# ---- measures and statistics


def test_measures(spark):
    df = spark.createDataFrame([("a", 110.0, 100), ("a", 90.0, 100), ("a", None, 100), ("b", 3.0, 0)], "k string, estimate double, exact long")
    got = {r.k: r for r in measures.summary(df, ["k"]).collect()}
    assert got["a"].n == 2 and got["a"].invalid == 1 and got["a"].rms_relerr == pytest.approx(0.1) and got["b"].mean_relerr == 3
    ids = spark.createDataFrame([(f"{k:016d}",) for k in range(300)], "identity string")
    assert measures.utf8_crossover(ids).first().crossover == 128 and measures.running_crossover(ids).first().first_n == 128
    assert learned.STATE_BYTES == 2048
    x = spark.createDataFrame([(k, float(k)) for k in range(3)], "s int, err double")
    y = spark.createDataFrame([(0, 0.0), (1, 0.5), (2, 0.0)], "s int, err double")
    assert measures.paired_median_diff(x, y, "s").first().median_paired_diff == 0.5


def test_bootstrap_and_signs(spark):
    rows = spark.createDataFrame([("w1", 3.0, 4), ("w2", 1.0, 4)], "window_id string, s double, n long")
    b = stats.cluster_bootstrap(rows, 4_000).first()
    assert b.estimate == 0.5 and b.low == 0.25 and b.high == 0.75
    rows = spark.createDataFrame([(f"w{k}", 1.0, 1) for k in range(20)], "window_id string, s double, n long")
    assert stats.sign_flip_test(rows, 20_000).first().p < 1e-3
    rows = spark.createDataFrame([("a", 1.0, 1), ("b", -1.0, 1)], "window_id string, s double, n long")
    assert stats.sign_flip_test(rows, 2_000).first().p == 1.0


def test_holm(spark):
    got = {r.contrast: r.p_holm for r in stats.holm(spark.createDataFrame([("a", 0.01), ("b", 0.04), ("c", 0.03)], "contrast string, p double")).collect()}
    assert got == {"a": pytest.approx(0.03), "c": pytest.approx(0.06), "b": pytest.approx(0.06)}


def test_generated_streams(spark):
    s = generated.identity_streams(spark, 3, 6_000, 1_000, 2_000)
    n = exact.exact_distinct(s, ["stream_no"]).toPandas()
    assert len(n) == 3 and n.exact.between(1_000, 2_000).all() and s.count() == 18_000


def test_error_law(spark):
    """Root-mean-square error over sets of one size is near the reference."""
    d = generated.distinct_streams(spark, [20_000], 60)
    e = readouts.read_distinct(registers.build_registers(d, ["rep"], 9, family="xx"), ["rep"], 9).withColumn("exact", F.lit(20_000))
    rms = measures.summary(e, []).first().rms_relerr
    assert 0.7 * reference_error(512) < rms < 1.3 * reference_error(512)


def test_extract(spark):
    df = spark.createDataFrame([(1, "x", "g"), (2, None, "g"), (3, "y", None)], "k int, z string, g string")
    got = extract.extract(df, [OperandSpec("s1", "z", "k < 3", "g"), OperandSpec("s2", "z", "k > 0", "g", "k")])
    assert sorted((r.stream_id, r.identity, r.group_key) for r in got.where("group_key is not null").collect()) == [("s1", "x", "g"), ("s2", "x", "g")]
    assert got.where("group_key is null").count() == 1
    seg = extract.with_segments(spark.range(100), 8, "contiguous", F.col("id"))
    assert seg.select("segment_id").distinct().count() == 8
    with pytest.raises(ValueError):
        extract.with_segments(df, 2, "nothing")


def test_plan_has_no_python(spark, sf):
    li = tables.load_table(spark, sf, "lineitem").select("l_returnflag", F.col("l_orderkey").alias("identity"))
    plan = readouts.read_distinct(registers.build_registers(li, ["l_returnflag"]), ["l_returnflag"])._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "partial_max" in plan and "ReadSchema: struct<l_orderkey:bigint,l_returnflag:string>" in plan
