"""Results that grow with the records stay off the driver, and experiments read given tables."""

import hashlib
import math
from collections import Counter

import duckdb
import pytest
from pyspark.sql import functions as F

from idagg import workloads
from idagg.functions.hashing import index_rank
from idagg.operators import learned, readouts, registers
from idagg.queries import core
from idagg.sources.dealt import dealt_streams


def plan_of(df):
    return df._jdf.queryExecution().optimizedPlan().toString()


def test_sessions_stay_off_the_driver(spark, tmp_path):
    """Every event a session of its own but two, and the last of a user still open: rows come from files, not from the driver's memory."""
    rows = [(k, k % 3, k * 7_200) for k in range(90)] + [(90, 0, 60), (91, 1, 400_000)] + [(92, 9, 2_000_000)]
    e = spark.createDataFrame(rows, "event_id long, user_id long, t long").select("event_id", F.timestamp_seconds("t").alias("ts"), "user_id", F.lit("view").alias("event_type"))
    e.coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    got = workloads.queries()["stream_session"](spark, str(tmp_path))
    assert "MemoryPlan" not in plan_of(got) and "LocalRelation" not in plan_of(got)
    assert {r.identity: (r.sessions, r.events) for r in got.collect()} == {"0": (30, 31), "1": (31, 31), "2": (30, 30)}


def test_merge_tree_of_a_table(spark, tmp_path):
    """One segment is empty and one is large; the root has every record."""
    keys = [k for k in range(512) if k % 256 != 7] + [5] * 40 + [-1, None]
    spark.createDataFrame([(k,) for k in keys], "l_orderkey long").write.parquet(f"{tmp_path}/lineitem.parquet")
    got = {r.k: (r.parts, r.largest, r.records) for r in workloads.queries()["op_recursive_cte"](spark, str(tmp_path)).collect()}
    for k in range(9):
        per = Counter(x % 256 >> (8 - k) for x in keys if x is not None)
        assert got[k] == (len(per), max(per.values()), 551)
    assert len(got) == 9


def test_guard_on_stored_states(spark, tmp_path):
    """States of a table: only those of the same descriptor are read, and they hold the table's identities."""
    spark.range(3_000).selectExpr("id as o_orderkey", "id % 700 as o_custkey").write.parquet(f"{tmp_path}/orders.parquet")
    got = {r.differs: (r.refused, r.estimate) for r in workloads.queries()["hll_incompatible_guard"](spark, str(tmp_path)).collect()}
    assert got.pop("same") == (False, pytest.approx(700, rel=0.06))
    assert got == dict.fromkeys(("hash", "identity", "registers", "seed"), (True, None))


def test_counterexample_in_a_table(spark, tmp_path):
    rows = [(k % 3, float(k * k % 37)) for k in range(200)] + [(9, 4.0)]
    spark.createDataFrame([(f"t{t}", v) for t, v in rows] + [("t0", None)], "event_type string, value double").write.parquet(f"{tmp_path}/events.parquet")
    got = {(r.event_type, r.context): (r.alone, r.followed) for r in workloads.queries()["att_counterexample"](spark, str(tmp_path)).collect()}
    assert len(got) == 8
    for t in (0, 1, 2, 9):
        v = [x for k, x in rows if k == t]
        w = [math.exp((x - max(v)) / 100) for x in v]
        num, den = sum(a * b for a, b in zip(w, v, strict=True)), sum(w)
        assert got[f"t{t}", "x"] == pytest.approx((num / den, num / (den + 1)), abs=1e-6)
        assert got[f"t{t}", "y"] == pytest.approx((num / den, num / den / 2), abs=1e-6)


def test_encoder_states_of_a_table_add_up(spark, tmp_path, monkeypatch):
    """Names with the separator, repeats, a null; and segments that lose records are noticed."""
    rows = [(k, k * k % 50, f"a:{k % 3}") for k in range(400)] + [(400, None, "b"), (401, 1, None)]
    spark.createDataFrame(rows, "event_id long, user_id long, event_type string").write.parquet(f"{tmp_path}/events.parquet")
    run = lambda: tuple(workloads.queries()["enc_partial_merge_consistency"](spark, str(tmp_path)).first())
    assert run() == (3, True)
    real = learned.encode_states
    monkeypatch.setattr(learned, "encode_states", lambda r, key, e: real(r.where("identity <> '4'") if key == "part" else r, key, e))
    assert run() == (3, False)


def test_budgets_from_the_largest(spark):
    """Registers of a smaller budget, from those of the largest, equal those built from the identities; every rank is tried."""
    hs = [(1 << 63 | 1 << k) - (1 << 64) for k in range(63)] + [1 << k for k in range(63)] + [0, -1]
    df = spark.createDataFrame([(h,) for h in hs], "h long")
    for p in (8, 12):
        one = df.select("h", *(c.alias(n) for c, n in zip(index_rank(F.col("h"), 13), "jr", strict=True)))
        two = df.select("h", *index_rank(F.col("h"), p))
        assert {tuple(r) for r in one.select("h", *registers.coarser(13 - p)).collect()} == {tuple(r) for r in two.collect()}


def test_every_identity_is_dealt_once(spark):
    r = spark.createDataFrame([(str(k % 5_000),) for k in range(9_000)] + [(None,)], "identity string")
    got = dealt_streams(r, [1, 10, 100], 4).collect()
    assert sorted(x.identity for x in got) == sorted(map(str, range(5_000)))
    for x in got[::50]:
        u = int(hashlib.md5(f"77:{x.identity}".encode()).hexdigest()[:16], 16) & (1 << 62) - 1
        assert (x.size, x.rep) == (sum(u % 111 >= b for b in (1, 11)), u // 111 % 4)


def test_stream_errors_brute_force(spark, tmp_path):
    """A small grid of given streams against states built and read one by one."""
    sets = spark.createDataFrame([(k, rep, f"{k}-{rep}-{z}") for k, n in enumerate((50, 3_000)) for rep in range(3) for z in range(n + rep)], "size int, rep long, identity string")
    streams = {8: 6, 11: 4}
    got = {r.p: r for r in core.stream_errors(sets, 2, streams).collect()}
    for p, n in streams.items():
        one = sets.where(F.col("rep") < n // 2)
        est = readouts.read_distinct(registers.build_registers(one, ["size", "rep"], p, family="xx"), ["size", "rep"], p).collect()
        err = [abs(r.estimate - size) / size for r in est for size in [(50, 3_000)[r["size"]] + r.rep]]
        assert got[p].n == n == len(err) and got[p].mean_relerr == pytest.approx(sum(err) / n)
        assert got[p].rms_relerr == pytest.approx(math.sqrt(sum(x * x for x in err) / n))


@pytest.mark.parametrize("name", ["hll_error_grid_exact", "hll_error_vs_reference"])
def test_errors_follow_the_table(spark, tmp_path, name):
    """Another table, other numbers: repeats, nulls and all; equal to the SQL."""
    rows = [(k // 4, k % 4) for k in range(3_000)] * 2 + [(None, 1), (1, None)]
    spark.createDataFrame(rows, "l_orderkey long, l_linenumber int").coalesce(1).write.parquet(f"{tmp_path}/lineitem.parquet")
    con = duckdb.connect()
    con.sql(f"CREATE VIEW lineitem AS SELECT * FROM '{tmp_path}/lineitem.parquet/*.parquet'")
    got = workloads.queries()[name](spark, str(tmp_path)).collect()
    assert sorted(map(tuple, got)) == sorted(con.sql(workloads.oracle_sql()[name]).fetchall()) and 0 < got[0].n < 241


def test_half_errors_brute_force(spark):
    sets = spark.createDataFrame([(h, f"{h}{z}") for h, n in (("F", 5_000), ("O", 700)) for z in range(n)], "rep string, identity string")
    err = [abs(r.estimate - n) / n for k in range(3) for r in readouts.read_distinct(registers.build_registers(sets, ["rep"], seed=k, family="xx"), ["rep"]).collect() for n in [{"F": 5_000, "O": 700}[r.rep]]]
    got = core.half_errors(sets, 3).first()
    assert got.n == 6 and got.mean_relerr == pytest.approx(sum(err) / 6) and got.rms_relerr == pytest.approx(math.sqrt(sum(x * x for x in err) / 6))


def halves_table(spark, path):
    rows = [(k // 4, k % 4, "FO"[k % 3 == 0]) for k in range(3_000)] * 2 + [(None, 1, "F"), (1, None, "O"), (1, 1, None), (2, 2, "P")]
    spark.createDataFrame(rows, "l_orderkey long, l_linenumber int, l_linestatus string").coalesce(1).write.parquet(f"{path}/lineitem.parquet")
    return str(path)


def test_streams_follow_the_table(spark, tmp_path):
    """A table of three streams has three estimates a seed."""
    d = halves_table(spark, tmp_path)
    assert {(r.rep, r.n) for r in core.halves(spark, d).groupBy("rep").agg(F.count("*").alias("n")).collect()} == {("F", 2_000), ("O", 1_000), ("P", 1)}
    assert workloads.queries()["hll_million_seeds"](spark, d).first().n == 30


@pytest.mark.parametrize("name, shares, streams", [("hll_length_all", (4, 25, 100), 100), ("hll_length_extrapolation", (4, 25), 20)])
def test_lengths_follow_the_table(spark, tmp_path, name, shares, streams):
    """Every record with keys is in one stream, below zero too; equal to the SQL."""
    keys = [(k // 3 - 20, k % 3, k * 7 % 900 - 10) for k in range(6_000)] + [(None, 1, 1), (1, None, 1), (1, 1, None)]
    spark.createDataFrame(keys, "l_orderkey long, l_linenumber int, l_partkey long").coalesce(1).write.parquet(f"{tmp_path}/lineitem.parquet")
    con = duckdb.connect()
    con.sql(f"CREATE VIEW lineitem AS SELECT * FROM '{tmp_path}/lineitem.parquet/*.parquet'")
    got = workloads.queries()[name](spark, str(tmp_path)).collect()
    assert sorted(map(tuple, got)) == sorted(con.sql(workloads.oracle_sql()[name]).fetchall())
    r = core.length_streams(spark, str(tmp_path), shares, streams).toPandas()
    assert len(r) == 6_000 and {x.share: x.n for x in got} == r.groupby("share").stream_no.nunique().to_dict() == dict.fromkeys(shares, streams)
    assert (r.stream_no == r.identity % streams).all()


@pytest.mark.parametrize("name", ["hll_million_seeds_exact", "hll_million"])
def test_halves_equal_sql(spark, tmp_path, name):
    d = halves_table(spark, tmp_path)
    con = duckdb.connect()
    con.sql(f"CREATE VIEW lineitem AS SELECT * FROM '{d}/lineitem.parquet/*.parquet'")
    got = workloads.queries()[name](spark, d).collect()
    assert list(map(tuple, got)) == con.sql(workloads.oracle_sql()[name]).fetchall() and got[0].n % 3 == 0
