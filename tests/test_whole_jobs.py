"""Queries that run an experiment at its full numbers."""

import hashlib
import inspect

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from idagg import workloads
from idagg.operators import learned
from idagg.plans import stats, tasks
from idagg.queries import evaluation
from idagg.sources.generated import distinct_streams, identity_streams


def test_code_subset_is_whole(sf):
    """The code arm's subset has all its tasks and each window and operator; test_query holds the query's rows against this SQL."""
    con = duckdb.connect()
    for t in ("events", "lineitem", "orders"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    got = con.sql(workloads.oracle_sql()["arm_code_all_tasks"]).df()
    every = con.sql("WITH " + tasks.TASK_SQL.strip() + " SELECT DISTINCT window_id, operator FROM tasks").fetchall()
    assert len(got) == tasks.CODE_TASKS == 1200 and got.task_id.is_unique
    assert {tuple(x.rsplit("/", 2)[:2]) for x in got.task_id} == set(every) and len(every) > 1000


@pytest.mark.parametrize("kind", [learned.SetEncoder, learned.SumPoolEncoder])
def test_length_errors_brute_force(spark, kind):
    """A small fixture: the encoder fed record by record, and counts from Python sets."""
    e = kind.create(3)
    e.mean = np.full(learned.STATE, 0.1)
    rows = identity_streams(spark, 5, 1_500, 100, 400, 7).toPandas()
    err = []
    for _, g in rows.groupby("stream_no"):
        n = g.identity.nunique()
        err.append(abs(float(e.decode(e.partial_state(g.identity.to_numpy()))[0]) - n) / n)
    got = evaluation.length_errors(spark, e, 5, 1_500, 100, 400).collect()
    assert len(got) == 1 and got[0].n == 5 and got[0].length == 1_500
    assert got[0].encoder_median == pytest.approx(np.median(err), rel=1e-6) and got[0].hll_median < 4 * 1.04 / 2048**0.5


def test_lengths_are_whole(spark, sf):
    got = {r.length: r for r in workloads.queries()["enc_vs_hll_error"](spark, sf).collect()}
    assert set(got) == {8_000, 50_000, 200_000}
    for r in got.values():
        assert r.n == 100 and 0.005 < r.hll_median < 0.025 and r.encoder_median > r.hll_median
    print("LENGTHS", sorted(got.items()))


def test_prefixes_are_whole(spark, tmp_path):
    spark.range(210_000).selectExpr("id div 4 as l_orderkey", "cast(id % 4 as int) as l_linenumber", "pmod(xxhash64(id), 30000) as l_partkey", "id % 7 as l_suppkey").write.parquet(f"{tmp_path}/lineitem.parquet")
    ids = [r.k for r in spark.range(210_000).selectExpr("id", "pmod(xxhash64(id), 30000) as k").orderBy("id").collect()]
    got = {r.length: r for r in workloads.queries()["hll_length_prefixes_all"](spark, str(tmp_path)).collect()}
    assert set(got) == {8_000, 50_000, 200_000}
    for n, r in got.items():
        assert r.records == n and r.exact == len(set(ids[:n])) and abs(r.estimate - r.exact) < 4 * 1.04 / 2048**0.5 * r.exact


def test_pieces_make_whole_sets(spark):
    d = distinct_streams(spark, [3, 600_000], 2)
    got = {(r.cardinality, r.rep): (r.n, r.u) for r in d.groupBy("cardinality", "rep").agg(F.count("*").alias("n"), F.count_distinct("identity").alias("u")).collect()}
    assert got == {(n, k): (n, n) for n in (3, 600_000) for k in (0, 1)}
    assert d.where("cardinality = 3 and rep = 1").select("identity").toPandas().identity.sort_values().tolist() == [f"u0-3-1-{k}" for k in range(3)]


def test_error_grid_and_million_are_whole(spark, sf):
    got = {r.p: r for r in workloads.queries()["hll_error_grid"](spark, "/root/testdata/sf0.1").collect()}
    print("GRID", sorted(got.items()))
    ids = duckdb.sql("SELECT DISTINCT l_orderkey || '-' || l_linenumber FROM '/root/testdata/sf0.1/lineitem.parquet'").fetchall()
    u = [int(hashlib.md5(f"77:{z}".encode()).hexdigest()[:16], 16) & (1 << 62) - 1 for z, in ids]
    there = {(next(k for k, b in enumerate((1, 11, 111, 1111, 11111)) if x % 11111 < b), x // 11111 % 48) for x in u}
    assert len({s for s in there if s[0]}) == 192
    streams = {8: 240, 9: 200, 10: 160, 11: 160, 12: 120, 13: 120}
    assert {p: r.n for p, r in got.items()} == {p: sum(rep < n // 5 for _, rep in there) for p, n in streams.items()}
    m = workloads.queries()["hll_million_seeds"](spark, sf).first()
    print("MILLION", m)
    assert m.n == 20 and m.mean_relerr <= 0.025
    for r in got.values():  # most streams of this table are too small for the law of the large budgets
        assert 0 < r.mean_relerr <= r.rms_relerr < 1.3 * r.reference


@pytest.mark.parametrize("name, test, draws", [
    ("stat_cluster_bootstrap", "cluster_bootstrap", 10_000), ("stat_bootstrap_streams", "cluster_bootstrap", 10_000),
    ("stat_sign_flip", "sign_flip_test", 100_000), ("stat_contrasts", "sign_flip_test", 100_000)])
def test_draws_are_whole(spark, sf, monkeypatch, name, test, draws):
    """Registered statistics use the full number of draws."""
    real, used = getattr(stats, test), []

    def noted(*args, **named):
        call = inspect.signature(real).bind(*args, **named)
        call.apply_defaults()
        used.append(call.arguments["draws"])
        return real(*args, **named)

    monkeypatch.setattr(stats, test, noted)
    got = workloads.queries()[name](spark, sf).toPandas()
    assert len(got) and set(used) == {draws}
    if name == "stat_contrasts":
        print("CONTRASTS", got.p.min(), got.to_dict("records"))
