"""Every registered query runs at the smallest size; those with SQL equal it."""

import duckdb
import pytest

import __spark_entry__ as entry
from idagg import workloads

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SLOW = {"hll_million", "stat_contrasts", "arm_code_generated_sql", "hll_error_vs_reference", "hll_million_seeds_exact", "stat_campaign", "stat_campaign_contrasts"}  # test_campaign.py runs the latter's parts


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    con.sql("SET TimeZone = 'UTC'")
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


def rows(df):
    cols = sorted(df.columns)

    def norm(v):
        if v is None or v != v:
            return None
        if isinstance(v, float):
            return f"{v:.9g}"
        return str(v)[:10] if hasattr(v, "year") else str(v)

    return cols, sorted((tuple(norm(v) for v in r) for r in df[cols].astype(object).itertuples(index=False)), key=str)


# what needs more rows than the smallest size has to hold
LARGE_ONLY = {"hll_length_prefixes", "x_frequency", "arm_budgeted_relations", "rel_matrix", "rel_grouped", "rel_containment", "builtin_theta_overlap"}


@pytest.mark.parametrize("name", [n for n in workloads.queries() if n not in SLOW | LARGE_ONLY])
def test_query(spark, sf, duck, name):
    got = workloads.queries()[name](spark, sf).toPandas()
    if name in workloads.oracle_sql():
        assert rows(got) == rows(duck.sql(workloads.oracle_sql()[name]).df())


@pytest.mark.parametrize("name", sorted(LARGE_ONLY))
def test_query_on_more_rows(spark, name):
    sf = "/root/testdata/sf0.01"
    con = duckdb.connect()
    con.sql("SET TimeZone = 'UTC'")
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    assert rows(workloads.queries()[name](spark, sf).toPandas()) == rows(con.sql(workloads.oracle_sql()[name]).df())


def test_entry(spark):
    assert entry.entry(spark).count() > 0
    assert set(workloads.queries()) <= set(entry.queries())
    assert set(workloads.oracle_sql()) <= set(workloads.queries())
