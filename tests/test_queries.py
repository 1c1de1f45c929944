"""Every registered query against its SQL twin."""

import duckdb
import pytest

from freqsketch.workloads import ORACLES, QUERIES

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


def normal(df):
    df = df[sorted(df.columns)].copy()
    for c in df.columns:
        if str(df[c].dtype).startswith("datetime"):
            df[c] = df[c].astype("datetime64[us]").astype(str)
    return df.sort_values(list(df.columns), na_position="first").reset_index(drop=True)


@pytest.mark.parametrize("name", sorted(QUERIES))
def test_query(spark, sf, duck, name):
    got = QUERIES[name](spark, sf).toPandas()
    if name not in ORACLES:
        assert len(got)
        return
    a, b = normal(got), normal(duck.execute(ORACLES[name]).fetchdf())
    assert list(a.columns) == list(b.columns) and len(a) == len(b)
    for c in a.columns:
        assert ((a[c] == b[c]) | (a[c].isna() & b[c].isna())).all(), c


def test_entry_point(spark):
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())
    assert e.entry(spark).where("excess < 0").count() == 0


#: Queries that once made their data up.
READS = ["hash_table", "spec_catalog", "lookup_cost", "memory_model", "schedule_makespan", "static_schedule", "dynamic_schedule", "rebalance_step", "f2s_convergence", "f2s_by_phase", "f2s_frozen", "rebalance_trace"]


@pytest.mark.parametrize("name", READS)
def test_query_reads_a_table(spark, tmp_path, name):
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        QUERIES[name](spark, str(tmp_path)).collect()
