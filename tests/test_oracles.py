"""Queries against the same in SQL, on the smallest tables."""

import math

import duckdb
import pytest

import __spark_entry__ as entry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
ORACLES = entry.oracle_sql()


@pytest.fixture(scope="module")
def database(sf_dir):
    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf_dir}/{t}.parquet')")
    return con


def text(v):
    if v is None or isinstance(v, (bool, str)):
        return str(v)
    if isinstance(v, float) or hasattr(v, "is_finite"):
        return "nan" if math.isnan(v) else f"{float(v) + 0.0:.9g}"
    return v.isoformat() if hasattr(v, "isoformat") else str(v)


def test_names_agree():
    assert set(ORACLES) <= set(entry.queries())


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_query_equals_sql(spark, database, sf_dir, name):
    df = entry.queries()[name](spark, sf_dir)
    names = sorted(df.columns)
    got = sorted(tuple(text(r[c]) for c in names) for r in df.collect())
    rel = database.sql(ORACLES[name])
    at = [rel.columns.index(c) for c in names]
    assert sorted(rel.columns) == names
    assert got == sorted(tuple(text(r[i]) for i in at) for r in rel.fetchall())


def test_entry(spark):
    df = entry.entry(spark)
    assert df.columns == ["query_id", "rank", "series_id", "distance"] and df.count() == 100


@pytest.mark.parametrize("name", ["regr_build", "operation_counts", "operation_counters"])
def test_results_come_from_a_table(spark, tmp_path, name):
    """On sf0.01: the smallest walks have no full root cell."""
    every = "/root/testdata/sf0.01"
    spark.read.parquet(f"{every}/lineitem.parquet").where("l_suppkey <= 3").write.parquet(f"{tmp_path}/lineitem.parquet")
    few, all_ = (sorted(map(str, entry.queries()[name](spark, d).collect())) for d in (str(tmp_path), every))
    assert all_ and few != all_
