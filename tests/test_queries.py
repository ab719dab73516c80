"""Every query with SQL against DuckDB on the smallest tables."""

import math
import os

import duckdb
import pytest

from bitplane import workloads

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="session")
def duck(small):
    con = duckdb.connect()
    for t in TABLES:
        p = f"{small}/{t}.parquet"
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{p + '/*.parquet' if os.path.isdir(p) else p}')")
    return con


def plain(x):
    if isinstance(x, float):
        return "nan" if math.isnan(x) else round(x, 6)
    return str(x) if type(x).__name__ in ("datetime", "Decimal") else x


def rows(names, data):
    order = sorted(range(len(names)), key=lambda i: names[i])
    return sorted((tuple(plain(r[i]) for i in order) for r in data), key=repr)


@pytest.mark.parametrize("name", sorted(workloads.QUERIES))
def test_query(spark, duck, small, name):
    df = workloads.QUERIES[name](spark, small)
    got = df.collect()
    if name in workloads.ORACLES:
        cur = duck.execute(workloads.ORACLES[name])
        cols = [c[0] for c in cur.description]
        assert sorted(cols) == sorted(df.columns)
        assert rows(df.columns, got) == rows(cols, cur.fetchall())


@pytest.mark.parametrize("name", [
    "m_block_bytes",
    "m_break_even",
    "m_cluster_seconds",
    "m_compound_cost",
    "m_compression",
    "m_economics",
    "m_passes",
])
def test_measures_read_their_table(spark, small, name):
    assert [f.rsplit("/", 1)[1] for f in workloads.QUERIES[name](spark, small).inputFiles()] == ["lineitem.parquet"]


def test_cardinality_beyond_literals(spark, small, tmp_path):
    """More names than a dictionary of literals may hold."""
    spark.read.parquet(f"{small}/part.parquet").write.parquet(f"{tmp_path}/part.parquet")
    spark.range(70_000).selectExpr("id AS c_custkey", "concat('Customer#', id) AS c_name").write.parquet(f"{tmp_path}/customer.parquet")
    con = duckdb.connect()
    for t in ("part", "customer"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{tmp_path}/{t}.parquet/*.parquet')")
    df = workloads.QUERIES["dictionary_cardinality"](spark, str(tmp_path))
    cur = con.execute(workloads.ORACLES["dictionary_cardinality"])
    assert rows(df.columns, df.collect()) == rows([c[0] for c in cur.description], cur.fetchall())


def test_entry(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).first()[0] > 0
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
