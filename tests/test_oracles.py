"""Every registered query of the graph methods runs at the smallest scale; those with SQL agree with it."""

import math

import duckdb
import pytest

import provgraph.coverage  # noqa: F401  its queries register themselves
from provgraph import queries

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SLOW = {"acyclic_audit_before_after"}


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return con


def plain(v):
    if isinstance(v, float):
        return None if math.isnan(v) else round(v, 6)
    return float(v) if hasattr(v, "as_tuple") else v


@pytest.mark.parametrize("name", sorted(set(queries.QUERIES) - SLOW))
def test_query(spark, duck, name):
    df = queries.QUERIES[name](spark, SF)
    cols = sorted(df.columns)
    got = sorted((tuple(plain(r[c]) for c in cols) for r in df.collect()), key=repr)
    if name in queries.ORACLES:
        r = duck.execute(queries.ORACLES[name])
        have = [d[0] for d in r.description]
        assert sorted(have) == cols
        want = sorted((tuple(plain(x[have.index(c)]) for c in cols) for x in r.fetchall()), key=repr)
        assert got == want


def test_entry(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() > 0
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
