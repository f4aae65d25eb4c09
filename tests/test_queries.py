"""Every query against its SQL twin on the smoke tables; those without one must run."""

import glob
import os

import duckdb
import pytest
from support import SF_SMOKE

from navspark.plans import registry

QUERIES, ORACLE = registry.queries(), registry.oracle_sql()


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for p in glob.glob(f"{SF_SMOKE}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(p)[:-8]} AS SELECT * FROM '{p}'")
    return con


@pytest.mark.parametrize("name", sorted(QUERIES))
def test_query(spark, duck, name):
    df = QUERIES[name](spark, SF_SMOKE)
    cols = sorted(df.columns)
    got = sorted((tuple(r[c] for c in cols) for r in df.collect()), key=repr)
    if name not in ORACLE:
        assert got
        return
    r = duck.execute(ORACLE[name])
    have = [d[0] for d in r.description]
    assert sorted(have) == cols
    want = sorted((tuple(x[have.index(c)] for c in cols) for x in r.fetchall()), key=repr)
    assert got == want


def test_entry_names():
    import __spark_entry__ as e

    assert set(QUERIES) <= set(e.queries())
    assert set(e.oracle_sql()) <= set(e.queries())
