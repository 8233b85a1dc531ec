"""Every catalogued query against its SQL on the smallest tables."""

import duckdb
import pytest

from rowproduct import catalog

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return con


def norm(rows, cols):
    order = sorted(range(len(cols)), key=lambda k: cols[k])
    cell = lambda x: None if x is None else repr(round(x, 6) + 0.0) if isinstance(x, float) else str(x)
    return [cols[k] for k in order], sorted((tuple(cell(r[k]) for k in order) for r in rows), key=repr)


@pytest.mark.parametrize("name", sorted(catalog.QUERIES))
def test_query(spark, sf, duck, name):
    df = catalog.QUERIES[name](spark, sf)
    got = norm([tuple(r) for r in df.collect()], df.columns)
    if name not in catalog.ORACLES:
        assert got[1]
    else:  # may be empty on tables so small, if the SQL's result is
        cur = duck.execute(catalog.ORACLES[name])
        assert got == norm(cur.fetchall(), [c[0] for c in cur.description])


def test_entry_module_needs_no_session():
    import os
    import subprocess
    import sys

    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    code = "import __spark_entry__ as e; q, o = e.queries(), e.oracle_sql(); assert len(q) > 150 and set(o) <= set(q)"
    subprocess.run([sys.executable, "-c", code], cwd=root, check=True, timeout=120)


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() == 24214
