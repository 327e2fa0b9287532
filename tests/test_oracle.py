"""Every registered query with SQL equals DuckDB on the small tables."""

import math
import os

import duckdb
import pytest

from edgecsr.queries import oracle_sql, queries


@pytest.fixture(scope="module")
def duck(sf):
    c = duckdb.connect()
    c.execute("set timezone='UTC'")
    for f in os.listdir(sf):
        p = f"{sf}/{f}"
        c.execute(f"create view {f.split('.')[0]} as select * from '{p if os.path.isfile(p) else p + '/*.parquet'}'")
    return c


def _norm(v):
    if isinstance(v, float):
        return None if math.isnan(v) else round(v, 9)
    return round(float(v), 9) if type(v).__name__ == "Decimal" else v


@pytest.mark.parametrize("name", sorted(oracle_sql()))
def test_query_equals_sql(spark, sf, duck, name):
    df = queries()[name](spark, sf)
    cols = sorted(df.columns)
    got = sorted((tuple(_norm(r[c]) for c in cols) for r in df.collect()), key=repr)
    found = duck.execute(oracle_sql()[name])
    names = [d[0] for d in found.description]
    assert sorted(names) == cols
    want = sorted((tuple(_norm(row[names.index(c)]) for c in cols) for row in found.fetchall()), key=repr)
    assert got == want


def test_contract():
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())


def test_entry_can_be_imported_before_there_is_a_session():
    import subprocess
    import sys

    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    code = "import __spark_entry__ as e; assert len(e.queries()) > 100 and e.oracle_sql()"
    subprocess.run([sys.executable, "-c", code], cwd=root, check=True, timeout=120)
