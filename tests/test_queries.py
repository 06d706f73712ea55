"""Every query against its DuckDB twin on the smallest tables."""

import glob
import math
from pathlib import Path

import duckdb
import pytest

from histreplay import catalog

SF = "/root/testdata/sf0.001"
SLOW = {"w05_latency", "w13_ne_model"}
QUERIES, SQL = catalog.queries(), catalog.oracle_sql()


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for p in glob.glob(f"{SF}/*.parquet"):
        con.execute(f"CREATE VIEW {Path(p).stem} AS SELECT * FROM '{p}'")
    return con


def rows(names, table):
    at = sorted(range(len(names)), key=lambda k: names[k])

    def plain(x):
        if x is None or isinstance(x, (str, bool)):
            return str(x)
        return f"{0.0 if math.isclose(x, 0, abs_tol=1e-12) else float(x):.9g}"

    return sorted(tuple(plain(r[k]) for k in at) for r in table)


@pytest.mark.parametrize("name", sorted(set(QUERIES) - SLOW))
def test_query(spark, duck, name):
    got = QUERIES[name](spark, SF)
    found = rows(got.columns, got.collect())
    if name in SQL:
        rel = duck.sql(SQL[name])
        assert sorted(got.columns) == sorted(rel.columns)
        assert found == rows(rel.columns, rel.fetchall())
    else:
        assert found


def test_entry(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())
