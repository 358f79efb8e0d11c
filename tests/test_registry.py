"""Every registered query that has an SQL twin against DuckDB on the smallest tables."""

import decimal
import os

import duckdb
import numpy as np
import pytest

from adapterlab import registry, surrounding  # noqa: F401
from adapterlab.sources.tables import NAMES


@pytest.fixture(scope="module")
def duck(sf_dir):
    con = duckdb.connect()
    con.execute("SET timezone = 'UTC'")
    for t in NAMES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{os.path.join(sf_dir, t)}.parquet')")
    return con


def plain(v):
    if isinstance(v, (float, np.floating, decimal.Decimal)):
        return None if v != v else round(float(v), 6)
    if isinstance(v, (bool, np.bool_)):
        return bool(v)
    return int(v) if isinstance(v, (int, np.integer)) else v


def table(rows, columns):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return sorted(repr(tuple(float(x) if isinstance(x := plain(r[i]), (int, float)) and not isinstance(x, bool) else x for i in order)) for r in rows)


@pytest.mark.parametrize("name", sorted(registry.SQL))
def test_query_equals_its_sql(spark, duck, sf_dir, name):
    df = registry.QUERIES[name](spark, sf_dir)
    got = table([tuple(r) for r in df.collect()], df.columns)
    found = duck.execute(registry.SQL[name])
    columns = [d[0] for d in found.description]
    assert sorted(df.columns) == sorted(columns)
    assert got == table(found.fetchall(), columns)


def test_entry_points_without_a_query_running():
    import __spark_entry__ as entry

    found, sql = entry.queries(), entry.oracle_sql()
    assert set(sql) <= set(found) and set(registry.QUERIES) <= set(found)
    assert "flagship_schedule" in found
