"""Every query with SQL, against DuckDB on the smallest tables."""

import datetime
import math

import duckdb
import pytest

from spark_curation import comparison, comparison_sql, oracles, surfaces, surfaces_sql, workloads
from spark_curation.io import TABLES
from tests.conftest import DATA

SQL = oracles.SQL | comparison_sql.SQL | surfaces_sql.SQL
CHECKED = sorted(set(workloads.QUERIES) & set(SQL))
assert comparison and surfaces  # they register queries


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{DATA}/{t}.parquet'")
    return c


def plain(x):
    if isinstance(x, float):
        return "nan" if math.isnan(x) else repr(round(x, 6) + 0.0)
    if isinstance(x, datetime.datetime):
        return x.replace(tzinfo=None).isoformat()
    return repr(x)


@pytest.mark.parametrize("name", CHECKED)
def test_query_equals_sql(spark, duck, name):
    df = workloads.QUERIES[name](spark, DATA)
    cols = sorted(df.columns)
    got = sorted([plain(r[c]) for c in cols] for r in df.collect())
    rel = duck.sql(SQL[name])
    names = rel.columns
    assert sorted(names) == cols
    assert got == sorted([plain(r[names.index(c)]) for c in cols] for r in rel.fetchall())


def test_most_queries_have_sql():
    assert len(CHECKED) >= 0.7 * len(workloads.QUERIES)
