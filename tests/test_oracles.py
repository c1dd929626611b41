"""Every query with a DuckDB counterpart gives its rows, on the smallest tables."""

import os

import duckdb
import pytest

from entlink import registry

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return con


def plain(v):
    if v is None:
        return "null"
    if isinstance(v, float) or type(v).__name__ == "Decimal":
        return repr(round(float(v), 9) + 0.0)
    return str(v)


@pytest.mark.parametrize("name", sorted(registry.oracles()))
@pytest.mark.skipif(not os.path.isdir(SF), reason="given tables are missing")
def test_query_equals_sql(spark, duck, name):
    got = registry.queries()[name](spark, SF)
    found = duck.execute(registry.oracles()[name])
    columns = [d[0] for d in found.description]
    assert sorted(columns) == sorted(got.columns)
    want = sorted(tuple(plain(v) for v in r) for r in found.fetchall())
    assert sorted(tuple(plain(v) for v in r) for r in got.select(*columns).collect()) == want
