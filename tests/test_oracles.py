"""Every query with SQL against DuckDB on the smallest tables."""

import math

import duckdb
import pytest

from patchflow.workloads import registry
from patchflow.workloads.surface import TABLES

SF = "/root/testdata/sf0.001"
KINDS = {"bigint": "BIGINT", "int": "INTEGER", "double": "DOUBLE", "string": "VARCHAR", "boolean": "BOOLEAN"}
SQL = registry.oracle_sql()


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return c


def plain(rows):
    def cell(v):
        if v is None or isinstance(v, float) and math.isnan(v):
            return "NULL"
        return repr(round(v, 6)) if isinstance(v, float) else str(v)

    return sorted(tuple(map(cell, r)) for r in rows)


@pytest.mark.parametrize("name", sorted(SQL))
def test_equals_oracle(spark, duck, name):
    df = registry.queries()[name](spark, SF)
    cols = sorted(df.columns)
    want = duck.sql(SQL[name])
    assert cols == sorted(want.columns)
    assert [KINDS[dict(df.dtypes)[c]] for c in cols] == [str(dict(zip(want.columns, want.types))[c]) for c in cols]
    quoted = ",".join(f'"{c}"' for c in cols)
    assert plain(map(tuple, df.select(*cols).collect())) == plain(duck.sql(f"select {quoted} from ({SQL[name]})").fetchall())


def test_entry_imports():
    import __spark_entry__

    assert set(registry.queries()) <= set(__spark_entry__.queries())
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
