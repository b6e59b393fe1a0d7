"""Every query with an SQL twin against DuckDB on the smallest tables."""

import glob
import os

import duckdb
import pytest

from relmodel import all_queries as Q


@pytest.fixture(scope="module")
def duck(sf):
    c = duckdb.connect()
    for p in glob.glob(f"{sf}/*.parquet"):
        c.execute(f"CREATE VIEW {os.path.basename(p)[:-8]} AS SELECT * FROM read_parquet('{p}')")
    return c


def plain(df):
    cols = sorted(df.columns)
    show = lambda v: "null" if v is None or v != v else repr(float(v)) if isinstance(v, (int, float)) or hasattr(v, "dtype") and v.dtype.kind in "iuf" else str(v)
    return cols, sorted(tuple(show(v) for v in row) for row in df[cols].astype(object).itertuples(index=False))


@pytest.mark.parametrize("name", sorted(Q.SQL))
def test_twin(spark, sf, duck, name):
    got, want = plain(Q.QUERIES[name](spark, sf).toPandas()), plain(duck.sql(Q.SQL[name]).df())
    assert got[0] == want[0] and len(got[1]) == len(want[1])
    assert got[1] == want[1]


def test_entry(spark, sf):
    out = Q.entry(spark, sf)
    assert out.count() > 0 and out.columns[:2] == ["node_id", "y"]
