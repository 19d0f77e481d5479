"""Queries of this folder that SQL can express equal their twins."""

import glob
import os

import duckdb
import pytest

from binsketch.llm import queries


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_twin(spark, sf, name):
    con = duckdb.connect()
    for p in glob.glob(f"{sf}/*.parquet"):
        con.sql(f"CREATE VIEW {os.path.basename(p)[:-8]} AS SELECT * FROM read_parquet('{p}')")
    want, got = con.sql(queries.ORACLES[name]), queries.QUERIES[name](spark, sf)
    assert sorted(want.columns) == sorted(got.columns)
    rows = lambda r: sorted(map(str, r))
    assert rows(got.select(*want.columns).toPandas().astype(object).where(lambda d: d.notna(), None).itertuples(index=False, name=None)) == rows(want.df().astype(object).where(lambda d: d.notna(), None).itertuples(index=False, name=None))
