"""Every registered query that has a twin equals it on the smallest tables."""

import glob
import math
import os

import duckdb
import pytest

from binsketch import registry
from binsketch.session import ship

SLOW = {"accuracy_by_coding", "accuracy_by_method", "accuracy_grid", "quality_labels", "sql_learner", "loading_times", "training_times", "sketching_times", "stream_scored_points", "accuracy_news_grid", "accuracy_cost_grid", "preprocessing_ratio", "new_point_cost"}


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for p in glob.glob(f"{sf}/*.parquet"):
        con.sql(f"CREATE VIEW {os.path.basename(p)[:-8]} AS SELECT * FROM read_parquet('{p}')")
    return con


def plain(v):
    if v is None or isinstance(v, float) and math.isnan(v):
        return None
    if isinstance(v, bool):
        return v
    return round(float(v), 5) if isinstance(v, (int, float)) else str(v)


def table(columns, rows):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return sorted((tuple(plain(r[i]) for i in order) for r in rows), key=str)


@pytest.mark.parametrize("name", sorted(registry.oracles()))
def test_twin(spark, sf, duck, name):
    ship(spark)
    df = registry.queries()[name](spark, sf)
    want = duck.sql(registry.oracles()[name])
    assert sorted(df.columns) == sorted(want.columns)
    assert table(df.columns, [tuple(r) for r in df.collect()]) == table(want.columns, want.fetchall())


@pytest.mark.parametrize("name", sorted(set(registry.queries()) - set(registry.oracles()) - SLOW))
def test_runs(spark, sf, name):
    ship(spark)
    assert registry.queries()[name](spark, sf).count() > 0


def test_learners_agree(spark, sf):
    ship(spark)
    r = registry.queries()["sql_learner"](spark, sf).first()
    assert r.accuracy >= r.majority
