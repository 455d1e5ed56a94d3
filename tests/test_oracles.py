"""Every query with SQL against DuckDB on the smallest tables. Training workloads are tested on their own."""

import math
import os

import duckdb
import pytest

from deltahop import queries

QUERIES, ORACLES = queries.load()
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        path = f"{sf}/{t}.parquet"
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{path + '/*.parquet' if os.path.isdir(path) else path}'")
    return con


def canon(rows, columns):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    value = lambda v: None if isinstance(v, float) and math.isnan(v) else v
    return sorted((tuple(value(r[i]) for i in order) for r in rows), key=repr)


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_query_equals_sql(spark, sf, duck, name):
    df = QUERIES[name](spark, sf)
    result = duck.execute(ORACLES[name])
    columns = [c[0] for c in result.description]
    assert sorted(columns) == sorted(df.columns)
    assert canon([tuple(r) for r in df.collect()], df.columns) == canon(result.fetchall(), columns)


def test_registry_is_consistent():
    assert set(ORACLES) <= set(QUERIES)
    assert len(QUERIES) > 150


def test_approximate_counts_are_close(spark, sf):
    for r in QUERIES["agg_approx_nbrs"](spark, sf).collect():
        assert abs(r.approx - r.exact) <= 0.06 * r.exact and abs(r.sketch - r.exact) <= 0.06 * r.exact


@pytest.mark.parametrize("name", "assign_deferred assign_eager assign_two_level_eager autotune_c autotune_l autotune_overheads autotune_p bias_trend_fit bias_uniform_deferred bias_uniform_eager cost_per_epoch epoch_cost_model".split())
def test_query_needs_its_tables(spark, tmp_path, name):
    """These once answered without any table."""
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        QUERIES[name](spark, str(tmp_path)).collect()
