"""Every engine query with SQL equals DuckDB on the smallest tables."""

import os

import duckdb
import pytest

from stablecf import registry

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    c.sql("SET TimeZone='UTC'")
    for t in os.listdir(SF):
        if t.endswith(".parquet"):
            c.sql(f"create view {t[:-8]} as select * from '{SF}/{t}'")
    return c


def rows(values, columns):
    place = [columns.index(c) for c in sorted(columns)]
    return sorted(tuple(repr(v[i]) for i in place) for v in values)


@pytest.mark.parametrize("name", sorted(registry.oracle_sql()))
def test_query_equals_sql(spark, duck, name):
    got = registry.queries()[name](spark, SF)
    want = duck.execute(registry.oracle_sql()[name])
    columns = [c[0] for c in want.description]
    assert sorted(columns) == sorted(got.columns)
    assert rows(got.collect(), got.columns) == rows(want.fetchall(), columns)


def test_feature_memory_follows_the_vectors(spark, tmp_path):
    """Its axes are those of the given table: vectors of other lengths, empty ones and nulls."""
    spark.createDataFrame([(1, [0.5] * 3), (2, [0.5] * 5), (3, []), (4, None)], "vec_id long, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    got = sorted(tuple(r) for r in registry.queries()["q_feature_memory"](spark, str(tmp_path)).collect())
    assert got == [(d, d + 2, 2 * d + 1, 1 + d + d * (d + 1) // 2) for d in range(1, 6)]
    con = duckdb.connect()
    con.sql(f"create view embeddings as select * from '{tmp_path}/embeddings.parquet/*.parquet'")
    assert got == sorted(con.sql(registry.oracle_sql()["q_feature_memory"]).fetchall())
