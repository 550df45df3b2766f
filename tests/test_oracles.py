"""Queries against the same said in SQL, on the smallest tables."""

import math

import duckdb
import pytest

from variety.queries import ORACLE_SQL, QUERIES

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def sql(small):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{small}/{t}.parquet')")
    return con


def plain(v):
    if isinstance(v, float):
        return None if math.isnan(v) else round(v, 3) + 0.0
    return float(round(v, 3)) if hasattr(v, "as_tuple") else v


@pytest.mark.parametrize("name", sorted(ORACLE_SQL))
def test_same_rows(spark, small, sql, name):
    df = QUERIES[name](spark, small)
    got = sql.execute(ORACLE_SQL[name])
    cols = [c[0] for c in got.description]
    assert sorted(cols) == sorted(df.columns)
    want = sorted(repr([plain(r[cols.index(c)]) for c in sorted(cols)]) for r in got.fetchall())
    have = sorted(repr([plain(r[c]) for c in sorted(cols)]) for r in df.collect())
    assert have == want
