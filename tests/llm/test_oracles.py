"""Queries whose whole result SQL can state, against that SQL, and on planted rows."""

import duckdb
import pytest
from pyspark.sql import functions as F

from variety.llm.near_duplicates import near_duplicates
from variety.llm.embeddings import near_vectors
from variety.llm.oracles import ORACLE_SQL
from variety.llm.queries import QUERIES


def rows_of(df, got):
    cols = sorted(df.columns)
    names = [c[0] for c in got.description]
    assert cols == sorted(names)
    want = sorted(repr([r[names.index(c)] for c in cols]) for r in got.fetchall())
    return sorted(repr([r[c] for c in cols]) for r in df.collect()), want


@pytest.mark.parametrize("name", sorted(ORACLE_SQL))
def test_same_rows(spark, small, name):
    con = duckdb.connect()
    for t in ("documents", "embeddings", "pages"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{small}/{t}.parquet')")
    have, want = rows_of(QUERIES[name](spark, small), con.execute(ORACLE_SQL[name]))
    assert have == want


def test_vectors_with_links_and_odd_rows(spark):
    turn = [[1.0, 0.4 * i, 0.0, 0.0] for i in range(8)]
    odd = [None, [0.0] * 4, [None, 1.0, 0.0, 0.0], [float("nan"), 1.0, 0.0, 0.0], [1.0, 0.0, 0.0, 0.0], [0.0, 0.0, 1.0, 1e-9]]
    df = spark.createDataFrame(list(enumerate(turn + odd)), "vec_id long, embedding array<double>")
    con = duckdb.connect()
    con.execute("CREATE TABLE embeddings (vec_id BIGINT, embedding DOUBLE[])")
    con.executemany("INSERT INTO embeddings VALUES (?, ?)", list(enumerate(turn + odd)))
    have, want = rows_of(near_vectors(df), con.execute(ORACLE_SQL["op8_embedding_near_dedup"]))
    assert have == want and sum("False" in r for r in have) >= 3


def test_texts_with_links_and_odd_rows(spark):
    base = [f"w{i}" for i in range(60)]
    texts = [" ".join(base), " ".join(base).upper(), " ".join(base[1:]), " ".join([*base, "x", "y"]), "", None, " \t", "", "a b", "A  b", "one", " ".join(base[:30])]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    con = duckdb.connect()
    con.execute("CREATE TABLE documents (doc_id BIGINT, text VARCHAR)")
    con.executemany("INSERT INTO documents VALUES (?, ?)", list(enumerate(texts)))
    found = near_duplicates(df, k=3, percent=85).select("doc_id", F.col("n_shingles"), "component_id", "kept")
    have, want = rows_of(found, con.execute(ORACLE_SQL["op10_near_duplicates"]))
    assert have == want and sum("False" in r for r in have) >= 4
