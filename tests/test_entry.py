import __spark_entry__ as entry


def test_catalogue():
    queries, sql = entry.queries(), entry.oracle_sql()
    assert set(sql) <= set(queries) and len(queries) > 120


def test_flagship(spark, small):
    assert entry.entry(spark).count() > 0
