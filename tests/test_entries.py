import __spark_entry__ as entries


def test_every_sql_has_its_query():
    queries, sql = entries.queries(), entries.oracle_sql()
    assert len(queries) > 150 and set(sql) <= set(queries)


def test_flagship(spark):
    got = entries.entry(spark)
    assert got.columns == ["x1", "x2", "x3", "mass"] and got.count() > 0
