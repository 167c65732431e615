import __spark_entry__ as entry


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert len(entry.queries()) > 80


def test_entry(spark):
    got = entry.entry(spark)
    assert got.count() == 38 and "score" in got.columns
