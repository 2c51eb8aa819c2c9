import __spark_entry__ as entry


def test_entry_and_registry(spark):
    df = entry.entry(spark)
    assert df.columns == ["node", "a", "b", "c"] and df.count() >= 0
    assert set(entry.oracle_sql()) <= set(entry.queries())
